"""Shortest-path searches: many runs over one network.

A run has a source and may have a radius and targets. All strategies give the
same rows: ``broadcast`` ships a compact copy of a network of a checked size to
every task and solves runs side by side; ``disk`` ships runs near each other
only the edges that their radii can touch; ``frontier`` keeps the state in a table
and relaxes it in rounds, for networks of any size; ``delta`` does so bucket by
bucket, which relaxes fewer nodes twice. A frontier may stop at targets and may
be pruned towards a goal.

Weights are positive integers. The predecessor of a node is the least node on
any shortest path, so paths do not depend on the strategy.
"""

import heapq
import tempfile
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Edges up to which a network is shipped whole: 24 bytes each, 192 MB.
MAX_BROADCAST_EDGES = 8_000_000


def cut(df: DataFrame) -> DataFrame:
    """df from the shared checkpoint folder, without lineage."""
    spark, context = df.sparkSession, df.sparkSession.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None and not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="chargepath-"))
    return df.checkpoint(eager=True)


def cut_size(df: DataFrame) -> DataFrame:
    """Like ``cut``, but without Spark's estimate of the size, which every join
    of a loop multiplies until the number itself outgrows the driver."""
    spark, kept = df.sparkSession, cut(df)
    return DataFrame(spark._jsparkSession.createDataFrame(kept._jdf.toJavaRDD(), kept._jdf.schema()), spark)


def narrow(values: np.ndarray) -> np.ndarray:
    """The same numbers in 32 bits where they fit."""
    small = np.iinfo(np.int32)
    fits = not len(values) or (small.min <= values.min() and values.max() <= small.max)
    return values.astype(np.int32, copy=False) if fits else values


class Run:
    """Positions in an ascending run of whole numbers without gaps, with the ``get`` of a map."""

    def __init__(self, first: int, size: int) -> None:
        self.first, self.size = first, size

    def get(self, node: int) -> int | None:
        k = node - self.first
        return k if 0 <= k < self.size else None


def places_of(ids: np.ndarray):
    """Where each of the ascending ids stands; a map only where the ids have gaps, as it takes 100 bytes an id."""
    if len(ids) and int(ids[-1]) - int(ids[0]) + 1 == len(ids):
        return Run(int(ids[0]), len(ids))
    return {v: k for k, v in enumerate(ids.tolist())}


class Network:
    """Adjacency in three arrays: sorted sources, targets, weights; coordinates where they are known."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, weight: np.ndarray, places: tuple[np.ndarray, np.ndarray, np.ndarray] | None = None) -> None:
        src, dst, weight = map(narrow, (src, dst, weight))
        order = np.lexsort((weight, dst, src))
        own = src[order]
        first = np.flatnonzero(np.r_[True, own[1:] != own[:-1]][: len(own)])
        self.ids, self.lo, self.hi = own[first], narrow(first), narrow(np.r_[first[1:], len(src)][: len(first)])
        self.dst, self.weight = dst[order], weight[order]
        self.places, self.speed = None, 1.0
        if places is not None:
            node, x, y = places
            by = np.argsort(node)
            self.places = node[by], x[by], y[by]
            step = 1 << 18  # its temporary arrays stay small
            self.speed = max((self._top_speed(src[k : k + step], dst[k : k + step], weight[k : k + step]) for k in range(0, len(src), step)), default=0.0) * (1 + 1e-9) or 1.0
        self._at = self._spot = None

    def _top_speed(self, src: np.ndarray, dst: np.ndarray, weight: np.ndarray) -> float:
        """The most straight-line length that a unit of weight covers."""
        node, x, y = self.places
        if not len(node):
            return 0.0
        a, b = np.minimum(np.searchsorted(node, src), len(node) - 1), np.minimum(np.searchsorted(node, dst), len(node) - 1)
        known = (node[a] == src) & (node[b] == dst)
        speed = np.hypot(x[a] - x[b], y[a] - y[b])[known] / weight[known]
        return float(speed.max(initial=0.0))

    def out(self, node: int):
        """(target, weight) pairs of a node."""
        if self._at is None:
            self._at = places_of(self.ids)
        k = self._at.get(node)
        if k is None:
            return ()
        lo, hi = self.lo[k], self.hi[k]
        return zip(self.dst[lo:hi].tolist(), self.weight[lo:hi].tolist(), strict=True)

    def spot(self, node: int) -> tuple[float, float] | None:
        """(x, y) of a node; None where it is unknown."""
        if self.places is None:
            return None
        if self._spot is None:
            self._spot = places_of(self.places[0])
        k = self._spot.get(node)
        return None if k is None else (float(self.places[1][k]), float(self.places[2][k]))

    def goal(self, *targets: int):
        """A lower bound of the cost between a node and any of targets, by the box around them; None without coordinates."""
        spots = [self.spot(t) for t in targets]
        if None in spots:
            return None
        x0, y0 = (min(s[c] for s in spots) for c in (0, 1))
        x1, y1 = (max(s[c] for s in spots) for c in (0, 1))

        def bound(node: int) -> int:
            at = self.spot(node)
            if not at:
                return 0
            dx, dy = max(x0 - at[0], at[0] - x1, 0.0), max(y0 - at[1], at[1] - y1, 0.0)
            return int((dx * dx + dy * dy) ** 0.5 / self.speed)

        return bound

    def flipped(self) -> "Network":
        return Network(self.dst, np.repeat(self.ids, self.hi - self.lo), self.weight, self.places)


@dataclass
class Found:
    """What a search settled, and what it cost."""

    dist: dict
    pred: dict
    settled: int
    pushes: int


def bounded(net: Network, source: int, radius: int | None = None, targets=None, bound=None, history: bool = True) -> Found:
    """Dijkstra in maps of what it reaches only.

    It stops at the radius or once all targets are settled. ``bound`` gives a
    lower bound of what is left from a node and makes the search goal-directed;
    it then goes on through the ties of the target, so predecessors do not
    depend on the order in which equal keys leave the heap. Without ``history``
    no predecessors are kept.
    """
    dist, pred, done = {source: 0}, {source: None}, {}
    left = set(targets) if targets is not None else None
    heap, pushes, last = [(bound(source) if bound else 0, source)], 1, None
    while heap:
        key, u = heap[0]
        if left is not None and not left:
            if bound is None or key > last:
                break
        heapq.heappop(heap)
        if u in done:
            continue
        done[u] = d = dist[u]
        if left:
            left.discard(u)
            if not left:
                last = key
        for v, w in net.out(u):
            nd = d + w
            if radius is not None and nd > radius:
                continue
            old = dist.get(v)
            if old is None or nd < old:
                dist[v] = nd
                if history:
                    pred[v] = u
                heapq.heappush(heap, (nd + (bound(v) if bound else 0), v))
                pushes += 1
            elif history and nd == old and v != source and u < pred[v]:
                pred[v] = u
    return Found(done, pred, len(done), pushes)


FAR = np.iinfo(np.int64).max // 4


class Indexed:
    """Edges by position among all their nodes, for searches from many sources at once."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, weight: np.ndarray, extra=()) -> None:
        self.nodes = np.unique(np.concatenate([src, dst, np.asarray(extra, dtype=np.int64)]))
        a, b = np.searchsorted(self.nodes, src), np.searchsorted(self.nodes, dst)
        by = np.argsort(a, kind="stable")
        self.dst, self.weight = b[by], weight[by].astype(np.int64)
        self.lo = np.searchsorted(a[by], np.arange(len(self.nodes) + 1))
        self.degree = np.diff(self.lo)
        self.least = int(weight.min()) if len(weight) else 1

    def at(self, nodes) -> np.ndarray:
        return np.searchsorted(self.nodes, nodes)

    def rows_at_once(self, cells: int = 1 << 22) -> int:
        return max(1, cells // max(1, len(self.nodes)))

    def distances(self, sources: np.ndarray) -> np.ndarray:
        """A row a source (a position), a column a node; FAR where there is no path.

        Dijkstra for all sources side by side: whatever lies less than the least
        weight over the nearest open entry is settled in one step of arrays.
        """
        n = len(self.nodes)
        dist, nth = np.full(len(sources) * n, FAR), np.zeros(len(sources) * n, dtype=np.int32)
        held = np.zeros(len(dist), dtype=bool)
        open_ = np.arange(len(sources), dtype=np.int64) * n + sources
        dist[open_], held[open_] = 0, True
        while len(open_):
            d = dist[open_]
            ripe = d < d.min() + self.least
            now, d, open_ = open_[ripe], d[ripe], open_[~ripe]
            v = now % n
            many = self.degree[v]
            first = np.cumsum(many) - many
            edge = np.arange(int(many.sum())) + np.repeat(self.lo[v] - first, many)
            to, cost = np.repeat(now - v, many) + self.dst[edge], np.repeat(d, many) + self.weight[edge]
            better = cost < dist[to]
            to, cost = to[better], cost[better]
            new = to[~held[to]]
            while len(to):  # of several ways to one entry the last is written, so until none is better
                dist[to] = cost
                better = cost < dist[to]
                to, cost = to[better], cost[better]
            nth[new] = np.arange(len(new), dtype=np.int32)
            new = new[nth[new] == np.arange(len(new))]
            held[new] = True
            open_ = np.concatenate([open_, new])
        return dist.reshape(len(sources), n)


def dense(net: Network, source: int, n: int, radius: int | None = None) -> tuple[np.ndarray, int]:
    """The baseline that allots a vector over all nodes 0..n-1 for each run."""
    far = np.iinfo(np.int64).max
    dist, settled = np.full(n, far), np.zeros(n, dtype=bool)
    dist[source], heap = 0, [(0, source)]
    while heap:
        d, u = heapq.heappop(heap)
        if settled[u]:
            continue
        settled[u] = True
        for v, w in net.out(u):
            if d + w < dist[v] and (radius is None or d + w <= radius):
                dist[v] = d + w
                heapq.heappush(heap, (d + w, v))
    return dist, int(settled.sum())


def bidirectional(net: Network, back: Network, s: int, t: int, bound_s=None, bound_t=None) -> tuple[int | None, int]:
    """(cost, settled): two goal-directed searches that meet.

    The potentials of both sides are half the difference of the lower bounds,
    which keeps them consistent with each other.
    """
    if s == t:
        return 0, 1
    half = (lambda v: (bound_t(v) - bound_s(v)) / 2) if bound_s and bound_t else (lambda v: 0)
    dist, done, best = ({s: 0}, {t: 0}), (set(), set()), None
    heaps = ([(half(s), s)], [(-half(t), t)])
    while heaps[0] and heaps[1]:
        if best is not None and heaps[0][0][0] + heaps[1][0][0] >= best:
            break
        k = 0 if heaps[0][0][0] <= heaps[1][0][0] else 1
        _, u = heapq.heappop(heaps[k])
        if u in done[k]:
            continue
        done[k].add(u)
        for v, w in (net, back)[k].out(u):
            nd = dist[k][u] + w
            if nd < dist[k].get(v, nd + 1):
                dist[k][v] = nd
                heapq.heappush(heaps[k], (nd + (half(v), -half(v))[k], v))
            other = dist[1 - k].get(v)
            if other is not None and (best is None or dist[k][v] + other < best):
                best = dist[k][v] + other
    return best, len(done[0]) + len(done[1])


def trace(pred: dict, end: int) -> list[int]:
    out = [end]
    while pred[out[-1]] is not None:
        out.append(pred[out[-1]])
    return out[::-1]


def spread(runs: DataFrame, by: str, tasks: int | None = None) -> DataFrame:
    """runs dealt over ``tasks`` tasks, as many as the cluster asks for if not given.

    A run is a few bytes and much work, so the number is named: sized by bytes,
    all runs would go to one task.
    """
    spark = runs.sparkSession
    return runs.repartition(tasks or max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))), by)


def load(edges: DataFrame, nodes: DataFrame | None = None, max_edges: int | None = None):
    """A broadcast Network of edges, or None if there are more than max_edges: they are counted first."""
    most = MAX_BROADCAST_EDGES if max_edges is None else max_edges
    if edges.count() > most:
        return None
    rows, places = gathered(edges.select("src", "dst", "weight")), None
    if nodes is not None:
        if nodes.count() > most:
            return None
        places = gathered(nodes.select("node", F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y")))
    return edges.sparkSession.sparkContext.broadcast(Network(*rows, places))


def gathered(rows: DataFrame) -> tuple[np.ndarray, ...]:
    """The columns of rows (whole numbers or doubles) on the driver, packed by the tasks: a batch is one row
    of bytes there, four a whole number where they fit, and the driver holds little beside the result."""
    kinds = [np.float64 if f.dataType.simpleString() == "double" else np.int64 for f in rows.schema.fields]
    names = [f"c{k}" for k in range(len(kinds))]

    def packed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            if any(pdf.iloc[:, k].isna().any() for k, kind in enumerate(kinds) if kind is np.int64):
                raise ValueError("a network has no nulls")
            own = [pdf.iloc[:, k].to_numpy(dtype=kind) for k, kind in enumerate(kinds)]
            own = [v if kind is np.float64 else narrow(v) for v, kind in zip(own, kinds, strict=True)]
            yield pd.DataFrame({"n": [len(pdf)], **{c: [v.tobytes()] for c, v in zip(names, own, strict=True)}})

    parts: list[list[np.ndarray]] = [[np.zeros(0, dtype=np.int32 if kind is np.int64 else kind)] for kind in kinds]
    for r in rows.mapInPandas(packed, f"n long, {', '.join(f'{c} binary' for c in names)}").toLocalIterator(prefetchPartitions=True):
        for k, kind in enumerate(kinds):
            wide = len(r[k + 1]) == 8 * r[0]
            parts[k].append(np.frombuffer(r[k + 1], dtype=kind if wide else np.int32))
    return tuple(np.concatenate(p) for p in parts)


def top_speed(edges: DataFrame, nodes: DataFrame) -> float:
    """The most straight-line length that a unit of weight covers, over all edges."""
    a = nodes.select(F.col("node").alias("src"), F.col("x").alias("ax"), F.col("y").alias("ay"))
    b = nodes.select(F.col("node").alias("dst"), F.col("x").alias("bx"), F.col("y").alias("by"))
    d = F.sqrt((F.col("ax") - F.col("bx")) ** 2 + (F.col("ay") - F.col("by")) ** 2)
    # Merged, as Spark takes tables of nodes for smaller than they are and would broadcast them.
    return edges.join(a.hint("merge"), "src").join(b.hint("merge"), "dst").agg(F.max(d / F.col("weight"))).first()[0] or 1.0


_PATHS = "run long, target long, cost long, path array<long>, settled long"
_REACH = "run long, node long, dist long, pred long"


def paths(edges: DataFrame, runs: DataFrame, nodes: DataFrame | None = None, net=None) -> DataFrame:
    """runs(run, source, targets array, radius) -> run, target, cost, path, settled.

    Node coordinates make a run goal-directed, towards the box around its targets. Targets
    out of reach give no row. Over the broadcast bound, runs with a radius go
    by disks where coordinates are known, others by the frontier.
    """
    net = net or load(edges, nodes)
    own = runs.select("run", "source", "targets", F.col("radius").cast("double").alias("radius"))
    if net is None:
        if nodes is not None and not _unbounded(runs):
            return _by_disk(edges, own, nodes, _runs_rows, _PATHS)
        return _frontier_paths(edges, runs, nodes)

    def solved(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            yield from _runs_rows(net.value, pdf)

    return spread(own, "run").mapInPandas(solved, _PATHS)


def _runs_rows(net: Network, runs: pd.DataFrame) -> Iterator[pd.DataFrame]:
    for run, source, targets, radius in zip(runs["run"], runs["source"], runs["targets"], runs["radius"], strict=True):
        yield _path_rows(net, run, source, radius, targets)


def _path_rows(net: Network, run, source, radius, targets) -> pd.DataFrame:
    goals = sorted({int(t) for t in targets})
    bound = net.goal(*goals) if goals else None
    found = bounded(net, int(source), None if pd.isna(radius) else int(radius), goals, bound)
    out = [(run, t, found.dist[t], trace(found.pred, t), found.settled) for t in goals if t in found.dist]
    return pd.DataFrame(out, columns=["run", "target", "cost", "path", "settled"])


def _unbounded(runs: DataFrame) -> bool:
    return not runs.where("radius IS NULL").isEmpty()


def reach(edges: DataFrame, runs: DataFrame, strategy: str = "auto", nodes: DataFrame | None = None, net=None, history: bool = True, delta: int = 2_000, tasks: int | None = None) -> DataFrame:
    """runs(run, source, radius) -> run, node, dist, pred of everything within the radius, by ``tasks`` tasks if given.

    ``auto`` takes broadcast for a network within the bound, else disk if all
    runs have a radius and coordinates are known, else the frontier. Without
    ``history`` predecessors are neither kept nor returned.
    """
    if strategy in ("auto", "broadcast"):
        net = net or load(edges)
        if net is None and strategy == "broadcast":
            raise ValueError("the network passes the broadcast bound")
        strategy = "broadcast" if net is not None else "disk" if nodes is not None and not _unbounded(runs) else "frontier"
    own = runs.select("run", "source", F.col("radius").cast("double").alias("radius"))
    schema = _REACH if history else "run long, node long, dist long"
    if strategy == "disk":
        return _by_disk(edges, own.withColumn("targets", F.array().cast("array<long>")), nodes, lambda net, rows: _reach_rows(net, rows, history), schema)
    if strategy in ("frontier", "delta"):
        out = _frontier_reach(edges, runs, delta=delta if strategy == "delta" else None, history=history)
        return out if history else out.drop("pred")

    def solved(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            yield from _reach_rows(net.value, pdf, history)

    return spread(own, "run", tasks).mapInPandas(solved, schema)


def _reach_rows(net: Network, runs: pd.DataFrame, history: bool, most: int = 1 << 16) -> Iterator[pd.DataFrame]:
    """What each run reaches, some ``most`` rows at a time."""
    own, sizes, node, dist, pred = [], [], [], [], []

    def flush() -> pd.DataFrame:
        out = pd.DataFrame({"run": np.repeat(np.array(own, dtype=np.int64), sizes), "node": np.array(node, dtype=np.int64), "dist": np.array(dist, dtype=np.int64)})
        if history:
            none = np.zeros(len(node), dtype=bool)
            none[np.cumsum([0, *sizes[:-1]])] = True  # a run settles its source first
            out["pred"] = pd.arrays.IntegerArray(np.array(pred, dtype=np.int64), none)
        return out

    for run, source, radius in zip(runs["run"].tolist(), runs["source"].tolist(), runs["radius"].tolist(), strict=True):
        found = bounded(net, source, None if pd.isna(radius) else int(radius), history=history)
        own.append(run)
        sizes.append(len(found.dist))
        node += found.dist.keys()
        dist += found.dist.values()
        if history:
            pred += [found.pred[v] or 0 for v in found.dist]
        if len(node) >= most:
            yield flush()
            own, sizes, node, dist, pred = [], [], [], [], []
    if own:
        yield flush()


def pack(*columns: np.ndarray) -> bytes:
    """Columns of numbers of eight bytes, compressed byte by byte; the first ascends and goes as its steps."""
    own = np.stack([np.ascontiguousarray(c).view(np.int64) for c in (np.diff(columns[0], prepend=0), *columns[1:])])
    return zlib.compress(own.view(np.uint8).reshape(*own.shape, 8).transpose(0, 2, 1).tobytes(), 1)


def unpack(rows, kinds: str) -> list[np.ndarray]:
    """The columns of all packed rows one after the other; kinds: l a whole number, d a double."""
    parts = [np.zeros((len(kinds), 0), dtype=np.int64)]
    for data in rows:
        own = np.frombuffer(zlib.decompress(data), dtype=np.uint8).reshape(len(kinds), 8, -1)
        parts.append(np.array(own.transpose(0, 2, 1), order="C").view(np.int64)[:, :, 0])
        parts[-1][0] = np.cumsum(parts[-1][0])
    return [np.ascontiguousarray(c).view(np.float64) if k == "d" else c for c, k in zip(np.concatenate(parts, axis=1), kinds, strict=True)]


def _groups(label: np.ndarray, *columns: np.ndarray) -> Iterator[tuple[int, bytes]]:
    """Each label and its rows, packed in the order of the first column."""
    order = np.lexsort((columns[0], label))
    label, columns = label[order], tuple(c[order] for c in columns)
    first = np.flatnonzero(np.r_[True, label[1:] != label[:-1]][: len(label)]).tolist()
    for a, b in zip(first, [*first[1:], len(label)][: len(first)], strict=True):
        yield int(label[a]), pack(*(c[a:b] for c in columns))


def _packed_by(rows: DataFrame, parts: int, most: int = 1 << 20) -> DataFrame:
    """part, data: rows by the remainder of their first column, packed some ``most`` at a time."""
    kinds = [np.float64 if f.dataType.simpleString() == "double" else np.int64 for f in rows.schema.fields]

    def dealt(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[list[np.ndarray]] = []

        def flush() -> pd.DataFrame:
            own = [np.concatenate(c) for c in zip(*held, strict=True)]
            return pd.DataFrame(list(_groups(own[0] % parts, *own)), columns=["part", "data"])

        for pdf in batches:
            held.append([pdf.iloc[:, k].to_numpy(dtype=kind) for k, kind in enumerate(kinds)])
            if sum(len(own[0]) for own in held) >= most:
                yield flush()
                held = []
        if held:
            yield flush()

    return rows.mapInPandas(dealt, "part long, data binary")


def _found(ids: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where each wanted number stands among the ascending ids, and whether it does."""
    at = np.minimum(np.searchsorted(ids, wanted), max(0, len(ids) - 1))
    return at, ids[at] == wanted if len(ids) else np.zeros(len(wanted), dtype=bool)


def _spots_of(rows: pd.DataFrame) -> tuple[np.ndarray, ...]:
    node, x, y = unpack(rows["data"], "ldd")
    by = np.argsort(node, kind="stable")
    return node[by], x[by], y[by]


def _placed(edges: DataFrame, nodes: DataFrame, parts: int) -> DataFrame:
    """speed, data: edges whose source has a place, packed with it (dst, src - dst, weight, x, y of src), and the
    most straight-line length that a unit of weight covers among those whose both ends have one.

    They meet their ends packed, by remainders of the nodes: a few bytes an edge move, not a row.
    """
    spots = lambda: _packed_by(nodes.select(F.col("node").cast("long").alias("node"), F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y")).dropna(), parts).withColumnRenamed("part", "of")
    arcs = _packed_by(edges.where("src IS NOT NULL").select(*[F.col(c).cast("long").alias(c) for c in ("src", "dst", "weight")]), parts)

    def sources(arcs: pd.DataFrame, spots: pd.DataFrame) -> pd.DataFrame:
        src, dst, weight = unpack(arcs["data"], "lll")
        node, x, y = _spots_of(spots)
        at, known = _found(node, src)
        src, dst, weight, at = (v[known] for v in (src, dst, weight, at))
        return pd.DataFrame(list(_groups(dst % parts, dst, src - dst, weight, x[at], y[at])), columns=["part", "data"])

    def targets(arcs: pd.DataFrame, spots: pd.DataFrame) -> pd.DataFrame:
        dst, step, weight, x, y = unpack(arcs["data"], "llldd")
        node, nx, ny = _spots_of(spots)
        at, known = _found(node, dst)
        speed = (np.hypot(nx[at[known]] - x[known], ny[at[known]] - y[known]) / weight[known]).max(initial=0.0)
        return pd.DataFrame([(speed, data) for _, data in _groups(np.zeros(len(dst), dtype=np.int64), dst, step, weight, x, y)], columns=["speed", "data"])

    # Dealt by number, as packed rows are few bytes and much work.
    by = lambda rows, c: rows.repartition(parts, c).groupBy(c)
    there = by(arcs, "part").cogroup(by(spots(), "of")).applyInPandas(sources, "part long, data binary")
    return cut(by(there, "part").cogroup(by(spots(), "of")).applyInPandas(targets, "speed double, data binary"))


def _by_disk(edges: DataFrame, runs: DataFrame, nodes: DataFrame, solve, schema: str, most: int = 1024) -> DataFrame:
    """Runs of a square cell share the edges of the cell and of a border around it.

    A node within cost r lies within speed * r of the source. Cells are four
    times as wide as the border, so an edge is shipped to some two cells, packed;
    runs of very different radii go by cells of different sizes, those that may
    reach everywhere by one that holds everything. A cell's runs are dealt over
    groups of about ``most``. A run without any edge is solved all the same.
    """
    spark = edges.sparkSession
    parts = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    box = nodes.agg(F.min("x").alias("x"), F.min("y").alias("y"), F.greatest(F.max("x") - F.min("x"), F.max("y") - F.min("y")).alias("w"), F.count("*").alias("n")).first()
    x0, y0, whole = box.x or 0.0, box.y or 0.0, box.w or 1.0
    arcs = _placed(edges, nodes, max(parts, box.n >> 17))
    speed = (arcs.agg(F.max("speed")).first()[0] or 1.0) * (1 + 1e-9)
    wide = F.pow(F.lit(2.0), 2 + F.ceil(F.log2(F.greatest(F.col("radius") * speed, F.lit(whole / 4096)))))
    side = F.when(F.col("radius").isNull() | (wide >= whole), F.lit(whole)).otherwise(wide)
    spot = nodes.select("node", (F.col("x") - x0).alias("x"), (F.col("y") - y0).alias("y"))
    cell = [F.when(F.col("side") == whole, F.lit(0)).otherwise(F.floor(F.col(c) / F.col("side"))).alias(i) for c, i in (("x", "i"), ("y", "j"))]
    at = runs.join(spot.hint("merge"), F.col("source") == F.col("node"), "left").withColumn("side", side).select("run", "source", "radius", "targets", "side", *cell)
    at = cut(at.withColumn("piece", F.pmod(F.xxhash64("run"), F.ceil(F.count("*").over(Window.partitionBy("side", "i", "j")) / most))))
    key = ["side", "i", "j", "piece"]
    used = cut(at.select(*key).distinct())
    sides = sorted(r.side for r in used.select("side").distinct().collect())  # a dozen at most

    def celled(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = []
        for data in (d for pdf in batches for d in pdf["data"]):
            held.append(unpack([data], "llldd"))
            if sum(len(own[0]) for own in held) >= 1 << 20:
                yield in_cells(*(np.concatenate(c) for c in zip(*held, strict=True)))
                held = []
        if held:
            yield in_cells(*(np.concatenate(c) for c in zip(*held, strict=True)))

    def in_cells(dst: np.ndarray, step: np.ndarray, weight: np.ndarray, x: np.ndarray, y: np.ndarray) -> pd.DataFrame:
        out = []
        for side in sides:
            near = np.zeros((4, len(dst)), dtype=np.int64)  # cells of the lower and of the upper border, by x and by y
            if side != whole:
                border = side * (0.25 + 1e-9)
                near = np.floor(np.array([(v + b) / side for v in (x - x0, y - y0) for b in (-border, border)])).astype(np.int64)
            ways = [(near[i], near[j], ((i == 0) | (near[1] > near[0])) & ((j == 2) | (near[3] > near[2]))) for i in (0, 1) for j in (2, 3)]
            label = np.concatenate([((i + 1 << 20) + j + 1)[own] for i, j, own in ways])
            some = np.concatenate([np.flatnonzero(own) for _, _, own in ways])
            out += [(side, (k >> 20) - 1, (k & (1 << 20) - 1) - 1, d) for k, d in _groups(label, (dst + step)[some], -step[some], weight[some])]
        return pd.DataFrame(out, columns=["side", "i", "j", "data"])

    if used.count() <= 1 << 16:  # some MB; it spares the edges a way
        used = F.broadcast(used)
    cells = arcs.select("data").mapInPandas(celled, "side double, i long, j long, data binary").join(used, ["side", "i", "j"]).select("data", *[F.col(c).alias(f"of_{c}") for c in key])  # names of their own: both sides come from one table

    def one(runs: pd.DataFrame, own: pd.DataFrame) -> pd.DataFrame:
        src, step, weight = unpack(own["data"], "lll")
        return pd.concat(list(solve(Network(src, src + step, weight), runs)), ignore_index=True)

    at, cells = at.repartition(4 * parts, *key), cells.repartition(4 * parts, *[f"of_{c}" for c in key])
    return at.groupBy(*key).cogroup(cells.groupBy(*[f"of_{c}" for c in key])).applyInPandas(one, schema)


#: Nodes of a block of the frontier, and runs that share a copy of its edges.
BLOCK_NODES, BLOCK_RUNS = 1 << 14, 256


def _block_reach(edges: DataFrame, runs: DataFrame, nodes: DataFrame, targets: DataFrame | None) -> DataFrame:
    """run, node, dist by rounds over square blocks of nodes: a round settles whatever opened in a block as far as
    the block goes, so there are as many rounds as blocks on a path and not as its hops.

    Stops and bounds as in ``_frontier_reach``. A task holds the edges of one block and the entries of some runs there.
    """
    box = nodes.agg(F.min("x").alias("x"), F.min("y").alias("y"), F.max("x").alias("x1"), F.max("y").alias("y1"), F.count("*").alias("n")).first()
    x0, y0 = box.x or 0.0, box.y or 0.0
    whole = max((box.x1 or 0.0) - x0, (box.y1 or 0.0) - y0) or 1.0
    side = whole / max(1, int((max((box.x1 or 0.0) - x0, whole / 1024) * max((box.y1 or 0.0) - y0, whole / 1024) / whole**2 * box.n / BLOCK_NODES) ** 0.5 + 1))
    cell = [F.least(F.floor((F.col(c) - v) / side), F.lit(1 << 20)) for c, v in (("x", x0), ("y", y0))]
    spots = cut(nodes.select("node", (cell[0] * (1 << 21) + cell[1]).alias("block"), "x", "y").dropDuplicates(["node"]))
    place = lambda df, c: df.join(spots.select(F.col("node").alias(c), "block").hint("merge"), c, "left").fillna(-1, ["block"])
    pieces = -(-runs.count() // BLOCK_RUNS) or 1
    piece = F.pmod(F.xxhash64("run"), F.lit(pieces))
    own = place(place(edges.select("src", "dst", "weight"), "dst").withColumnRenamed("block", "to"), "src")
    own = cut(own.withColumn("piece", F.explode(F.sequence(F.lit(0), F.lit(pieces - 1)))).select(F.col("block").alias("of"), F.col("piece").cast("long").alias("part"), "src", "dst", "weight", "to"))
    state = place(runs.select("run", F.col("source").alias("node")), "node").select("run", "node", "block", piece.alias("piece"), F.lit(0).cast("long").alias("dist"), F.lit(1).alias("open"))
    caps, limit, lower = runs.select("run", F.col("radius").cast("double").alias("cap")), None, None
    if targets is not None:
        wanted = cut(targets.select("run", "target").distinct())
        total = wanted.groupBy("run").agg(F.count("*").alias("wanted"))
        if total.where("wanted > 1").isEmpty():
            goal = wanted.join(spots.select(F.col("node").alias("target"), F.col("x").alias("gx"), F.col("y").alias("gy")), "target").select("run", "gx", "gy")
            lower = cut(goal), top_speed(edges, nodes) * (1 + 1e-9)

    def settle(rows: pd.DataFrame, arcs: pd.DataFrame) -> pd.DataFrame:
        out: list[tuple] = []
        if len(rows):
            block, part = int(rows["block"].iloc[0]), int(rows["piece"].iloc[0])
            ways: dict[int, list] = {}
            for s, t, w, b in zip(*(arcs[c].tolist() for c in ("src", "dst", "weight", "to")), strict=True):
                ways.setdefault(s, []).append((t, w, b))
            for run, some in rows.groupby("run"):
                cap, dist, done, gone = some["cap"].min(), {}, {}, {}
                cap = float("inf") if pd.isna(cap) else cap
                for v, d in zip(some["node"].tolist(), some["dist"].tolist(), strict=True):
                    dist[v] = min(d, dist.get(v, d))
                heap = [(dist[v], v) for v in some.loc[some["open"] == 1, "node"].tolist()]
                heapq.heapify(heap)
                while heap:
                    d, u = heapq.heappop(heap)
                    if u in done or d > dist[u]:
                        continue
                    done[u] = d
                    for v, w, b in ways.get(u, ()):
                        nd = d + w
                        if nd > cap:
                            continue
                        if b != block:
                            if nd < gone.get(v, (nd + 1,))[0]:
                                gone[v] = nd, b
                        elif nd < dist.get(v, nd + 1):
                            dist[v] = nd
                            heapq.heappush(heap, (nd, v))
                out += [(run, v, block, part, d, 0) for v, d in done.items()]
                out += [(run, v, b, part, d, 1) for v, (d, b) in gone.items()]
        return pd.DataFrame(out, columns=["run", "node", "block", "piece", "dist", "open"])

    while True:
        live, stop = state.where("open = 1"), caps
        if limit is not None:
            live = live.join(limit, "run", "left").where("limit IS NULL OR dist <= limit")
            stop = caps.join(limit, "run", "left").select("run", F.least("cap", F.col("limit").cast("double")).alias("cap"))
            if lower is not None:
                live = live.join(spots.select("node", "x", "y"), "node", "left").join(lower[0], "run", "left")
                ahead = F.floor(F.sqrt((F.col("x") - F.col("gx")) ** 2 + (F.col("y") - F.col("gy")) ** 2) / lower[1])
                live = live.where(F.col("limit").isNull() | (F.col("dist") + F.coalesce(ahead, F.lit(0)) <= F.col("limit")))
        live = cut_size(live.select("run", "node", "block", "piece", "dist", "open"))
        if live.isEmpty():
            return state.select("run", "node", "dist")
        known = state.withColumn("open", F.lit(0)).join(live.select("block", "piece").distinct(), ["block", "piece"], "left_semi")
        rows = known.unionByName(live).join(stop, "run")
        new = rows.groupBy("block", "piece").cogroup(own.groupBy("of", "part")).applyInPandas(settle, "run long, node long, block long, piece long, dist long, open int")
        # On equal costs the closed entry stays: its block was settled from it already.
        merged = state.unionByName(new).groupBy("run", "node", "block", "piece").agg(F.min(F.struct("dist", "open")).alias("s"))
        state = cut_size(merged.select("run", "node", "block", "piece", "s.dist", "s.open"))
        if targets is not None:
            got = state.join(wanted.withColumnRenamed("target", "node"), ["run", "node"]).groupBy("run").agg(F.count("*").alias("got"), F.max("dist").alias("limit"))
            limit = got.join(total, "run").where("got = wanted").select("run", "limit")


def _frontier_reach(edges: DataFrame, runs: DataFrame, targets: DataFrame | None = None, nodes: DataFrame | None = None, delta: int | None = None, history: bool = True) -> DataFrame:
    """Rounds of relaxation over state(run, node, dist, open); open nodes were improved since they were last relaxed.

    ``targets(run, target)`` stop a run: once all of its targets are reached,
    nothing over the dearest of them is relaxed. With one target a run and
    coordinates, what cannot reach it within that cost is pruned as well.
    ``delta`` relaxes only the lowest bucket of each run. Where coordinates are
    known, a round goes through whole blocks of nodes.
    """
    spark = edges.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # Dealt once by source; the rounds only move the state to them.
    edges = cut(edges.select("src", "dst", "weight")).repartition(parts, "src").persist()
    state = runs.select("run", F.col("source").alias("node"), F.lit(0).cast("long").alias("dist"), F.lit(1).alias("open"))
    blocks = nodes is not None and delta is None
    if blocks:
        state = _block_reach(edges, runs, nodes, targets)
    radius, limit = runs.select("run", F.col("radius").cast("long").alias("radius")), None
    if targets is not None and not blocks:
        wanted = cut(targets.select("run", "target").distinct())
        total = wanted.groupBy("run").agg(F.count("*").alias("wanted"))
    while not blocks:
        act = state.where("open = 1")
        if delta is not None:
            low = act.groupBy("run").agg(F.floor(F.min("dist") / delta).alias("low"))
            act = act.join(low, "run").where(F.floor(F.col("dist") / delta) == F.col("low")).drop("low")
        if limit is not None:
            act = act.join(limit, "run", "left").where("limit IS NULL OR dist <= limit")
        act = act.select("run", "node", "dist")
        if delta is not None or limit is not None:
            act = cut_size(act)
        if act.isEmpty():
            break
        new = act.join(edges, F.col("node") == F.col("src")).join(radius, "run")
        new = new.select("run", F.col("dst").alias("node"), (F.col("dist") + F.col("weight")).alias("dist"), "radius").where("radius IS NULL OR dist <= radius")
        new = new.groupBy("run", "node").agg(F.min("dist").alias("dist")).withColumn("open", F.lit(1))
        # On equal costs the closed entry stays: it was relaxed already.
        rows = state.unionByName(act.withColumn("open", F.lit(0))).unionByName(new.select("run", "node", "dist", "open"))
        merged = rows.groupBy("run", "node").agg(F.min(F.struct("dist", "open")).alias("s"))
        state = cut_size(merged.select("run", "node", "s.dist", "s.open"))
        if targets is not None:
            got = state.join(wanted.withColumnRenamed("target", "node"), ["run", "node"]).groupBy("run").agg(F.count("*").alias("got"), F.max("dist").alias("limit"))
            limit = got.join(total, "run").where("got = wanted").select("run", "limit")
    if not history:
        edges.unpersist()
        return state.select("run", "node", "dist", F.lit(None).cast("long").alias("pred"))
    a, b = state.alias("a"), state.alias("b")
    tight = a.join(edges, F.col("a.node") == F.col("src")).join(b, (F.col("a.run") == F.col("b.run")) & (F.col("dst") == F.col("b.node")) & (F.col("a.dist") + F.col("weight") == F.col("b.dist")))
    pred = tight.groupBy(F.col("b.run").alias("run"), F.col("b.node").alias("node")).agg(F.min("a.node").alias("pred"))
    out = cut_size(state.join(pred, ["run", "node"], "left").select("run", "node", "dist", "pred"))
    edges.unpersist()
    return out


def backtrace(found: DataFrame, ends: DataFrame) -> DataFrame:
    """reach rows and ends(run, target) -> run, target, pos, node; links double each round."""
    hop = cut_size(found.select("run", "node", F.coalesce("pred", "node").alias("up"), "dist"))
    steps = cut_size(ends.select("run", "target", F.col("target").alias("node"), F.lit(0).cast("long").alias("back")))
    jump, size = hop.select("run", "node", "up", "dist"), 1
    out = steps
    while True:
        more = out.join(jump, ["run", "node"]).where("up <> node").select("run", "target", F.col("up").alias("node"), (F.col("back") + size).alias("back"))
        merged = cut_size(out.unionByName(more).dropDuplicates(["run", "target", "node"]))
        a, b = jump.alias("a"), jump.alias("b")
        jump = cut_size(a.join(b, (F.col("a.run") == F.col("b.run")) & (F.col("a.up") == F.col("b.node"))).select(F.col("a.run"), F.col("a.node"), F.col("b.up"), F.col("a.dist")))
        # Nodes over the stop of a run may be left without a predecessor: links end there as at a source.
        done = jump.join(hop.where("up <> node").select("run", F.col("node").alias("up")), ["run", "up"], "left_semi").isEmpty()
        out, size = merged, size * 2
        if done:
            last = out.join(jump, ["run", "node"]).where("up <> node").select("run", "target", F.col("up").alias("node"), (F.col("back") + size).alias("back"))
            return out.unionByName(last).dropDuplicates(["run", "target", "node"]).join(hop.select("run", "node", "dist"), ["run", "node"]).select("run", "target", "node", F.col("dist").alias("cum"))


def _frontier_paths(edges: DataFrame, runs: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    ends = runs.select("run", F.explode("targets").alias("target")).distinct()
    found = _frontier_reach(edges, runs, ends, nodes)
    ends = ends.join(found.select("run", F.col("node").alias("target"), F.col("dist").alias("cost")), ["run", "target"])
    walk = backtrace(found, ends.select("run", "target")).groupBy("run", "target").agg(F.transform(F.array_sort(F.collect_list(F.struct("cum", "node"))), lambda s: s["node"]).alias("path"))
    settled = found.groupBy("run").agg(F.count("*").alias("settled"))
    return ends.join(walk, ["run", "target"]).join(settled, "run").select("run", "target", "cost", "path", "settled")
