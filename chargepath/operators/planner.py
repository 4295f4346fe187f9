"""The trip planner: initial path, bases, candidate stations, legs, the process
graph, its shortest path and the stitched solution. All trips of a batch go
through each step together.

A network and stations of a checked size are shipped whole, and each step is
one pass of kernels over its runs (trips, bases, places of a stop, trips again).
Larger ones go through the searches over tables; both forms give equal rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from chargepath.config import TripOptions
from chargepath.operators import bins, search, separators
from chargepath.operators.network import reverse, validate
from chargepath.operators.search import cut, cut_size

SOURCE, TARGET = -1, -2
#: Stations up to which they are shipped whole: 48 bytes each.
MAX_BROADCAST_STATIONS = 2_000_000
#: Targets of one search run.
RUN_TARGETS = 4096
#: Layers of process graphs that one cut solves.
LAYERS = 8


@dataclass
class Net:
    """A network with its nodes, stations and bin grid. What is loaded stays, also that it was too large."""

    edges: DataFrame
    nodes: DataFrame
    stations: DataFrame
    grid: bins.BinGrid
    _kept: dict = field(default_factory=dict, repr=False)

    def load(self):
        return self._once("there", lambda: search.load(self.edges, self.nodes))

    def load_back(self):
        """The loaded network with all edges turned round."""
        there = self.load()
        return None if there is None else self._once("back", lambda: self.edges.sparkSession.sparkContext.broadcast(there.value.flipped()))

    def load_stations(self):
        """Broadcast arrays (station, node, x, y, plug) in the order of stations, or None if there are too many."""
        def read():
            if self.stations.count() > MAX_BROADCAST_STATIONS:
                return None
            rows = self.stations.select("station", "node", F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"), *["plug"] * ("plug" in self.stations.columns)).toPandas()
            return self.edges.sparkSession.sparkContext.broadcast(rows.sort_values("station", ignore_index=True))

        return self._once("stations", read)

    def _once(self, name: str, make):
        if name not in self._kept:
            self._kept[name] = make()
        return self._kept[name]

    def validate(self) -> DataFrame:
        return validate(self.edges, self.nodes)


def initial_path(net: Net, trips: DataFrame) -> DataFrame:
    """trips(trip, source, target) -> trip, cost, path, cum (running cost by node), settled."""
    loaded = net.load()
    if loaded is None:
        return _initial_path_tables(net, trips)

    def solved(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            own, out = loaded.value, []
            for trip, s, t in zip(pdf["trip"], pdf["source"], pdf["target"], strict=True):
                found = search.bounded(own, int(s), None, [int(t)], own.goal(int(t)))
                if t in found.dist:
                    path = search.trace(found.pred, int(t))
                    out.append((trip, found.dist[t], path, [found.dist[v] for v in path], found.settled))
            yield pd.DataFrame(out, columns=["trip", "cost", "path", "cum", "settled"])

    return search.spread(trips.select("trip", "source", "target"), "trip").mapInPandas(solved, "trip long, cost long, path array<long>, cum array<long>, settled long")


def _initial_path_tables(net: Net, trips: DataFrame) -> DataFrame:
    runs = trips.select(F.col("trip").alias("run"), "source", F.array("target").alias("targets"), F.lit(None).cast("long").alias("radius"))
    found = search._frontier_paths(net.edges, runs, net.nodes)
    steps = found.select(F.col("run").alias("trip"), "cost", "settled", F.posexplode("path").alias("pos", "node"))
    before = Window.partitionBy("trip").orderBy("pos")
    steps = steps.withColumn("prev", F.lag("node").over(before)).join(net.edges.select(F.col("src").alias("prev"), F.col("dst").alias("node"), "weight").groupBy("prev", "node").agg(F.min("weight").alias("weight")), ["prev", "node"], "left")
    run = Window.partitionBy("trip").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    steps = steps.withColumn("cum", F.coalesce(F.sum("weight").over(run), F.lit(0)))
    rows = steps.groupBy("trip").agg(F.first("cost").alias("cost"), F.first("settled").alias("settled"), F.array_sort(F.collect_list(F.struct("pos", "node", "cum"))).alias("s"))
    return rows.select("trip", "cost", F.col("s.node").alias("path"), F.col("s.cum").alias("cum"), "settled")


def split_bases(path: DataFrame, opts: TripOptions) -> DataFrame:
    """path -> trip, stop (from 1), pos, node, cum: where the trip is cut."""
    step, tail = opts.step, opts.capacity if opts.tail_rule == "capacity" else opts.step
    points = F.arrays_zip("path", "cum")
    if opts.split_rule == "multiples":
        cls = lambda c: F.ceil(c / step)
        rows = path.select("trip", "cost", F.posexplode(points).alias("pos", "p")).select("trip", "cost", "pos", F.col("p.path").alias("node"), F.col("p.cum").alias("cum"))
        rows = rows.where(F.col("cum") > 0).groupBy("trip", "cost", cls(F.col("cum")).alias("k")).agg(F.max(F.struct("cum", "node", "pos")).alias("m"))
        rows = rows.where((F.col("m.cum") < F.col("cost")) & (F.col("cost") - (F.col("k") - 1) * step > tail))
    else:
        kind = "array<struct<pos:int,node:bigint,cum:bigint>>"
        start = F.struct(F.lit(0).cast("long").alias("base"), F.lit(0).alias("pos"), F.struct(F.lit(0).alias("pos"), F.col("path")[0].alias("node"), F.lit(0).cast("long").alias("cum")).alias("prev"), F.array().cast(kind).alias("out"))

        def take(s, p):
            here = F.struct(s["pos"].alias("pos"), p["path"].alias("node"), p["cum"].alias("cum"))
            over = (p["cum"] - s["base"] > step) & (F.col("cost") - s["base"] > tail)
            jump = over & (s["prev"]["cum"] <= s["base"])  # one edge passes the step
            base = F.when(jump & (p["cum"] < F.col("cost")), here).when(over & ~jump, s["prev"])
            return F.struct(F.coalesce(base["cum"], s["base"]).alias("base"), (s["pos"] + 1).alias("pos"), here.alias("prev"), F.when(base.isNotNull(), F.concat(s["out"], F.array(base).cast(kind))).otherwise(s["out"]).alias("out"))

        rows = path.select("trip", "cost", F.posexplode(F.aggregate(points, start, take)["out"]).alias("k", "m"))
    if opts.direct_if_within:
        rows = rows.where(F.col("cost") > opts.capacity)
    stop = F.row_number().over(Window.partitionBy("trip").orderBy("m.cum"))
    return rows.select("trip", stop.alias("stop"), F.col("m.pos").cast("int").alias("pos"), F.col("m.node").alias("node"), F.col("m.cum").alias("cum"))


def usable(stations: DataFrame, opts: TripOptions) -> DataFrame:
    """Stations with a plug that fits; all where no plugs are named."""
    return stations if opts.plugs is None else stations.where(F.col("plug").isin(*opts.plugs))


def _disk(net: Net, runs: DataFrame, direction: str) -> DataFrame:
    """run, node, dist of the disk around each run's source, by searches over tables."""
    out = search.reach(net.edges, runs, "auto", net.nodes, net.load(), history=False) if direction != "in" else None
    if direction == "out":
        return out
    back = search.reach(net._once("reversed", lambda: cut(reverse(net.edges))), runs, "auto", net.nodes, net.load_back(), history=False)
    if direction == "in":
        return back
    return out.unionByName(back).groupBy("run", "node").agg(F.max("dist").alias("dist"), F.count("*").alias("n")).where("n = 2").drop("n")


_CANDIDATES = "trip long, stop int, station long, node long, dist long, widen_round int"
_VISITS = "settled long, bins_visited long, scanned long"


class Gatherer:
    """Candidate stations of a base: bins of the reached disk and one ring more, then the n best."""

    def __init__(self, net: search.Network, back: search.Network | None, stations: pd.DataFrame, grid: bins.BinGrid, opts: TripOptions) -> None:
        self.net, self.back, self.grid, self.opts = net, back, grid, opts
        if opts.plugs is not None:
            stations = stations[stations["plug"].isin(opts.plugs)]
        self.by_bin: dict[int, list] = {}
        self.cells: dict[int, int | None] = {}  # of nodes seen
        self.blocks: dict[int, list[int]] = {}  # around bins seen
        for row in zip(stations["station"].tolist(), stations["node"].tolist(), stations["x"].tolist(), stations["y"].tolist(), strict=True):
            self.by_bin.setdefault(grid.bin_at(row[2], row[3]), []).append(row)

    def disk(self, base: int, radius: int) -> tuple[dict, int]:
        there = search.bounded(self.net, base, radius, history=False) if self.opts.direction != "in" else None
        if self.opts.direction == "out":
            return there.dist, there.settled
        back = search.bounded(self.back, base, radius, history=False)
        if self.opts.direction == "in":
            return back.dist, back.settled
        return {v: max(d, back.dist[v]) for v, d in there.dist.items() if v in back.dist}, there.settled + back.settled

    def cell(self, node: int) -> int | None:
        """The bin of a node; None where its place is unknown."""
        if node not in self.cells:
            xy = self.net.spot(node)
            self.cells[node] = None if xy is None else self.grid.bin_at(*xy)
        return self.cells[node]

    def block(self, cell: int) -> list[int]:
        if cell not in self.blocks:
            self.blocks[cell] = list(self.grid.block(cell, 1))
        return self.blocks[cell]

    def gather(self, base: int) -> tuple[list, int, int, int, int]:
        """((station, node, dist) of the n best, round, settled, bins visited, stations looked at)."""
        opts, best, k = self.opts, [], 0
        settled = visited = scanned = 0
        for k in range(opts.max_widen + 1):
            dist, n = self.disk(base, opts.radius(k))
            near = {c for cell in {self.cell(v) for v in dist} if cell is not None for c in self.block(cell)}
            found = [(dist.get(r[1]), c, r) for c in near for r in self.by_bin.get(c, ())]
            settled, visited, scanned = settled + n, visited + len(near), scanned + len(found)
            if opts.order == "bins":
                best = sorted(found, key=lambda f: (f[1], f[2][0]))
            else:
                at = self.net.spot(base) if opts.order == "straight" else None
                best = sorted((f for f in found if f[0] is not None), key=lambda f: ((f[2][2] - at[0]) ** 2 + (f[2][3] - at[1]) ** 2 if at else f[0], f[2][0]))
            best = best[: opts.n]
            if len(best) >= opts.n:
                break
        return [(f[2][0], f[2][1], f[0]) for f in best], k, settled, visited, scanned


def find_candidates(net: Net, bases: DataFrame, opts: TripOptions, visits: bool = False) -> DataFrame:
    """bases(trip, stop, node) -> trip, stop, station, node, dist, widen_round.

    A bounded search from each base, without history, gives the reached nodes;
    their bins and one more ring around them give the stations. Bases with fewer
    than n stations search again in a wider disk. ``visits`` adds what the search
    and the bins cost at each base (for loaded networks).
    """
    loaded, stations = net.load(), net.load_stations()
    if loaded is None or stations is None:
        return _candidates_tables(net, bases, opts)
    back, grid = net.load_back() if opts.direction != "out" else None, net.grid

    def gathered(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        own = Gatherer(loaded.value, back.value if back else None, stations.value, grid, opts)
        for pdf in batches:
            out, known = [], {}
            for trip, stop, node in zip(pdf["trip"], pdf["stop"], pdf["node"], strict=True):
                if node not in known:
                    known[node] = own.gather(int(node))
                best, k, *cost = known[node]
                out += [(trip, stop, s, at, d, k, *cost) for s, at, d in best]
            yield pd.DataFrame(out, columns=["trip", "stop", "station", "node", "dist", "widen_round", "settled", "bins_visited", "scanned"]).astype({"dist": "Int64"})

    # Bases at one node share their search.
    rows = search.spread(bases.select("trip", "stop", "node"), "node").mapInPandas(gathered, f"{_CANDIDATES}, {_VISITS}")
    return rows if visits else rows.drop("settled", "bins_visited", "scanned")


def _candidates_tables(net: Net, bases: DataFrame, opts: TripOptions) -> DataFrame:
    left = cut(bases.select("trip", "stop", F.col("node").alias("base"), F.abs(F.xxhash64("trip", "stop")).alias("run")))
    items = bins.with_bin(usable(net.stations, opts), net.grid).select("station", F.col("node").alias("at"), "x", "y", F.col("bin").alias("near"))
    spots = bins.with_bin(net.nodes, net.grid).select("node", "bin")
    out = None
    for k in range(opts.max_widen + 1):
        if left.isEmpty():
            break
        disk = _disk(net, left.select("run", F.col("base").alias("source"), F.lit(opts.radius(k)).alias("radius")), opts.direction)
        disk = cut(disk)
        near = bins.around(disk.join(spots, "node").select("run", "bin").distinct(), net.grid, 1).select("run", "near").distinct()
        found = near.join(items, "near").join(disk.withColumnRenamed("node", "at"), ["run", "at"], "left" if opts.order == "bins" else "inner")
        found = found.join(left, "run")
        order = [F.col("dist"), F.col("station")]
        if opts.order == "straight":
            b = net.nodes.select(F.col("node").alias("base"), F.col("x").alias("bx"), F.col("y").alias("by"))
            found = found.join(b, "base").withColumn("d2", (F.col("x") - F.col("bx")) ** 2 + (F.col("y") - F.col("by")) ** 2)
            order = [F.col("d2"), F.col("station")]
        elif opts.order == "bins":
            order = [F.col("near"), F.col("station")]
        rank = F.row_number().over(Window.partitionBy("run").orderBy(*order))
        found = cut(found.withColumn("rank", rank).where(F.col("rank") <= opts.n).select("run", "trip", "stop", "station", F.col("at").alias("node"), "dist", F.lit(k).alias("widen_round")))
        full = found.groupBy("run").agg(F.count("*").alias("n")).where(F.col("n") >= (opts.n if k < opts.max_widen else 1))
        now = found.join(full.select("run"), "run", "left_semi")
        out = now if out is None else out.unionByName(now)
        left = cut(left.join(full.select("run"), "run", "left_anti"))
    if out is None:
        out = bases.sparkSession.createDataFrame([], "run long, trip long, stop int, station long, node long, dist long, widen_round int")
    return out.drop("run")


def slide(net: Net, path: DataFrame, bases: DataFrame, candidates: DataFrame, opts: TripOptions) -> DataFrame:
    """Candidates of bases that have none: the base moves along the path, one
    position back or forth at a time, until a station is in its disk."""
    empty = bases.join(candidates.select("trip", "stop").distinct(), ["trip", "stop"], "left_anti")
    steps = [s for d in range(1, opts.slide_steps + 1) for s in (-d, d)]
    moved = empty.withColumn("try", F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.lit(s).alias("s")) for k, s in enumerate(steps)])))
    moved = moved.join(path.select("trip", "path"), "trip").withColumn("i", F.col("pos") + F.col("try.s")).where("i >= 0 AND i < size(path)")
    moved = moved.select("trip", (F.col("stop") * len(steps) + F.col("try.k")).cast("int").alias("stop"), F.col("path")[F.col("i")].alias("node"))
    found = find_candidates(net, moved, replace(opts, max_widen=0))
    first = found.groupBy("trip", F.floor(F.col("stop") / len(steps)).alias("s")).agg(F.min("stop").alias("stop"))
    return found.join(first, ["trip", "stop"]).select("trip", F.col("s").cast("int").alias("stop"), "station", "node", "dist", "widen_round")


def layers(trips: DataFrame, bases: DataFrame, candidates: DataFrame) -> DataFrame:
    """trip, layer, id, node: source at 0, stations at 1..m, target at m + 1; trips without a station at some base have no layers."""
    m = trips.select("trip").join(bases.groupBy("trip").agg(F.max("stop").alias("m")), "trip", "left").fillna(0, ["m"])
    have = candidates.groupBy("trip").agg(F.count_distinct("stop").alias("c"))
    m = m.join(have, "trip", "left").where(F.coalesce("c", F.lit(0)) == F.col("m")).select("trip", "m")
    ends = trips.join(m, "trip")
    return (ends.select("trip", F.lit(0).alias("layer"), F.lit(SOURCE).cast("long").alias("id"), F.col("source").alias("node"))
            .unionByName(candidates.join(m.select("trip"), "trip").select("trip", F.col("stop").alias("layer"), F.col("station").alias("id"), "node"))
            .unionByName(ends.select("trip", (F.col("m") + 1).alias("layer"), F.lit(TARGET).cast("long").alias("id"), F.col("target").alias("node"))))


def legs(net: Net, stops: DataFrame, opts: TripOptions, cache: DataFrame | None = None) -> DataFrame:
    """layers -> trip, layer, u, v, u_node, v_node, cost, path, settled, run: all legs between consecutive layers within the limit.

    one_to_many starts one search at each place and stops when all that any trip
    wants from there are settled; pairwise starts one for each pair. Trips share
    searches; legs that ``cache`` (see ``leg_cache``) holds are not searched again.
    """
    a = stops.select("trip", "layer", F.col("id").alias("u"), F.col("node").alias("u_node"))
    b = stops.select("trip", (F.col("layer") - 1).alias("layer"), F.col("id").alias("v"), F.col("node").alias("v_node"))
    pairs = cut(a.join(b, ["trip", "layer"]).where("u <> v"))
    wanted = pairs if cache is None else pairs.join(cache.where(F.col("limit") >= opts.limit).select("u_node", "v_node"), ["u_node", "v_node"], "left_anti")
    wanted = wanted.select("u_node", "v_node").distinct()
    part = F.col("v_node")
    if opts.leg_mode == "one_to_many":  # a place with very many targets is dealt over several runs
        wanted = wanted.withColumn("many", F.count("*").over(Window.partitionBy("u_node")))
        part = F.pmod(F.xxhash64("v_node"), F.ceil(F.col("many") / RUN_TARGETS))
    wanted = wanted.groupBy("u_node", part.alias("part")).agg(F.array_sort(F.collect_list("v_node")).alias("targets"))
    runs = wanted.select(F.abs(F.xxhash64("u_node", "targets")).alias("run"), F.col("u_node").alias("source"), "targets", F.lit(opts.limit).alias("radius"))
    found = search.paths(net.edges, runs, net.nodes, net.load()).withColumn("u_node", F.col("path")[0]).withColumnRenamed("target", "v_node")
    if cache is not None:
        held = cache.where((F.col("limit") >= opts.limit) & F.col("cost").isNotNull())
        found = found.unionByName(held.select("u_node", "v_node", "cost", "path", "settled", F.lit(None).cast("long").alias("run")))
    found = found.groupBy("u_node", "v_node").agg(F.min(F.struct("cost", "settled", "run", "path")).alias("m")).select("u_node", "v_node", "m.cost", "m.path", "m.settled", "m.run")
    return pairs.join(found, ["u_node", "v_node"]).where(F.col("cost") <= opts.limit).select("trip", "layer", "u", "v", "u_node", "v_node", "cost", "path", "settled", "run")


def leg_cache(stops: DataFrame, found: DataFrame, opts: TripOptions) -> DataFrame:
    """u_node, v_node, limit, cost, path, settled of every pair that was asked for; cost is null where no leg is within the limit."""
    a = stops.select("trip", "layer", F.col("id").alias("u"), F.col("node").alias("u_node"))
    b = stops.select("trip", (F.col("layer") - 1).alias("layer"), F.col("id").alias("v"), F.col("node").alias("v_node"))
    asked = a.join(b, ["trip", "layer"]).where("u <> v").select("u_node", "v_node").distinct()
    known = found.groupBy("u_node", "v_node").agg(F.min(F.struct("cost", "path", "settled")).alias("m")).select("u_node", "v_node", "m.cost", "m.path", "m.settled")
    return asked.join(known, ["u_node", "v_node"], "left").select("u_node", "v_node", F.lit(opts.limit).cast("long").alias("limit"), "cost", "path", "settled")


def adjusted(cost, last, opts: TripOptions):
    """An edge's cost with charging; last tells whether it ends at the target."""
    part = cost * (opts.capacity + opts.penalty) / opts.capacity
    if opts.penalty_mode == "none":
        return cost.cast("double")
    if opts.penalty_mode == "flat":
        return (cost + F.when(last, 0).otherwise(opts.penalty)).cast("double")
    if opts.penalty_mode == "proportional_no_last":
        return F.when(last, cost.cast("double")).otherwise(part)
    return part


def process_edges(found: DataFrame, opts: TripOptions) -> DataFrame:
    """legs -> trip, layer, u, v, weight, weight_adj."""
    return found.select("trip", "layer", "u", "v", F.col("cost").alias("weight"), adjusted(F.col("cost"), F.col("v") == TARGET, opts).alias("weight_adj"))


_CHAIN = "trip long, layer int, u long, v long, weight long, weight_adj double"


def _best_chain(pdf: pd.DataFrame, by: str) -> pd.DataFrame:
    """The cheapest chain of one trip's process edges, layer by layer; ties go to the smaller station."""
    best, came = {(0, SOURCE): 0}, {}
    for row in pdf.sort_values(["layer", "u", "v"]).itertuples():
        before = best.get((row.layer, row.u))
        if before is None:
            continue
        at, total = (row.layer + 1, row.v), before + getattr(row, by)
        if at not in best or total < best[at]:
            best[at], came[at] = total, row
    ends = [at for at in came if at[1] == TARGET]
    rows = []
    for at in ends:
        while at in came:
            row = came[at]
            rows.append(row)
            at = (row.layer, row.u)
    return pd.DataFrame([(r.trip, r.layer, r.u, r.v, r.weight, r.weight_adj) for r in rows], columns=["trip", "layer", "u", "v", "weight", "weight_adj"])


def final_path(edges: DataFrame, by: str = "weight", mode: str = "group") -> DataFrame:
    """process edges -> trip, layer, u, v, weight, weight_adj of the best chain; ties go to the smaller station.

    ``group`` solves each trip's process graph (n * n * m edges at most) in one
    call; ``layers`` is the same dynamic program as joins, all trips at once;
    ``sssp`` is a plain shortest path over the process graph by the frontier
    search; ``udtf`` a table function over trips in SQL.
    """
    if mode == "layers":
        return _final_layers(edges, by)
    if mode == "sssp":
        return _final_sssp(edges, by)
    if mode == "udtf":
        return _final_udtf(edges, by)
    return edges.groupBy("trip").applyInPandas(lambda pdf: _best_chain(pdf, by), _CHAIN)


def _final_udtf(edges: DataFrame, by: str) -> DataFrame:
    spark = edges.sparkSession

    @F.udtf(returnType=_CHAIN)
    class SolveProcess:
        def __init__(self) -> None:
            self.rows = []

        def eval(self, row) -> None:
            self.rows.append((row["trip"], row["layer"], row["u"], row["v"], row["weight"], row["weight_adj"]))

        def terminate(self):
            pdf = pd.DataFrame(self.rows, columns=["trip", "layer", "u", "v", "weight", "weight_adj"])
            for row in _best_chain(pdf, by).itertuples(index=False):
                yield tuple(x.item() if isinstance(x, np.generic) else x for x in row)

    spark.udtf.register("solve_process", SolveProcess)
    edges.createOrReplaceTempView("process_edges_of_trips")
    return spark.sql("SELECT * FROM solve_process(TABLE(process_edges_of_trips) PARTITION BY trip ORDER BY (layer, u, v))")


def _final_sssp(edges: DataFrame, by: str) -> DataFrame:
    """Places are numbered in the order of trip, layer and station, so that the least predecessor is the smaller station."""
    if by != "weight":
        raise ValueError("the plain search takes whole weights")
    edges = cut(edges)
    ends = edges.select("trip", "layer", F.col("u").alias("id")).union(edges.select("trip", F.col("layer") + 1, "v")).distinct()
    ends = cut(ends.withColumn("at", F.row_number().over(Window.partitionBy("trip").orderBy("layer", "id")).cast("long")))
    a, b = ends.select("trip", "layer", F.col("id").alias("u"), F.col("at").alias("a")), ends.select("trip", (F.col("layer") - 1).alias("layer"), F.col("id").alias("v"), F.col("at").alias("b"))
    # A trip's places get a range of their own: its number times the most places of any trip.
    most = ends.agg(F.max("at")).first()[0] or 1
    trips = ends.select("trip").distinct().withColumn("nth", F.row_number().over(Window.orderBy("trip")).cast("long"))
    arcs = cut(edges.join(a, ["trip", "layer", "u"]).join(b, ["trip", "layer", "v"]).join(trips, "trip").withColumns({"src": F.col("nth") * (most + 1) + F.col("a"), "dst": F.col("nth") * (most + 1) + F.col("b")}))
    runs = arcs.where(F.col("u") == SOURCE).select(F.col("trip").alias("run"), F.col("src").alias("source"), F.lit(None).cast("long").alias("radius")).distinct()
    goal = arcs.where(F.col("v") == TARGET).select(F.col("trip").alias("run"), F.col("dst").alias("target")).distinct()
    found = search._frontier_reach(arcs.select("src", "dst", "weight"), runs)
    walk = search.backtrace(found, goal.join(found.select("run", F.col("node").alias("target")), ["run", "target"]))
    order = Window.partitionBy("run").orderBy("cum")
    hops = walk.select(F.col("run").alias("trip"), F.lag("node").over(order).alias("src"), F.col("node").alias("dst")).where("src IS NOT NULL")
    return hops.join(arcs, ["trip", "src", "dst"]).select("trip", "layer", "u", "v", "weight", "weight_adj")


def _final_layers(edges: DataFrame, by: str) -> DataFrame:
    """Later layers are joined to the best costs of the earlier ones, all trips at once.

    A place's row carries the places of its best chain, so only the newest layer and the
    chains that are done are kept, and no plan grows with the number of layers.
    """
    edges = cut(edges)
    last = edges.agg(F.max("layer")).first()[0]
    if last is None:
        return edges
    # No number of a layer stands in a plan, so all rounds share their compiled code, and each names the state once.
    ahead = edges.select("trip", "layer", F.col("u").alias("at"), F.col("v").alias("to"), F.col(by).alias("more"))
    state = edges.where("layer = 0").select("trip", F.lit(1).alias("layer"), F.col("v").alias("at"), F.col(by).alias("total"), F.array("u").alias("chain"))
    on = F.col("to").isNotNull()
    for k in range(1, last + 1):
        step = state.join(ahead, ["trip", "layer", "at"], "left").where(on | (F.col("at") == TARGET))
        # What has arrived waits; its chain ends before the target.
        step = step.select("trip", F.when(on, F.col("layer") + 1).otherwise(F.col("layer")).alias("layer"), F.coalesce("to", "at").alias("next"), F.when(on, F.col("total") + F.col("more")).otherwise(F.col("total")).alias("total"), "at", F.when(on, F.concat("chain", F.array("at"))).otherwise(F.col("chain")).alias("chain"))
        state = step.groupBy("trip", "layer", F.col("next").alias("at")).agg(F.min(F.struct("total", step["at"], "chain")).alias("m")).select("trip", "layer", "at", "m.total", "m.chain")
        if k % LAYERS == 0:
            state = cut_size(state)
    ends = cut_size(state.where(F.col("at") == TARGET).select("trip", "chain"))
    after = F.concat(F.slice("chain", 2, F.size("chain")), F.array(F.lit(TARGET).cast("long")))
    steps = ends.select("trip", F.posexplode(F.arrays_zip(F.col("chain").alias("u"), after.alias("v"))).alias("layer", "e"))
    return steps.select("trip", "layer", "e.u", "e.v").join(edges, ["trip", "layer", "u", "v"])


def solution(chain: DataFrame, found: DataFrame, opts: TripOptions) -> DataFrame:
    """One row a leg: trip, leg_index, station (null at the target), costs and running costs, path."""
    run = Window.partitionBy("trip").orderBy("layer").rowsBetween(Window.unboundedPreceding, 0)
    rows = chain.join(found.select("trip", "layer", "u", "v", "path"), ["trip", "layer", "u", "v"])
    return rows.select(
        "trip", F.col("layer").alias("leg_index"), F.when(F.col("v") != TARGET, F.col("v")).alias("station"), F.col("weight").alias("leg_cost"), F.col("weight_adj").alias("leg_cost_adj"),
        F.sum("weight").over(run).alias("cum_cost"), F.sum("weight_adj").over(run).alias("cum_cost_adj"), "path")


def aggregated(legs_of: DataFrame) -> DataFrame:
    """One row a trip: total costs, stations, the whole path with joints once."""
    parts = legs_of.groupBy("trip").agg(F.sum("leg_cost").alias("cost"), F.sum("leg_cost_adj").alias("cost_adj"), F.array_sort(F.collect_list(F.struct("leg_index", "station", "path"))).alias("s"))
    path = F.flatten(F.transform("s", lambda x, i: F.when(i == 0, x["path"]).otherwise(F.slice(x["path"], 2, F.greatest(F.size(x["path"]) - 1, F.lit(0))))))
    return parts.select("trip", "cost", "cost_adj", F.filter("s.station", lambda x: x.isNotNull()).alias("stations"), path.alias("path"))


@dataclass
class Plan:
    """Every step of a batch of trips."""

    path: DataFrame
    bases: DataFrame
    candidates: DataFrame
    layers: DataFrame
    legs: DataFrame
    edges: DataFrame
    chain: DataFrame
    solution: DataFrame
    status: DataFrame


def plan_trips(net: Net, trips: DataFrame, opts: TripOptions, clock=None, cache: DataFrame | None = None) -> Plan:
    """Plans of trips(trip, source, target). Each step is cut, as several later ones read it.

    ``clock(name)`` is called when a step is done; ``cache`` holds legs of earlier batches.
    """
    tick = clock or (lambda name: None)
    trips = cut(trips.select("trip", "source", "target"))
    net.load(), net.load_stations()
    tick("load")
    path = cut(initial_path(net, trips))
    tick("initial path")
    bases = cut(split_bases(path, opts))
    tick("cut")
    candidates = cut(find_candidates(net, bases, opts))
    if opts.mitigation == "slide":
        candidates = cut(candidates.unionByName(slide(net, path, bases, candidates, opts)))
    tick("candidates")
    stops = cut(layers(trips.join(path.select("trip"), "trip", "left_semi"), bases, candidates))
    found = cut(legs(net, stops, opts, cache))
    tick("legs")
    edges = process_edges(found, opts)
    chain = cut(final_path(edges, "weight_adj" if opts.penalty_mode == "proportional_no_last" else "weight", opts.final))
    tick("final path")
    return Plan(path, bases, candidates, stops, found, edges, chain, solution(chain, found, opts), status(trips, path, stops, chain, opts))


def cut_points(cum: np.ndarray, opts: TripOptions) -> list[int]:
    """Positions where a path of running costs ``cum`` is cut, as ``split_bases`` has them."""
    cost, step = int(cum[-1]), opts.step
    tail = opts.capacity if opts.tail_rule == "capacity" else step
    if opts.direct_if_within and cost <= opts.capacity:
        return []
    if opts.split_rule == "multiples":
        kind = -(-cum // step)
        last = np.flatnonzero(np.r_[kind[1:] != kind[:-1], True])
        return [int(k) for k in last if 0 < cum[k] < cost and cost - (kind[k] - 1) * step > tail]
    out, base, at = [], 0, 0
    while cost - base > tail:
        at = max(at, int(np.searchsorted(cum, base + step, "right")))
        if at >= len(cum):
            break
        k = at - 1 if cum[at - 1] > base else at  # else one edge passes the step
        if cum[k] < cost:
            base = int(cum[k])
            out.append(k)
        at += 1
    return out


def _routes(there, trips: DataFrame, opts: TripOptions) -> DataFrame:
    """trip, source, target, cost, steep (an edge passes the limit), bases: of all trips that have a path, by tables of cells."""

    def solved(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        pdf, own = pd.concat([pd.DataFrame({"trip": [], "source": [], "target": []}, dtype="int64"), *batches], ignore_index=True), there.value
        (s, known), (t, also) = (own.at(pdf[c].to_numpy(dtype=np.int64)) for c in ("source", "target"))
        alone = pdf[~(known & also) & (pdf["source"] == pdf["target"])]
        yield alone.assign(cost=0, steep=False, bases=pd.Series([[] for _ in range(len(alone))], index=alone.index, dtype=object))
        pdf, s, t = pdf[known & also], s[known & also], t[known & also]
        order = np.argsort(s, kind="stable")
        pdf, s, t = pdf.iloc[order], s[order], t[order]
        sources, nth = np.unique(s, return_inverse=True)
        for k in range(0, len(sources), step := own.sources_at_once()):
            lo, hi = np.searchsorted(nth, [k, k + step])
            dist = own.distances(sources[k : k + step])
            near = np.flatnonzero(dist[t[lo:hi], nth[lo:hi] - k] < own.FAR)
            pair, at, cum = own.routes(dist, nth[lo:hi][near] - k, t[lo:hi][near])
            rows, nodes = [], own.nodes[at]
            for a, b in zip(*(np.searchsorted(pair, np.arange(len(near)) + c) for c in (0, 1)), strict=True):
                way = cum[a:b]
                rows.append((int(way[-1]), bool(np.diff(way).max(initial=0) > opts.limit), nodes[a:b][cut_points(way, opts)].tolist()))
            out = pdf.iloc[lo:hi].iloc[near].reset_index(drop=True)
            yield out.assign(cost=[r[0] for r in rows], steep=[r[1] for r in rows], bases=pd.Series([r[2] for r in rows], dtype=object))

    return search.spread(trips, "source").mapInPandas(solved, "trip long, source long, target long, cost long, steep boolean, bases array<long>")


class Choices:
    """The candidates of every base, and what legs between their nodes cost, in arrays."""

    def __init__(self, bases: np.ndarray, stations: np.ndarray, nodes: np.ndarray) -> None:
        order = np.argsort(bases, kind="stable")
        self.bases, first = np.unique(bases[order], return_index=True)
        self.lo = np.r_[first, len(bases)]
        self.station, self.node = stations[order], nodes[order]

    def add(self, from_: np.ndarray, to: np.ndarray, cost: np.ndarray) -> Choices:
        """With legs, by one ascending number a pair of nodes."""
        (self.from_, a), (self.to, b) = (np.unique(v, return_inverse=True) for v in (from_, to))
        pair = a.astype(np.int64) * max(1, len(self.to)) + b
        order = np.argsort(pair)
        self.pair, self.cost = pair[order], cost[order].astype(np.int64)
        return self

    def of(self, bases: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """(stations, nodes) of bases, a row each; -1 where there are fewer than n."""
        if not len(self.bases):
            return (np.full((len(bases), n), -1, dtype=np.int64),) * 2
        k = np.minimum(np.searchsorted(self.bases, bases), len(self.bases) - 1)
        at = self.lo[k][:, None] + np.arange(n)
        have = (self.bases[k] == bases)[:, None] & (at < self.lo[k + 1][:, None])
        at = np.where(have, at, 0)
        return np.where(have, self.station[at], -1), np.where(have, self.node[at], -1)

    def legs(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        """Costs of legs between nodes; FAR where there is none."""
        if not len(self.pair):
            return np.full(np.broadcast_shapes(u.shape, v.shape), search.FAR)
        a, b = np.minimum(np.searchsorted(self.from_, u), len(self.from_) - 1), np.minimum(np.searchsorted(self.to, v), len(self.to) - 1)
        want = a * len(self.to) + b
        k = np.minimum(np.searchsorted(self.pair, want), len(self.pair) - 1)
        return np.where((self.pair[k] == want) & (self.from_[a] == u) & (self.to[b] == v), self.cost[k], search.FAR)


def _layered(routes: pd.DataFrame, choices: Choices, n: int) -> Iterator[tuple[np.ndarray, int, int, tuple, tuple]]:
    """(rows, bases, layer, places before, places after) between any two layers of trips with equal numbers of bases; places are (ids, nodes), -1 none."""
    many = routes["bases"].map(len).to_numpy()
    for m in np.unique(many):
        rows = np.flatnonzero(many == m)
        own = routes.iloc[rows]
        ends = [(np.full((len(rows), 1), k, dtype=np.int64), own[c].to_numpy()[:, None]) for k, c in ((SOURCE, "source"), (TARGET, "target"))]
        bases = np.array(own["bases"].tolist(), dtype=np.int64).reshape(len(rows), m)
        before = ends[0]
        for layer in range(m + 1):
            after = choices.of(bases[:, layer], n) if layer < m else ends[1]
            yield rows, m, layer, before, after
            before = after


def costs_of(net: Net, trips: DataFrame, opts: TripOptions, single: int | None = None) -> DataFrame:
    """trip, status, cost, direct of plans of very many trips, without the paths of legs.

    The same rows as the steps of ``plan_trips`` give: initial paths by tables of
    cells, candidates once a base, legs once a pair of places, searched from the
    stations, and the layered program over arrays of trips. Few trips, and what
    has no such form, go through ``plan_trips``.
    """
    trips = cut(trips.select("trip", "source", "target"))
    loaded = net.load()
    there = None
    if loaded is not None and net.load_stations() is not None and opts.mitigation == "none" and opts.penalty_mode != "proportional_no_last":
        there = separators.closed(loaded, trips.count(), single)
    if there is None:
        plan = plan_trips(net, trips, opts)
        cost = plan.solution.groupBy("trip").agg(F.sum("leg_cost").alias("cost"))
        return plan.status.join(cost, "trip", "left").join(plan.path.select("trip", F.col("cost").alias("direct")), "trip", "left")
    spark = trips.sparkSession
    there = spark.sparkContext.broadcast(there)
    routes = cut(_routes(there, trips, opts))
    there.unpersist()
    bases = routes.select(F.explode("bases").alias("node")).distinct().select(F.col("node").alias("trip"), F.lit(1).alias("stop"), "node")
    # Cut first: gathering makes a partition or two at a time.
    known = Choices(*search.gathered(cut(find_candidates(net, bases, opts).select("trip", "station", "node"))))
    choices = spark.sparkContext.broadcast(known)
    n, limit, back = opts.n, opts.limit, net.load_back()

    def asked(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            parts = [pd.DataFrame({"u": [], "v": [], "back": []}, dtype="int64")]
            for _, m, layer, (u, a), (v, b) in _layered(pdf, choices.value, n):
                if m:  # else the leg is the direct path
                    held = ((u[:, :, None] != -1) | (layer == 0)) & (v[:, None, :] != -1) & (u[:, :, None] != v[:, None, :])
                    from_, to = (c[held] for c in np.broadcast_arrays(a[:, :, None], b[:, None, :]))
                    parts.append(pd.DataFrame({"u": from_, "v": to, "back": int(layer == 0)}).drop_duplicates())
            yield pd.concat(parts).drop_duplicates()

    def searched(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for place, other, turned in zip(pdf["place"], pdf["other"], pdf["back"], strict=True):
                found = search.bounded((back if turned else loaded).value, int(place), limit, other.tolist(), history=False)
                got = [(v, d) for v in other.tolist() if (d := found.dist.get(v)) is not None]
                rows = pd.DataFrame(got, columns=["v", "cost"], dtype="int64").assign(u=place)
                yield rows.rename(columns={"u": "v", "v": "u"}) if turned else rows

    # A source's legs are searched back from its stations, which are fewer.
    wanted = routes.mapInPandas(asked, "u long, v long, back long").distinct()
    place, other = (F.when(F.col("back") == 1, F.col(a)).otherwise(F.col(b)) for a, b in (("v", "u"), ("u", "v")))
    runs = wanted.select("back", place.alias("place"), other.alias("other")).groupBy("place", "back").agg(F.collect_list("other").alias("other"))
    found = search.spread(runs, "place").mapInPandas(searched, "u long, v long, cost long")
    ready = spark.sparkContext.broadcast(known.add(*search.gathered(cut(found))))

    def solved(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            name, cost = np.full(len(pdf), "no_leg_chain", dtype=object), np.full(len(pdf), search.FAR)
            direct = pdf["cost"].to_numpy()
            for rows, m, layer, (u, a), (v, b) in _layered(pdf, ready.value, n):
                if m == 0:
                    cost[rows] = np.where(direct[rows] <= limit, direct[rows], search.FAR)
                    continue
                way = np.where((u[:, :, None] == v[:, None, :]) | (v[:, None, :] == -1), search.FAR, ready.value.legs(a[:, :, None], b[:, None, :]))
                total = way[:, 0] if layer == 0 else np.minimum((total[:, :, None] + way).min(axis=1), search.FAR)
                cost[rows] = total[:, 0]
                name[rows[(v == -1).all(axis=1)]] = "no_candidate"
            name[pdf["steep"].to_numpy()] = "edge_exceeds_capacity"
            name[cost < search.FAR] = "ok"
            yield pd.DataFrame({"trip": pdf["trip"], "status": name, "cost": pd.Series(cost, index=pdf.index).astype("Int64").where(cost < search.FAR), "direct": pdf["cost"]})

    done = routes.mapInPandas(solved, "trip long, status string, cost long, direct long")
    return trips.select("trip").join(done, "trip", "left").fillna("no_path", ["status"])


def status(trips: DataFrame, path: DataFrame, stops: DataFrame, chain: DataFrame, opts: TripOptions) -> DataFrame:
    """trip, status: ok, no_path, edge_exceeds_capacity, no_candidate or no_leg_chain."""
    steep = F.exists(F.transform("cum", lambda c, i: c - F.coalesce(F.get("cum", i - 1), F.lit(0))), lambda w: w > opts.limit)
    known = path.select("trip", F.lit(True).alias("p"), steep.alias("steep"))
    ok = chain.where(F.col("v") == TARGET).select("trip", F.lit(True).alias("ok"))
    rows = trips.select("trip").join(known, "trip", "left").join(stops.select("trip", F.lit(True).alias("c")).distinct(), "trip", "left").join(ok, "trip", "left")
    name = F.when(F.col("ok"), "ok").when(F.col("p").isNull(), "no_path").when(F.col("steep"), "edge_exceeds_capacity").when(F.col("c"), "no_leg_chain").otherwise("no_candidate")
    return rows.select("trip", name.alias("status"))


def plan_mixed(net: Net, trips: DataFrame, opts: TripOptions, most: int = 200) -> Plan:
    """Plans of trips with options of their own: columns capacity, penalty, n or alpha override ``opts``.

    Trips of equal options go together; there may be ``most`` different ones.
    """
    own = [c for c in ("capacity", "penalty", "n", "alpha") if c in trips.columns]
    kinds = trips.select(*own).distinct().limit(most + 1).collect() if own else [None]
    if len(kinds) > most:
        raise ValueError(f"more than {most} different options")
    plans = []
    for kind in kinds:
        some = trips if kind is None else trips.where(" AND ".join(f"{c} <=> {kind[c]!r}" if kind[c] is not None else f"{c} IS NULL" for c in own))
        given = {c: kind[c] for c in own if kind[c] is not None} if kind is not None else {}
        plans.append(plan_trips(net, some, replace(opts, **given)))
    if not plans:
        return plan_trips(net, trips, opts)
    return Plan(*(reduce(DataFrame.unionByName, parts) for parts in zip(*(vars(p).values() for p in plans), strict=True)))


def edge_budget_published(n: int, m: int) -> int:
    return n * (n * m + 2)


def edge_count_layered(sizes: list[int]) -> int:
    """Edges of a layered graph with the given numbers of stations between two end points."""
    full = [1, *sizes, 1]
    return sum(a * b for a, b in zip(full, full[1:], strict=False))
