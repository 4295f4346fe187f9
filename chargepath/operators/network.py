"""Building road networks from segment tables, and their tiles."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from chargepath.operators.search import cut


def filter_road_classes(segs: DataFrame, drop=("R",)) -> DataFrame:
    return segs.where(~F.col("road_class").isin(*drop)) if drop else segs


def clip_region(segs: DataFrame, nodes: DataFrame, ring: list[tuple[float, float]]) -> DataFrame:
    """Segments whose both ends lie in a polygon (even-odd rule, box test first)."""
    xs, ys = [p[0] for p in ring], [p[1] for p in ring]
    crossings = F.lit(0)
    for (ax, ay), (bx, by) in zip(ring, [*ring[1:], ring[0]], strict=True):
        if ay != by:
            hit = ((F.lit(ay) > F.col("y")) != (F.lit(by) > F.col("y"))) & (F.col("x") < (bx - ax) * (F.col("y") - ay) / (by - ay) + ax)
            crossings = crossings + hit.cast("int")
    inside = nodes.where(F.col("x").between(min(xs), max(xs)) & F.col("y").between(min(ys), max(ys)) & (crossings % 2 == 1)).select("node")
    return segs.join(inside.select(F.col("node").alias("a")), "a", "left_semi").join(inside.select(F.col("node").alias("b")), "b", "left_semi").select(segs.columns)


def expand_direction(segs: DataFrame) -> DataFrame:
    """One directed edge for a one-way segment (O), two for a two-way one (F)."""
    ahead = F.struct(F.col("a").alias("src"), F.col("b").alias("dst"), "weight")
    back = F.struct(F.col("b").alias("src"), F.col("a").alias("dst"), "weight")
    return segs.select(F.explode(F.when(F.col("direction") == "F", F.array(ahead, back)).otherwise(F.array(ahead))).alias("e")).select("e.*")


def min_parallel(edges: DataFrame) -> DataFrame:
    """The cheapest of parallel edges; loops go."""
    return edges.where("src <> dst").groupBy("src", "dst").agg(F.min("weight").alias("weight"))


def assemble(tiles: list[DataFrame]) -> DataFrame:
    """One edge table from any number of segment tables that share nodes only."""
    return min_parallel(expand_direction(reduce(DataFrame.unionByName, tiles)))


def reverse(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight")


def validate(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """problem, n: null or unknown ends and weights below 1."""
    known = nodes.select("node")
    parts = [
        edges.where("src IS NULL OR dst IS NULL OR weight IS NULL").select(F.lit("null").alias("problem")),
        edges.where("weight < 1").select(F.lit("weight").alias("problem")),
        edges.join(known, edges["src"] == known["node"], "left_anti").select(F.lit("unknown src").alias("problem")),
        edges.join(known, edges["dst"] == known["node"], "left_anti").select(F.lit("unknown dst").alias("problem")),
    ]
    return reduce(DataFrame.union, parts).groupBy("problem").agg(F.count("*").alias("n"))


def plan_tiles(nodes: DataFrame, max_nodes: int, cells: int = 64) -> DataFrame:
    """tile, x0, y0, x1, y1, nodes: rectangles split at their median until each
    holds at most max_nodes nodes (or is one cell).

    Works on a histogram of at most cells x cells counts, so the nodes are read
    once and what reaches the driver is bounded by the number of cells.
    """
    lo = nodes.agg(F.min("x").alias("x0"), F.min("y").alias("y0"), F.max("x").alias("x1"), F.max("y").alias("y1")).first()
    if lo.x0 is None:
        return nodes.sparkSession.createDataFrame([], "tile long, x0 double, y0 double, x1 double, y1 double, nodes long")
    dx, dy = (lo.x1 - lo.x0) / cells or 1.0, (lo.y1 - lo.y0) / cells or 1.0
    i = F.least(F.floor((F.col("x") - lo.x0) / dx), F.lit(cells - 1))
    j = F.least(F.floor((F.col("y") - lo.y0) / dy), F.lit(cells - 1))
    count = {(r.i, r.j): r.n for r in nodes.groupBy(i.alias("i"), j.alias("j")).agg(F.count("*").alias("n")).collect()}
    open_, out = [(0, 0, cells, cells)], []
    while open_:
        a, b, c, d = open_.pop()
        own = [(k, v) for k, v in count.items() if a <= k[0] < c and b <= k[1] < d]
        total = sum(v for _, v in own)
        if total <= max_nodes or (c - a == 1 and d - b == 1):
            out.append((len(out), lo.x0 + a * dx, lo.y0 + b * dy, lo.x0 + c * dx, lo.y0 + d * dy, total))
            continue
        axis = 0 if (c - a) >= (d - b) else 1
        start, end = (a, c) if axis == 0 else (b, d)
        at, seen = start + 1, 0
        for k in range(start, end - 1):
            seen += sum(v for (x, y), v in own if (x, y)[axis] == k)
            at = k + 1
            if 2 * seen >= total:
                break
        open_ += [(a, b, at, d), (at, b, c, d)] if axis == 0 else [(a, b, c, at), (a, at, c, d)]
    return nodes.sparkSession.createDataFrame(out, "tile long, x0 double, y0 double, x1 double, y1 double, nodes long")


def assign_segments(segs: DataFrame, nodes: DataFrame, tiles: DataFrame) -> DataFrame:
    """segs + tile: that of the end a, so tiles share nodes and never segments.

    Tiles are a bounded list made on the driver, so the range join broadcasts them."""
    t = F.broadcast(tiles.groupBy().agg(F.collect_list(F.struct("tile", "x0", "y0", "x1", "y1")).alias("tiles"), F.max("x1").alias("mx"), F.max("y1").alias("my")))
    at = nodes.crossJoin(t).select(F.col("node").alias("a"), F.filter("tiles", lambda r: (
        (F.col("x") >= r["x0"]) & ((F.col("x") < r["x1"]) | (r["x1"] >= F.col("mx"))) & (F.col("y") >= r["y0"]) & ((F.col("y") < r["y1"]) | (r["y1"] >= F.col("my")))))[0]["tile"].alias("tile"))
    return segs.join(at, "a").select(*segs.columns, "tile")


def shared_nodes(assigned: DataFrame) -> DataFrame:
    """node, tiles: nodes that are ends in two tiles or more."""
    ends = assigned.select("tile", F.explode(F.array("a", "b")).alias("node"))
    return ends.groupBy("node").agg(F.count_distinct("tile").alias("tiles")).where("tiles > 1")


def tile_adaptive(nodes: DataFrame, max_nodes: int) -> DataFrame:
    """nodes(node, x, y) -> node, x, y, tile: each tile over the threshold is cut at the exact median
    of its longer side, until none is; the exact form beside the histogram.

    A tile is a number whose bits are the sides taken. Nodes at one point stay
    together, so a point with more nodes than the threshold is a tile.
    """
    state = cut(nodes.select("node", "x", "y", F.lit(1).cast("long").alias("tile"), F.lit(True).alias("open")))
    while True:
        size = state.where("open").groupBy("tile").agg(
            F.count("*").alias("n"), (F.max("x") - F.min("x")).alias("w"), (F.max("y") - F.min("y")).alias("h"),
            F.percentile("x", 0.5).alias("mx"), F.percentile("y", 0.5).alias("my"), F.min("x").alias("x0"), F.min("y").alias("y0"))
        size = cut(size.withColumn("split", (F.col("n") > max_nodes) & ((F.col("w") > 0) | (F.col("h") > 0))))
        if size.where("split").isEmpty():
            return state.select("node", "x", "y", "tile")
        over = size.where("split").select("tile", (F.col("w") >= F.col("h")).alias("wide"), "mx", "my", "x0", "y0")
        rows = state.join(over, "tile", "left")
        # At the median, unless all of the lower half lies on the border itself.
        at = lambda c, m, lo: F.when(F.col(m) > F.col(lo), F.col(c) >= F.col(m)).otherwise(F.col(c) > F.col(lo))
        right = F.when(F.col("wide"), at("x", "mx", "x0")).otherwise(at("y", "my", "y0"))
        state = cut(rows.select("node", "x", "y", F.when(right.isNull(), F.col("tile")).otherwise(2 * F.col("tile") + right.cast("long")).alias("tile"), right.isNotNull().alias("open")))


def tile_contract(assigned: DataFrame) -> DataFrame:
    """problem, n: segments that lie in two tiles or in none; nothing where tiles share nodes only."""
    twice = assigned.groupBy("seg_id").agg(F.count_distinct("tile").alias("t")).where("t > 1").select(F.lit("segment in two tiles").alias("problem"))
    none = assigned.where("tile IS NULL").select(F.lit("segment without a tile").alias("problem"))
    return twice.union(none).groupBy("problem").agg(F.count("*").alias("n"))


def dense_ids(rows: DataFrame, order: list[str], name: str) -> DataFrame:
    """rows + name: 0, 1, ... in the order of columns, by range partitions and their counts; no single task sorts all."""
    parts = cut(rows.repartitionByRange(*order).sortWithinPartitions(*order).select("*", F.spark_partition_id().alias("_part"), F.monotonically_increasing_id().alias("_row")))
    sizes = parts.groupBy("_part").agg(F.count("*").alias("_n"), F.min("_row").alias("_first"))  # one row a partition
    starts = sizes.select("_part", "_first", (F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).alias("_start"))
    return parts.join(F.broadcast(starts), "_part").withColumn(name, F.col("_start") + F.col("_row") - F.col("_first")).drop("_part", "_row", "_first", "_start")


def index_endpoints(segs: DataFrame, digits: int = 6) -> tuple[DataFrame, DataFrame]:
    """segs(ax, ay, bx, by, ...) -> (nodes(node, x, y), segs with a and b).

    Ends whose coordinates agree to ``digits`` decimals are one node, which is
    all that joins tiles; nodes are numbered in the order of x, y.
    """
    r = lambda c: (F.round(F.col(c), digits) + F.lit(0.0)).alias(c)  # noqa: E731  (adding 0.0 turns -0.0 round)
    rows = segs.select(*[c for c in segs.columns if c not in ("ax", "ay", "bx", "by")], r("ax"), r("ay"), r("bx"), r("by"))
    ends = rows.select(F.col("ax").alias("x"), F.col("ay").alias("y")).union(rows.select("bx", "by")).distinct()
    nodes = dense_ids(ends, ["x", "y"], "node").select("node", "x", "y")
    a, b = nodes.select(F.col("node").alias("a"), F.col("x").alias("ax"), F.col("y").alias("ay")), nodes.select(F.col("node").alias("b"), F.col("x").alias("bx"), F.col("y").alias("by"))
    return nodes, rows.join(a, ["ax", "ay"]).join(b, ["bx", "by"]).drop("ax", "ay", "bx", "by")


def write_network(edges: DataFrame, path: str) -> None:
    """edges(tile, src, dst, weight) as Parquet, a folder a tile, sorted by src: a fixed topology that is read tile by tile."""
    edges.repartition("tile").sortWithinPartitions("tile", "src", "dst").write.mode("overwrite").partitionBy("tile").parquet(path)


def read_network(spark: SparkSession, path: str, tiles: list[int] | None = None) -> DataFrame:
    """One scan of the stored tiles; only the folders of ``tiles`` are read where they are named."""
    rows = spark.read.schema("src long, dst long, weight long, tile long").parquet(path)
    return rows if tiles is None else rows.where(F.col("tile").isin(*tiles))


def bucket_network(edges: DataFrame, name: str, buckets: int) -> None:
    """The same as a table bucketed by src, so that joins of a frontier on src move only the frontier."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "dst").saveAsTable(name)


@dataclass(frozen=True)
class ColumnRoles:
    """Which columns of a segment table play which part; ends by number or by coordinates."""

    weight: str = "weight"
    direction: str | None = "direction"
    road_class: str | None = "road_class"
    ends: tuple[str, ...] = ("a", "b")  # or four coordinate columns
    wkt: str | None = None  # a LINESTRING column instead of ends


@dataclass(frozen=True)
class NetworkSpec:
    """What a network is built from; the region is a ring of (x, y) or a POLYGON text."""

    roles: ColumnRoles = ColumnRoles()
    drop: tuple[str, ...] = ("R",)
    region: object = None
    max_nodes: int | None = None  # of a tile; None leaves the network whole
    view: str | None = None  # name of SQL views <view>_edges and <view>_nodes


@dataclass
class Built:
    nodes: DataFrame
    segments: DataFrame
    edges: DataFrame
    tiles: DataFrame | None


def build_network(segs: DataFrame, spec: NetworkSpec, nodes: DataFrame | None = None) -> Built:
    """One call from segment rows to a checked network.

    Columns are read by their roles, classes dropped, ends made nodes where they
    are coordinates, the region clipped, tiles cut and put together again, and
    the result is validated. With ``view`` it can be queried in SQL.
    """
    from chargepath.functions.sql import parse_linestring, parse_ring

    roles = spec.roles
    direction = F.col(roles.direction) if roles.direction else F.lit("F")
    road = F.col(roles.road_class) if roles.road_class else F.lit("")
    base = [direction.alias("direction"), road.alias("road_class"), F.col(roles.weight).cast("long").alias("weight")]
    if roles.wkt is not None:
        line = parse_linestring(F.col(roles.wkt))
        ends = [line[0]["x"].alias("ax"), line[0]["y"].alias("ay"), F.element_at(line, -1)["x"].alias("bx"), F.element_at(line, -1)["y"].alias("by")]
    else:
        names = ("a", "b") if len(roles.ends) == 2 else ("ax", "ay", "bx", "by")
        ends = [F.col(c).alias(n) for c, n in zip(roles.ends, names, strict=True)]
    rows = filter_road_classes(segs.select(*ends, *base), spec.drop)
    if roles.wkt is not None or len(roles.ends) == 4:
        nodes, rows = index_endpoints(rows)
        nodes, rows = cut(nodes), cut(rows)
    if nodes is None:
        raise ValueError("segments with numbered ends need a table of nodes")
    if spec.region is not None:
        ring = parse_ring(spec.region) if isinstance(spec.region, str) else spec.region
        rows = clip_region(rows, nodes, ring)
    tiles = None
    if spec.max_nodes is not None:
        tiles = plan_tiles(nodes, spec.max_nodes)
        rows = assign_segments(rows, nodes, tiles)
    edges = assemble([rows])
    problems = validate(edges, nodes).collect()  # four kinds at most
    if problems:
        raise ValueError(f"the network is not sound: {[tuple(p) for p in problems]}")
    if spec.view:
        edges.createOrReplaceTempView(f"{spec.view}_edges")
        nodes.createOrReplaceTempView(f"{spec.view}_nodes")
    return Built(nodes, rows, edges, tiles)


def network_stats(nodes: DataFrame, edges: DataFrame, tiles: DataFrame | None = None) -> DataFrame:
    """One row: nodes, edges, tiles, most nodes of a tile, bytes of the compact form (24 an edge, 24 a node)."""
    out = nodes.agg(F.count("*").alias("nodes")).crossJoin(edges.agg(F.count("*").alias("edges")))
    of = tiles.agg(F.count("*").alias("tiles"), F.max("nodes").alias("most_nodes")) if tiles is not None else nodes.sparkSession.sql("SELECT 0L AS tiles, 0L AS most_nodes")
    return out.crossJoin(of).withColumn("bytes", 24 * F.col("nodes") + 24 * F.col("edges"))  # rows of one
