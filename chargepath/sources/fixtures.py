"""Networks, stations and trips derived from the given tables, in integers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_COUNTS: dict[tuple[str, str], int] = {}


def size(spark: SparkSession, sf_dir: str, name: str = "customer") -> tuple[int, int, int]:
    """(nodes, columns, full rows) of the lattice over a table, which is counted once."""
    n = _COUNTS.get((sf_dir, name))
    if n is None:
        n = _COUNTS[sf_dir, name] = table(spark, sf_dir, name).count()
    w = 1
    while w * w * 2 < 3 * n:
        w += 1
    return n, w, n // w


def cents(column):
    return F.round(column * 100).cast("long") + 100_000


def nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """node, x, y of the customer lattice."""
    _, w, _ = size(spark, sf_dir)
    key = F.col("c_custkey")
    return table(spark, sf_dir, "customer").select(key.alias("node"), (key % w).cast("double").alias("x"), F.floor(key / w).cast("double").alias("y"))


def edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """src, dst, weight: to the four neighbours; what a step costs depends on where it ends."""
    n, w, _ = size(spark, sf_dir)
    key = F.col("c_custkey")
    into = table(spark, sf_dir, "customer").select(key.alias("dst"), (300 + cents(F.col("c_acctbal")) % 301).alias("weight"))
    column = F.col("dst") % w
    near = F.array(F.when(column > 0, F.col("dst") - 1), F.when(column < w - 1, F.col("dst") + 1), F.col("dst") - w, F.col("dst") + w)
    out = into.select(F.explode(near).alias("src"), "dst", "weight")
    return out.where((F.col("src") >= 0) & (F.col("src") < n))


def stations(spark: SparkSession, sf_dir: str, dense: bool = False) -> DataFrame:
    """station, node, x, y, plug; dense takes parts instead of suppliers."""
    _, w, h = size(spark, sf_dir)
    if dense:
        rows = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("station"), (F.col("p_partkey") * 7919 + F.col("p_size") * 104_729).alias("v"), F.lit(None).cast("string").alias("plug"))
    else:
        s, n, r = (table(spark, sf_dir, t) for t in ("supplier", "nation", "region"))
        rows = s.join(n, F.col("s_nationkey") == F.col("n_nationkey"), "left").join(r, F.col("n_regionkey") == F.col("r_regionkey"), "left").select(
            F.col("s_suppkey").alias("station"), cents(F.col("s_acctbal")).alias("v"), F.col("r_name").alias("plug"))
    x, y = F.col("v") % w, F.floor(F.col("v") / h) % h
    return rows.select("station", (y * w + x).alias("node"), x.cast("double").alias("x"), y.cast("double").alias("y"), "plug")


def corner_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, w, h = size(spark, sf_dir)
    return spark.createDataFrame([(0, 0, w * h - 1)], "trip long, source long, target long")


def batch_trips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """trip, source, target of every urgent order."""
    n, _, _ = size(spark, sf_dir)
    rows = table(spark, sf_dir, "orders").where(F.col("o_orderpriority") == "1-URGENT")
    rows = rows.select(F.col("o_orderkey").alias("trip"), F.col("o_custkey").alias("source"), ((31 * F.col("o_custkey") + 17 * F.col("o_orderkey") + 7) % n).alias("target"))
    return rows.where("source <> target")


def depots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """nation, node: the first customer of each nation."""
    return table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.min("c_custkey").alias("node"))


def depot_trips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """trip, source, target between the depots of any two nations: pairs all over the map."""
    d = depots(spark, sf_dir)
    a, b = d.select(F.col("nation").alias("a"), F.col("node").alias("source")), d.select(F.col("nation").alias("b"), F.col("node").alias("target"))
    return a.join(F.broadcast(b), F.col("a") != F.col("b")).select((F.col("a") * 1000 + F.col("b")).cast("long").alias("trip"), "source", "target")  # nations are few


#: Capacity of a vehicle by its order's priority.
CAPACITIES = {"1-URGENT": 10_000, "2-HIGH": 9_000, "3-MEDIUM": 8_000, "4-NOT SPECIFIED": 12_000, "5-LOW": 15_000}


def mixed_trips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The trips between depots with capacities of their own."""
    by = F.array(*[F.lit(q) for q in CAPACITIES.values()])
    return depot_trips(spark, sf_dir).withColumn("capacity", F.get(by, (F.col("trip") % len(CAPACITIES)).cast("int")))


def segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """a, b, road_class, direction, weight of the order network."""
    n, w, _ = size(spark, sf_dir, "orders")
    side, a = F.col("l_partkey") % 4, F.col("l_orderkey")
    b = F.when(side == 0, a + 1).when(side == 1, a + w).when(side == 2, a - 1).otherwise(a - w)
    rows = table(spark, sf_dir, "lineitem").select(
        a.alias("a"), b.alias("b"), side.alias("side"), F.col("l_returnflag").alias("road_class"), F.col("l_linestatus").alias("direction"), (60 + 10 * F.col("l_quantity")).cast("long").alias("weight"))
    wraps = ((F.col("side") == 0) & (F.col("a") % w == w - 1)) | ((F.col("side") == 2) & (F.col("a") % w == 0))
    return rows.where(~wraps & (F.col("b") >= 0) & (F.col("b") < n)).drop("side")


def order_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, w, _ = size(spark, sf_dir, "orders")
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("node"), (F.col("o_orderkey") % w).cast("double").alias("x"), F.floor(F.col("o_orderkey") / w).cast("double").alias("y"))


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """wkt, road_class, direction, weight: the segments as lines between coordinates."""
    _, w, _ = size(spark, sf_dir, "orders")
    at = lambda c: F.concat((F.col(c) % w).cast("string"), F.lit(" "), F.floor(F.col(c) / w).cast("string"))
    return segments(spark, sf_dir).select(F.concat(F.lit("LINESTRING("), at("a"), F.lit(", "), at("b"), F.lit(")")).alias("wkt"), "road_class", "direction", "weight")


def points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Irregular points: node, x, y."""
    e = F.col("embedding")
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("node"), e[0].cast("double").alias("x"), e[1].cast("double").alias("y"))


__all__ = ["CAPACITIES", "batch_trips", "cents", "corner_trip", "depot_trips", "depots", "edges", "lines", "mixed_trips", "nodes", "order_nodes", "points", "segments", "size", "stations", "table"]
