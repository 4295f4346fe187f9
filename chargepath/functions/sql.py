"""SQL surface: functions and table functions usable from spark.sql."""

import re

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


def register(spark: SparkSession) -> None:
    """Temporary SQL functions; all but ring_cells stay inside the JVM."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bin_of(x DOUBLE, y DOUBLE, x0 DOUBLE, y0 DOUBLE, cell DOUBLE, ni BIGINT) RETURNS BIGINT RETURN bigint(floor((y - y0) / cell)) * ni + bigint(floor((x - x0) / cell))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION straight_line(ax DOUBLE, ay DOUBLE, bx DOUBLE, by_ DOUBLE) RETURNS DOUBLE RETURN sqrt((ax - bx) * (ax - bx) + (ay - by_) * (ay - by_))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION charge_adjusted(cost BIGINT, penalty BIGINT, q BIGINT) RETURNS DOUBLE RETURN cost * (q + penalty) / q")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edge_budget(n BIGINT, m BIGINT) RETURNS BIGINT RETURN n * (n * m + 2)")

    @F.udtf(returnType="i int, j int")
    class RingCells:
        def eval(self, i: int, j: int, k: int):
            for a in range(-k, k + 1):
                for b in range(-k, k + 1):
                    if max(abs(a), abs(b)) == k:
                        yield i + a, j + b

    spark.udtf.register("ring_cells", RingCells)


def path_wkt(path, nodes_xy):
    """WKT of a path column (array of nodes) through a map column node -> struct(x, y)."""
    point = lambda n: F.concat_ws(" ", nodes_xy[n]["x"].cast("string"), nodes_xy[n]["y"].cast("string"))
    return F.concat(F.lit("LINESTRING("), F.array_join(F.transform(path, point), ", "), F.lit(")"))


def routes_wkt(rows: DataFrame, nodes: DataFrame) -> DataFrame:
    """rows(trip, path) + wkt; coordinates are joined by node, so no map of the network is needed."""
    steps = rows.select("trip", F.posexplode("path").alias("pos", "node")).join(nodes.select("node", "x", "y"), "node")
    point = F.concat_ws(" ", F.col("x").cast("string"), F.col("y").cast("string"))
    lines = steps.groupBy("trip").agg(F.array_sort(F.collect_list(F.struct("pos", point.alias("p")))).alias("s"))
    return rows.join(lines.select("trip", F.concat(F.lit("LINESTRING("), F.array_join(F.col("s.p"), ", "), F.lit(")")).alias("wkt")), "trip", "left")


def parse_linestring(wkt):
    """array<struct<x,y>> of a LINESTRING text column; null for anything else."""
    body = F.regexp_extract(wkt, "(?i)^\\s*LINESTRING\\s*\\((.*)\\)\\s*$", 1)
    points = F.transform(F.split(body, ","), lambda p: F.split(F.trim(p), "\\s+"))
    xy = F.transform(points, lambda p: F.struct(p[0].cast("double").alias("x"), p[1].cast("double").alias("y")))
    return F.when(body != "", xy)


def parse_ring(wkt: str) -> list[tuple[float, float]]:
    """The outer ring of a POLYGON text."""
    found = re.fullmatch(r"(?i)\s*POLYGON\s*\(\s*\(([^()]*)\)\s*\)\s*", wkt)
    if not found:
        raise ValueError("a POLYGON with one ring is wanted")
    ring = [tuple(map(float, p.split())) for p in found[1].split(",")]
    return ring[:-1] if len(ring) > 1 and ring[0] == ring[-1] else ring


@F.pandas_udf(DoubleType())
def polyline_length(x: pd.Series, y: pd.Series) -> float:
    """A grouped aggregate: the length of a line whose points come in order."""
    return float(np.hypot(np.diff(x), np.diff(y)).sum())


@F.pandas_udf(DoubleType())
def haversine_km(lon1: pd.Series, lat1: pd.Series, lon2: pd.Series, lat2: pd.Series) -> pd.Series:
    """Great-circle distance in kilometres of coordinates in degrees."""
    a1, o1, a2, o2 = (np.radians(v) for v in (lat1, lon1, lat2, lon2))
    h = np.sin((a2 - a1) / 2) ** 2 + np.cos(a1) * np.cos(a2) * np.sin((o2 - o1) / 2) ** 2
    return 2 * 6371.0088 * np.arcsin(np.sqrt(h.clip(0, 1)))
