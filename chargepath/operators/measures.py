"""Cost and accuracy measures of plans."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chargepath.operators import search
from chargepath.operators.planner import Net, Plan

#: Bytes of an entry of a dense run (distance and predecessor of each node) and of a sparse one (two map entries).
DENSE_BYTES, SPARSE_BYTES = 16, 200


def trip_report(plan: Plan, exact: DataFrame | None = None, units_per_hour: float = 3600.0) -> DataFrame:
    """trip, status, direct, cost, hours, stops, longest leg, bases, candidates, widenings, deviation from the direct path, gap to the optimum."""
    cost = plan.solution.groupBy("trip").agg(F.sum("leg_cost").alias("cost"), F.count("station").alias("stops"), F.max("leg_cost").alias("longest_leg"), (F.sum("leg_cost_adj") / units_per_hour).alias("hours"))
    bases = plan.bases.groupBy("trip").agg(F.count("*").alias("bases"))
    found = plan.candidates.groupBy("trip").agg(F.count("*").alias("candidates"), F.max("widen_round").alias("widenings"))
    rows = plan.status.join(plan.path.select("trip", F.col("cost").alias("direct")), "trip", "left").join(cost, "trip", "left").join(bases, "trip", "left").join(found, "trip", "left")
    rows = rows.fillna(0, ["bases", "candidates", "widenings"]).withColumn("deviation", (F.col("cost") - F.col("direct")) / F.col("direct"))
    if exact is not None:
        rows = rows.join(exact.select("trip", F.col("cost").alias("best")), "trip", "left").withColumn("gap", (F.col("cost") - F.col("best")) / F.col("best"))
    return rows


def shared_share(plan: Plan) -> DataFrame:
    """trip, edges, shared: how many steps of a solution are steps of the direct path as well."""
    step = lambda df, *by: df.select(*by, F.explode(F.transform(F.slice("path", 2, F.greatest(F.size("path") - 1, F.lit(0))), lambda v, i: F.struct(F.get("path", i).alias("a"), v.alias("b")))).alias("e"))
    own, direct = step(plan.solution, "trip"), step(plan.path, "trip").distinct().withColumn("hit", F.lit(1))
    return own.join(direct, ["trip", "e"], "left").groupBy("trip").agg(F.count("*").alias("edges"), F.coalesce(F.sum("hit"), F.lit(0)).alias("shared"))


def capacity_check(plan: Plan, capacity: int) -> DataFrame:
    """trip, longest_leg, within: no leg may pass the capacity."""
    return plan.solution.groupBy("trip").agg(F.max("leg_cost").alias("longest_leg")).withColumn("within", F.col("longest_leg") <= capacity)


def edge_report(plan: Plan) -> DataFrame:
    """trip, possible, kept and self pairs, search runs, most settled nodes."""
    a = plan.layers.select("trip", "layer", F.col("id").alias("u"))
    b = plan.layers.select("trip", (F.col("layer") - 1).alias("layer"), F.col("id").alias("v"))
    pairs = a.join(b, ["trip", "layer"]).groupBy("trip").agg(F.count("*").alias("possible"), F.sum((F.col("u") == F.col("v")).cast("long")).alias("self_pairs"))
    runs = plan.layers.where("id <> -2").groupBy("trip").agg(F.count("*").alias("runs"))
    kept = plan.legs.groupBy("trip").agg(F.count("*").alias("kept"), F.max("settled").alias("max_settled"))
    return pairs.join(runs, "trip").join(kept, "trip", "left").fillna(0, ["kept"])


def feasible_share(status: DataFrame) -> DataFrame:
    """status, trips, share of trips' status."""
    rows = status.groupBy("status").agg(F.count("*").alias("trips"))
    return rows.crossJoin(status.agg(F.count("*").alias("n"))).select("status", "trips", (F.col("trips") / F.col("n")).alias("share"))  # by one row


def dense_and_sparse(net: Net, places: DataFrame, radius: int) -> DataFrame:
    """run, settled, equal, dense_bytes, sparse_bytes of bounded runs from places(node), by maps and by vectors over all nodes.

    Node numbers must be 0..n-1, which is what the vectors are indexed by.
    """
    import numpy as np
    import pandas as pd

    loaded, n = net.load(), net.nodes.count()

    def solved(batches):
        for pdf in batches:
            out = []
            for node in pdf["node"].tolist():
                found = search.bounded(loaded.value, node, radius, history=False)
                dist, settled = search.dense(loaded.value, node, n, radius)
                at = np.array(list(found.dist))
                same = settled == found.settled and bool((dist[at] == np.array(list(found.dist.values()))).all())
                out.append((node, found.settled, same, DENSE_BYTES * n, SPARSE_BYTES * found.settled))
            yield pd.DataFrame(out, columns=["run", "settled", "equal", "dense_bytes", "sparse_bytes"])

    return search.spread(places.select("node").distinct(), "node").mapInPandas(solved, "run long, settled long, equal boolean, dense_bytes long, sparse_bytes long")


def settled_by_search(net: Net, trips: DataFrame) -> DataFrame:
    """trip, cost and settled nodes of the plain, the goal-directed and the two-sided search."""
    import pandas as pd

    there, back = net.load(), net.load_back()

    def solved(batches):
        for pdf in batches:
            out = []
            for trip, s, t in zip(pdf["trip"].tolist(), pdf["source"].tolist(), pdf["target"].tolist(), strict=True):
                plain = search.bounded(there.value, s, None, [t])
                goal = search.bounded(there.value, s, None, [t], there.value.goal(t))
                cost, both = search.bidirectional(there.value, back.value, s, t, there.value.goal(s), there.value.goal(t))
                out.append((trip, plain.dist.get(t), goal.dist.get(t), cost, plain.settled, goal.settled, both))
            yield pd.DataFrame(out, columns=["trip", "cost", "cost_goal", "cost_two", "plain", "goal", "two"]).astype({"cost": "Int64", "cost_goal": "Int64", "cost_two": "Int64"})

    return search.spread(trips, "trip").mapInPandas(solved, "trip long, cost long, cost_goal long, cost_two long, plain long, goal long, two long")


class Clock:
    """Seconds of each step of a plan; an instance is a ``clock`` of ``plan_trips``."""

    def __init__(self) -> None:
        self.last, self.steps = time.perf_counter(), []

    def __call__(self, name: str) -> None:
        now = time.perf_counter()
        self.steps.append((name, now - self.last))
        self.last = now

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.steps, "step string, seconds double")


def scaling(spark: SparkSession, work, tasks=(1, 2, 4, 8)) -> DataFrame:
    """tasks, seconds, speed_up, efficiency of ``work(k)``, a table that k tasks make."""
    rows = []
    for k in tasks:
        start = time.perf_counter()
        work(k).write.format("noop").mode("overwrite").save()
        rows.append((k, time.perf_counter() - start))
    first = rows[0][1] * rows[0][0]
    return spark.createDataFrame([(k, s, first / s, first / s / k) for k, s in rows], "tasks int, seconds double, speed_up double, efficiency double")


def stacked(parts: dict[int, DataFrame], name: str) -> DataFrame:
    """Tables of several settings, one under the other, with the setting as a column."""
    return reduce(DataFrame.unionByName, [df.withColumn(name, F.lit(k)) for k, df in parts.items()])
