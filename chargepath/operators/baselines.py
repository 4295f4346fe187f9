"""Baselines and exact answers that the planner is measured against."""

from collections.abc import Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chargepath.operators import search
from chargepath.operators.network import reverse
from chargepath.operators.planner import SOURCE, TARGET, Net
from chargepath.operators.search import cut, cut_size


def exact_optimum(net: Net, trips: DataFrame, capacity: int) -> DataFrame:
    """trip, cost: the cheapest chain over all stations with no leg over the capacity.

    Arcs between stations are found once for all trips; each trip adds the arcs
    from its source and to its target and is solved as a shortest path.
    """
    places = net.stations.select("node").union(trips.select("source")).union(trips.select("target")).distinct()
    runs = places.select(F.col("node").alias("run"), F.col("node").alias("source"), F.lit(capacity).alias("radius"))
    arcs = search.reach(net.edges, runs, "auto", net.nodes, net.load(), history=False).select(F.col("run").alias("src"), F.col("node").alias("dst"), F.col("dist").alias("weight"))
    arcs = cut(arcs.join(places.select(F.col("node").alias("dst")), "dst").where("src <> dst"))
    own = net.stations.select(F.col("node").alias("src")).distinct()
    between = search.load(arcs.join(own, "src").select("src", "dst", "weight"))
    if between is None:
        return _frontier_optimum(arcs, own, trips)
    starts = arcs.select(F.col("src").alias("source"), F.struct("dst", "weight").alias("a")).groupBy("source").agg(F.collect_list("a").alias("starts"))
    rows = trips.join(starts, "source", "left")

    def solved(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import heapq

        for pdf in batches:
            out = []
            for trip, source, target, first in zip(pdf["trip"], pdf["source"], pdf["target"], pdf["starts"], strict=True):
                best, heap, done = {}, [], set()
                for a in first if first is not None else ():
                    heapq.heappush(heap, (a["weight"], a["dst"]))
                if source == target:
                    heap = [(0, target)]
                while heap:
                    d, u = heapq.heappop(heap)
                    if u in done:
                        continue
                    done.add(u)
                    best[u] = d
                    if u == target:
                        out.append((trip, d))
                        break
                    for v, w in between.value.out(int(u)):
                        if v not in done:
                            heapq.heappush(heap, (d + w, v))
            yield pd.DataFrame(out, columns=["trip", "cost"])

    return rows.select("trip", "source", "target", "starts").mapInPandas(solved, "trip long, cost long")


def _frontier_optimum(arcs: DataFrame, own: DataFrame, trips: DataFrame) -> DataFrame:
    """The same by frontier rounds, for arcs over the broadcast bound.

    Nodes are doubled; a source gets an odd name of its own, so that its first
    arcs are open to its trips only.
    """
    twice = arcs.select("src", (2 * F.col("dst")).alias("dst"), "weight")
    between = twice.join(own, "src").select((2 * F.col("src")).alias("src"), "dst", "weight")
    first = twice.join(trips.select(F.col("source").alias("src")).distinct(), "src").select((2 * F.col("src") + 1).alias("src"), "dst", "weight")
    far = trips.where("source <> target").select("trip", (2 * F.col("source") + 1).alias("source"), (2 * F.col("target")).alias("node"))
    runs = far.select(F.col("source").alias("run"), "source", F.lit(None).cast("long").alias("radius")).distinct()
    found = search.reach(between.unionByName(first), runs, "frontier").select(F.col("run").alias("source"), "node", "dist")
    there = far.join(found, ["source", "node"]).select("trip", F.col("dist").alias("cost"))
    return there.unionByName(trips.where("source = target").select("trip", F.lit(0).cast("long").alias("cost")))


def enumerate_chains(edges: DataFrame) -> DataFrame:
    """trip, cost of the best of all station combinations; what the process graph
    saves. For small n and m only: rows grow as n to the power of m."""
    last = edges.agg(F.max("layer")).first()[0]
    rows = edges.where("layer = 0").select("trip", F.col("v").alias("at"), F.col("weight").alias("cost"))
    done = rows.where(F.col("at") == TARGET)
    for k in range(1, (last or 0) + 1):
        step = edges.where(F.col("layer") == k).select("trip", F.col("u").alias("at"), F.col("v").alias("to"), "weight")
        rows = rows.join(step, ["trip", "at"]).select("trip", F.col("to").alias("at"), (F.col("cost") + F.col("weight")).alias("cost"))
        done = done.unionByName(rows.where(F.col("at") == TARGET))
    return done.groupBy("trip").agg(F.min("cost").alias("cost"))


def greedy_trip(net: Net, trips: DataFrame, capacity: int) -> DataFrame:
    """trip, cost, stops: always on to the reachable station nearest to the target, if that comes nearer.

    What is left falls with every stop, so each trip arrives or finds no nearer
    station, and the rounds end.
    """
    runs = trips.select(F.col("target").alias("run"), F.col("target").alias("source"), F.lit(None).cast("long").alias("radius")).distinct()
    back = search.reach(reverse(net.edges), runs, "auto", net.nodes, net.load_back(), history=False)
    left = cut(back.select(F.col("run").alias("target"), "node", F.col("dist").alias("rest")))
    sites = net.stations.groupBy("node").agg(F.min("station").alias("station"))
    state = trips.select("trip", "source", "target", F.col("source").alias("at"), F.lit(0).cast("long").alias("cost"), F.lit(0).alias("stops"))
    done = []
    while True:
        state = cut_size(state)
        if state.isEmpty() and done:
            return reduce(DataFrame.unionByName, done)
        here = state.join(left.withColumnRenamed("node", "at"), ["target", "at"])
        arrived = here.where(F.col("rest") <= capacity).select("trip", (F.col("cost") + F.col("rest")).alias("cost"), "stops")
        done.append(cut(arrived))
        far = here.where(F.col("rest") > capacity)
        runs = far.select(F.col("at").alias("run"), F.col("at").alias("source"), F.lit(capacity).alias("radius")).distinct()
        hops = search.reach(net.edges, runs, "auto", net.nodes, net.load(), history=False).join(sites, "node").select(F.col("run").alias("at"), F.col("node").alias("to"), "dist", "station")
        nxt = far.join(hops, "at").join(left.select("target", F.col("node").alias("to"), F.col("rest").alias("after")), ["target", "to"]).where("after < rest")
        pick = nxt.groupBy("trip", "source", "target").agg(F.min(F.struct("after", "station", "to", (F.col("cost") + F.col("dist")).alias("c"), "stops")).alias("m"))
        state = pick.select("trip", "source", "target", F.col("m.to").alias("at"), F.col("m.c").alias("cost"), (F.col("m.stops") + 1).alias("stops"))


__all__ = ["SOURCE", "TARGET", "enumerate_chains", "exact_optimum", "greedy_trip"]
