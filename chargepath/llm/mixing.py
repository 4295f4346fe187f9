"""Mixing sources to target weights.

Each source gets a token budget by water filling: shares follow the weights,
no share passes ``max_epochs`` times what the source has, and what is over is
shared again. Inside a source, documents lie in the order of a random hash
key of all their columns; key ranges are summed, a prefix sum over the ranges
gives each range its start, and a sort inside the range where the budget ends
finishes the prefix sum. Whole epochs are taken first and the last one is cut
at the exact budget. The number of ranges follows the number of rows, so a
range has a bounded number of them on average, whatever the source; whole rows
are never shuffled.

Null and empty texts have size 0 and are never taken; a null source is a
source of its own, after all others. Rows of one id and different texts have
keys of their own; rows equal in all columns are told apart by a number within
their copies, dealt over ranges, and are interchangeable, so reruns agree as
tables. Long texts count whole; an empty table gives no rows; an output
replaces a column of its name.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from chargepath.llm.common import SPACE, boxed, cut, unboxed


def word_count(text):
    """Number of white-space separated words; null counts none."""
    parts = F.split(F.coalesce(text, F.lit("")), f"{SPACE}+")
    return F.size(F.filter(parts, lambda x: x != "")).cast("long")


def budgets(sizes: DataFrame, weights=(3, 1, 2), share: float = 1.5, max_epochs: float = 2.0) -> DataFrame:
    """sizes(source, source_size), one row a source -> + target.

    ``weights`` repeat over the sources by code point, null last. The level of
    the water is the smallest one that the caps below it leave consistent, so
    no loop over rounds of resharing is needed.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    nth = (F.row_number().over(order) - 1) % len(weights)
    weight = reduce(lambda c, k: c.when(nth == k, float(weights[k])), range(1, len(weights)), F.when(nth == 0, float(weights[0])))
    rows = sizes.select("source", "source_size", weight.alias("w"), (F.col("source_size") * max_epochs).alias("cap"))
    full = Window.partitionBy(F.lit(0))
    below = Window.partitionBy(F.lit(0)).orderBy((F.col("cap") / F.col("w")).asc(), F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumns({
        "level": (F.sum("source_size").over(full) * share - F.coalesce(F.sum("cap").over(below), F.lit(0.0)))
        / (F.sum("w").over(full) - F.coalesce(F.sum("w").over(below), F.lit(0.0))),
    })
    level = F.max("level").over(full)  # it rises while caps bind and falls after
    return rows.select("source", "source_size", F.least("cap", level * F.col("w")).alias("target"))


def mix_sources(docs: DataFrame, size, weights=(3, 1, 2), share: float = 1.5, max_epochs: float = 2.0, seed: int = 17, range_rows: int = 20_000, max_broadcast: int = 200_000) -> DataFrame:
    """docs -> docs + size, source_size, target, taken (words, repeats counted).

    Only the range in which a source's budget ends is sorted; in every other one
    all rows are taken alike. Ranges, and the rows of those that are sorted, are
    broadcast up to ``max_broadcast`` of them, else joined by shuffles.
    """
    own = [F.col(f"`{c}`") for c in docs.columns]
    rows = boxed(docs, source=F.col("source"), size=size, digest=F.xxhash64(F.lit(seed), *own), other=F.xxhash64(F.lit(seed + 1), *own))
    light = cut(rows.select("source", "size", "digest", "other"))
    ranges = 1 + light.count() // range_rows
    place = F.pmod(F.shiftright("digest", 20), F.lit(ranges))
    summed = light.groupBy("source", place.alias("range")).agg(F.sum("size").alias("part"))
    before = Window.partitionBy("source").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    starts = summed.withColumn("start", F.coalesce(F.sum("part").over(before), F.lit(0)))
    plan = budgets(summed.groupBy("source").agg(F.sum("part").alias("source_size")), weights, share, max_epochs)
    budget = F.floor("target").cast("long")
    plan = plan.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(budget / F.col("source_size"))).otherwise(0).cast("long"))
    plan = plan.withColumn("rest", budget - F.col("whole") * F.col("source_size"))  # words of the last epoch
    starts = cut(starts.alias("s").join(plan.alias("p"), F.col("s.source").eqNullSafe(F.col("p.source"))).select(
        F.col("s.source").alias("of"), F.col("range").alias("at"), "start", "source_size", "target", "whole", "rest", ((F.col("start") < F.col("rest")) & (F.col("rest") < F.col("start") + F.col("part"))).alias("edge"),
        (F.col("start") + F.col("part") <= F.col("rest")).alias("inside")))
    small = lambda df: F.broadcast(df) if df.count() <= max_broadcast else df
    edge = cut(_edge(light.withColumn("range", place), starts.where("edge")))
    placed = rows.withColumn("range", place).join(small(starts), F.col("source").eqNullSafe(F.col("of")) & (F.col("range") == F.col("at")))
    same = F.col("source").eqNullSafe(F.col("e_source")) & (F.col("digest") == F.col("e_digest")) & (F.col("other") == F.col("e_other"))
    out = _numbered(placed.join(small(edge), same, "left"), edge)
    extra = F.when(F.col("inside"), F.col("size")).when(F.col("edge"), F.least(F.greatest(F.col("e_rest") - F.col("nth") * F.col("size"), F.lit(0)), F.col("size"))).otherwise(0)
    return unboxed(out, size=F.col("size"), source_size=F.col("source_size"), target=F.col("target"), taken=(F.col("whole") * F.col("size") + extra).cast("long"))


def _edge(light: DataFrame, starts: DataFrame) -> DataFrame:
    """Groups of equal rows in the ranges where budgets end: e_source, e_digest, e_other, e_rest, e_copies.

    e_rest is what the last epoch takes of all rows of the group together.
    """
    some = light.join(F.broadcast(starts), F.col("source").eqNullSafe(F.col("of")) & (F.col("range") == F.col("at")))  # one range a source at most
    groups = some.groupBy("source", "digest", "other", "size", "start", "rest").agg(F.count("*").alias("e_copies"))
    order = Window.partitionBy("source").orderBy("digest", "other").rowsBetween(Window.unboundedPreceding, -1)
    first = F.col("start") + F.coalesce(F.sum(F.col("size") * F.col("e_copies")).over(order), F.lit(0))
    left = F.least(F.greatest(F.col("rest") - first, F.lit(0)), F.col("size") * F.col("e_copies"))
    return groups.select(F.col("source").alias("e_source"), F.col("digest").alias("e_digest"), F.col("other").alias("e_other"), left.alias("e_rest"), "e_copies")


def _numbered(rows: DataFrame, edge: DataFrame) -> DataFrame:
    """rows + nth, a row's number among its copies where a budget may end within them, else 0.

    Copies are numbered within 1,024 lots, each from where the lots before it end.
    """
    if edge.where("e_copies > 1").isEmpty():
        return rows.withColumn("nth", F.lit(0).cast("long"))
    key = ["source", "digest", "other"]
    lots = cut(rows.where("e_copies > 1").withColumn("lot", F.pmod(F.monotonically_increasing_id(), F.lit(1024))))
    sizes = lots.groupBy(*key, "lot").agg(F.count("*").alias("n"))
    before = Window.partitionBy(*key).orderBy("lot").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.select(*[F.col(c).alias(f"l_{c}") for c in (*key, "lot")], F.coalesce(F.sum("n").over(before), F.lit(0)).alias("ahead"))
    same = F.col("source").eqNullSafe(F.col("l_source")) & (F.col("digest") == F.col("l_digest")) & (F.col("other") == F.col("l_other")) & (F.col("lot") == F.col("l_lot"))
    nth = F.col("ahead") + F.row_number().over(Window.partitionBy(*key, "lot").orderBy("size")) - 1
    many = lots.join(sizes, same).withColumn("nth", nth.cast("long")).select(*rows.columns, "nth")
    return rows.where("e_copies IS NULL OR e_copies = 1").withColumn("nth", F.lit(0).cast("long")).unionByName(many)
