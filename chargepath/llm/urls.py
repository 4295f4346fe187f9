"""URL filters: explicit rules first, mined association rules for the rest.

Explicit rules fit a host and its subdomains where the path starts with the
rule's; the longest wins. Labels are the rules' verdicts, and "block" for hosts
that hold a word of a short fixed list; a caller may pass labels of its own.
FP-growth mines combinations of host words, path words and query names from
them; urls without a label take part as such, so a combination that is common
among them implies nothing. Combinations that imply a verdict are kept above a
support and a confidence, and matched through an inverted index from a token
to the rules that hold it. Urls without a matching rule are allowed.

Only tokens above the support are mined, and tokens that occur in exactly the
same urls are one item, so a template of many equal tokens is one item and not
all its subsets. Of several matching rules the one of most confidence decides,
then the longer, then "block" after "allow" by letters, then the last by tokens.

A null url, or one without ://, has empty host and path, matches no rule and
is allowed. Repeated rows are judged as rows. Long urls are read whole. An empty
table mines no rule and gives no rows; an output replaces a column of its name.
"""

from itertools import combinations

import pandas as pd
from pyspark.ml.fpm import FPGrowth
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chargepath.llm.common import boxed, cut, unboxed

#: (host, path, verdict) of the explicit rules.
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
VERDICTS = ("block", "allow")
# Words in a host that label it as blocked.
BLOCK_WORDS = ("casino", "poker", "betting", "xxx", "porn", "viagra", "pills")


def parts(url):
    """(host, path) columns of a url column."""
    u = F.coalesce(url, F.lit(""))
    at = F.instr(u, "://")
    rest = F.when(at > 0, u.substr(at + 3, F.length(u))).otherwise(F.lit(""))
    host = F.translate(F.regexp_extract(rest, "(?s)^[^/?#]*", 0), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract(rest, "(?s)^[^/?#]*([^?#]*)", 1)
    return host, path


def explicit(host, path, rules=RULES):
    """The longest fitting rule as a struct(rule, verdict), else null."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for h, p, verdict in sorted(rules, key=lambda r: len(r[0]) + len(r[1])):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        out = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def tokens(host, path, url):
    """Distinct tokens: words of the host, path words (digits as one), query names."""
    labels = F.transform(F.split(host, "[.-]"), lambda x: F.concat(F.lit("h:"), x))
    words = F.transform(F.split(F.regexp_replace(F.lower(path), "[0-9]+", "0"), "[^a-z0-9]+"), lambda x: F.concat(F.lit("p:"), x))
    names = F.transform(F.regexp_extract_all(F.coalesce(url, F.lit("")), F.lit("[?&]([A-Za-z_]+)="), 1), lambda x: F.concat(F.lit("q:"), F.lower(x)))
    return F.array_distinct(F.filter(F.concat(labels, words, names), lambda x: F.length(x) > 2))


def items(rows: DataFrame, min_support: float) -> DataFrame:
    """rows(tokens, verdict) -> items, verdict: frequent tokens, those of the same urls as one, named by the first.

    The frequent tokens are at most the mean number of tokens of a url, divided
    by the support; they ride along as one map.
    """
    keyed = rows.withColumn("id", F.monotonically_increasing_id())
    keyed = cut(keyed)
    least = min_support * keyed.count()
    counts = keyed.select(F.explode("tokens").alias("t"), F.xxhash64("id").cast("decimal(38,0)").alias("h")).groupBy("t").agg(F.count("*").alias("n"), F.sum("h").alias("h")).where(F.col("n") >= least)
    same = counts.groupBy("n", "h").agg(F.sort_array(F.collect_list("t")).alias("ts")).select(F.explode("ts").alias("t"), F.col("ts")[0].alias("name"))
    names = same.agg(F.map_from_entries(F.collect_list(F.struct("t", "name"))).alias("names"))
    mapped = F.transform(F.filter("tokens", lambda t: F.map_contains_key("names", t)), lambda t: F.element_at("names", t))
    return keyed.crossJoin(F.broadcast(names)).select(F.array_distinct(mapped).alias("items"), "verdict")  # one row


def mine(labelled: DataFrame, min_support: float = 0.01, confidence: float = 0.6, max_items: int = 4) -> list[tuple[tuple[str, ...], str, float]]:
    """labelled(tokens, verdict) -> [(antecedent tokens, verdict, confidence)], antecedents of max_items tokens at most.

    A rule is dropped if a part of its tokens says the same with no less
    confidence. Each kept rule has ``min_support`` of all rows, which bounds
    their number and so what reaches the driver.
    """
    rows = items(labelled, min_support).select(F.concat(F.col("items"), F.array(F.concat(F.lit("="), F.col("verdict")))).alias("items"))
    model = FPGrowth(itemsCol="items", minSupport=min_support, minConfidence=confidence).fit(rows)
    found = model.associationRules.where(
        (F.size("consequent") == 1) & F.col("consequent")[0].isin(*[f"={v}" for v in VERDICTS]) & (F.size("antecedent") <= max_items) & ~F.exists("antecedent", lambda x: x.startswith("="))
    ).select(F.array_sort("antecedent").alias("antecedent"), F.expr("substring(consequent[0], 2)").alias("verdict"), "confidence")
    best: dict[tuple[str, ...], tuple[str, float]] = {}
    for r in found.orderBy(F.size("antecedent"), F.col("antecedent"), "verdict").toLocalIterator():
        key = tuple(r.antecedent)
        parts = (best.get(part) for n in range(1, len(key)) for part in combinations(key, n))
        if not any(p and p[0] == r.verdict and p[1] >= r.confidence for p in parts):
            best[key] = (r.verdict, r.confidence)
    return [(k, v, c) for k, (v, c) in best.items()]


def matcher(rules: list[tuple[tuple[str, ...], str, float]]):
    """A pandas UDF: token array -> struct(mined, verdict) of the best matching rule."""

    @F.pandas_udf("mined string, verdict string")
    def match(sets: pd.Series) -> pd.DataFrame:
        index: dict[str, list[int]] = {}
        for k, (antecedent, _, _) in enumerate(rules):
            index.setdefault(antecedent[0], []).append(k)
        out = []
        for have in sets:
            own = set(have) if have is not None else set()
            hits = [rules[k] for t in own for k in index.get(t, ()) if own.issuperset(rules[k][0])]
            best = max(hits, key=lambda r: (r[2], len(r[0]), r[1], r[0]), default=None)
            out.append((" ".join(best[0]), best[1]) if best else (None, None))
        return pd.DataFrame(out, columns=["mined", "verdict"], dtype=object)

    return match


def judge(pages: DataFrame, rules=RULES, min_support: float = 0.01, confidence: float = 0.6, labels=None) -> DataFrame:
    """pages -> pages + host, path, rule, verdict, mined (the association rule that decided).

    ``labels`` is a column over pages of "block", "allow" or null that takes
    the place of the list of words.
    """
    host, path = parts(F.col("url"))
    given = {} if labels is None else {"given": labels}
    rows = boxed(pages, url=F.col("url"), host=host, path=path, **given)
    rows = rows.withColumns({"explicit": explicit(F.col("host"), F.col("path"), rules), "tokens": tokens(F.col("host"), F.col("path"), F.col("url"))})
    word = F.exists(F.split("host", "[.-]"), lambda x: x.isin(*BLOCK_WORDS))
    weak = F.when(word, "block") if labels is None else F.col("given")
    labelled = rows.select("tokens", F.coalesce("explicit.verdict", weak, F.lit("unlabelled")).alias("verdict"))
    mined = mine(labelled, min_support, confidence)
    rows = rows.withColumn("found", F.when(F.col("explicit").isNull(), matcher(mined)(F.col("tokens"))))
    verdict = F.coalesce(F.col("explicit.verdict"), F.col("found.verdict"), F.lit("allow"))
    return unboxed(rows, host=F.col("host"), path=F.col("path"), rule=F.col("explicit.rule"), verdict=verdict, mined=F.col("found.mined"))


__all__ = ["BLOCK_WORDS", "RULES", "explicit", "items", "judge", "matcher", "mine", "parts", "tokens"]
