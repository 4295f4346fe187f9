"""Quality rules with distribution divergence; built-in functions only.

Base rules count words, symbols, repeated lines and repeated three-word
windows. The method compares a document's histogram of character classes and
its histogram of common words with those of its language by the
Jensen-Shannon distance. The references of a language are summed over all its
documents that pass the base rules, so junk does not shape them. Texts shorter
than a guard are not compared, as their histograms say little; nor are those
of a language without references.

Null and empty texts have no words and fail the base rule; a null language is
a language of its own; repeated rows are judged as rows and get equal results;
long texts are read whole; an empty table gives no rows. Windows of three
words are told apart by their 64-bit hashes. An output replaces a key column
of its name. The rows' features, with the columns that are to be carried, are
cut once and no text is shuffled.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chargepath.llm.common import SPACE, boxed, cut, unboxed

# Frequent function words of four languages.
COMMON = tuple(sorted(set((
    "the of and to in a is that for it was on are as with be by at this have from or had not but "
    "der die und das den von zu mit sich des auf für ist im dem nicht ein eine als auch es an werden aus "
    "de la le et les des en un du une que est pour qui dans par plus pas au sur se ce il son "
    "el que los se del las por con no su al lo como más pero sus le ya o este sí porque y una"
).split())))
#: Character classes: name -> regular class of the characters that do not count.
CLASSES = {"lower": "[^a-z]+", "upper": "[^A-Z]+", "digit": "[^0-9]+", "stop": "[^.,;:!?'\"()\\-]+", "sign": "[^#*$%&|<>]+", "space": "[^\\x20\\x09-\\x0D]+"}
_BINS = (*CLASSES, "other")


def _jsd_term(p, q):
    """What one bin with p > 0 adds to twice the divergence, less its share of q log 2."""
    m = (p + q) / 2
    return p * F.log(p / m) + F.when(q > 0, q * F.log(q / m)).otherwise(0.0)


def features(docs: DataFrame, width: int = 3) -> DataFrame:
    """docs(row, text, lang) -> row, base counts, class counts and common-word counts."""
    text = F.coalesce(F.col("text"), F.lit(""))
    kept = lambda pattern: F.length(F.regexp_replace(text, pattern, ""))
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike("[^\\x20\\x09-\\x0D]"))
    words = F.filter(F.split(text, f"{SPACE}+"), lambda x: x != "")
    rows = docs.select(
        "row", F.col("lang").alias("_lang"), F.length(text).alias("_chars"), *[kept(p).alias(f"_{c}") for c, p in CLASSES.items()],
        F.transform(F.array(lines), lambda x: (F.size(x) - F.size(F.array_distinct(x))))[0].alias("_dup"),
        F.explode(F.array(words)).alias("_w"),
    )
    n = F.size("_w")
    w = F.col("_w")
    grams = F.when(n > width, F.transform(F.slice(w, 1, n - width + 1), lambda x, i: F.xxhash64(x, *[F.get(w, i + k) for k in range(1, width)]))).otherwise(F.array().cast("array<bigint>"))
    bare = F.transform(w, lambda x: F.lower(F.rtrim(x, F.lit(".,;:!?"))))
    common = F.filter(bare, lambda x: x.isin(*COMMON))
    rows = rows.select("*", F.explode(F.array(F.struct(grams.alias("g"), common.alias("c"), n.alias("n")))).alias("_x")).drop("_w")
    g = F.col("_x.g")
    spots = F.sort_array(F.transform(g, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    twice = F.transform(F.array(spots), lambda s: F.sort_array(F.transform(F.filter(F.transform(s, lambda x, j: F.struct(
        x["i"].alias("i"), (F.coalesce(F.get(s, j - 1)["h"] == x["h"], F.lit(False)) | F.coalesce(F.get(s, j + 1)["h"] == x["h"], F.lit(False))).alias("r"))), lambda y: y["r"]), lambda y: y["i"])))
    reach = F.transform(twice, lambda p: F.aggregate(F.transform(p, lambda x, j: F.least(F.lit(width), F.coalesce(F.get(p, j + 1) - x, F.lit(width)))), F.lit(0), lambda a, b: a + b))[0]
    repeated = F.when(F.size(F.array_distinct(g)) < F.size(g), reach).otherwise(0)
    c = F.col("_x.c")
    return rows.select(
        "row", "_lang", "_chars", *[f"_{c}" for c in CLASSES], "_dup", F.col("_x.n").alias("_n"), repeated.alias("_rep"), F.size(c).alias("_n_common"),
        F.transform(F.array_distinct(c), lambda x: F.struct(x.alias("w"), (F.size(c) - F.size(F.array_remove(c, x))).alias("k"))).alias("_common"),
    )


def judge(docs: DataFrame, key: list[str], min_words: int = 50, max_repeat: int = 50, guard_words: int = 80, max_class: float = 0.25, max_common: float = 0.8, max_broadcast: int = 10_000) -> DataFrame:
    """key columns + n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
    base_failed, class_distance, common_distance, kept; one row for each row of docs."""
    own = boxed(docs, text=F.col("text"), lang=F.col("lang"))
    rows = cut(features(own.withColumn("row", F.struct(*[F.col(f"row.`{k}`").alias(k) for k in key]))))
    other = F.col("_chars") - sum((F.col(f"_{c}") for c in CLASSES), F.lit(0))
    failed = (F.col("_n") < min_words) | (100 * F.col("_rep") > max_repeat * F.col("_n"))
    rows = rows.withColumns({"_other": other, "_failed": failed})
    good = rows.where(~F.col("_failed"))
    sums = good.groupBy("_lang").agg(*[F.sum(f"_{c}").cast("double").alias(f"q_{c}") for c in _BINS], F.sum("_chars").cast("double").alias("q_all"), F.sum("_n_common").cast("double").alias("q_common"))
    by_word = good.select("_lang", F.explode("_common").alias("x")).groupBy("_lang", F.col("x.w").alias("w")).agg(F.sum("x.k").cast("double").alias("k"))
    by_word = by_word.groupBy("_lang").agg(F.map_from_entries(F.collect_list(F.struct("w", "k"))).alias("q_words"))  # at most one entry for each of COMMON
    refs = cut(sums.alias("s").join(by_word.alias("b"), F.col("s._lang").eqNullSafe(F.col("b._lang")), "left").select("s.*", "q_words"))
    refs = refs.withColumnRenamed("_lang", "q_lang")
    joined = rows.join(F.broadcast(refs) if refs.count() <= max_broadcast else refs, F.col("_lang").eqNullSafe(F.col("q_lang")), "left")
    n_chars, ln2 = F.col("_chars"), 0.6931471805599453
    class_sum = F.lit(0.0)
    for c in _BINS:
        p, q = F.col(f"_{c}") / n_chars, F.col(f"q_{c}") / F.col("q_all")
        class_sum = class_sum + F.when(p > 0, _jsd_term(p, q)).otherwise(q * ln2)
    shares = F.transform("_common", lambda x: F.struct((x["k"] / F.col("_n_common")).alias("p"), (F.coalesce(F.element_at("q_words", x["w"]), F.lit(0.0)) / F.col("q_common")).alias("q")))
    word_sum = F.aggregate(shares, F.lit(ln2), lambda a, x: a + _jsd_term(x["p"], x["q"]) - x["q"] * ln2)
    root = lambda x: F.sqrt(F.greatest(x / (2 * ln2), F.lit(0.0)))
    known = F.col("q_all").isNotNull()
    out = joined.withColumns({
        "_class": F.when(known & (n_chars > 0), root(class_sum)).otherwise(0.0),
        "_words": F.when(known & (F.col("_n_common") > 0), root(word_sum)).otherwise(1.0),
    })
    far = (F.col("_class") > max_class) | ((F.col("_words") > max_common) & F.col("q_words").isNotNull())
    long = lambda c: c.cast("long")
    return unboxed(
        out, n_words=long(F.col("_n")), word_chars=long(F.col("_chars") - F.col("_space")), n_symbols=long(F.col("_sign")), n_dup_lines=long(F.col("_dup")), n_repeat_words=long(F.col("_rep")),
        base_failed=F.col("_failed"), class_distance=F.col("_class"), common_distance=F.col("_words"), kept=~F.col("_failed") & ~((F.col("_n") >= guard_words) & far))
