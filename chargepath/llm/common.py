"""Helpers that the text operators share: tables, durable cuts and vectorised words."""

from __future__ import annotations

import gc
import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from xxhash import xxh3_64_intdigest

from chargepath.operators.search import cut, cut_size

#: Java and RE2 class of the white space that parts words.
SPACE = "[\\x20\\x09-\\x0D]"
#: ASCII upper case to lower case, all other bytes as they are.
LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def release(spark: SparkSession) -> None:
    """Let Spark delete shuffle files of finished jobs that nothing refers to.

    Its cleaner acts when the driver's garbage is collected, which in a long
    job of several rounds may come after the disks are full.
    """
    for _ in range(2):  # first the driver's Python lets go, then its JVM
        gc.collect()
        time.sleep(0.3)
        spark.sparkContext._jvm.System.gc()


def cut_clean(df: DataFrame) -> DataFrame:
    """``cut``, with the shuffle files behind df deleted at once: after it nothing reads them.

    ``release`` leaves that to collectors of garbage, which a busy machine may
    run too late or not at all. df must not be used again.
    """
    context = df.sparkSession.sparkContext._jsc.sc()
    kept = cut(df)
    if context.cleaner().isDefined():
        for k in shuffles(df._jdf.queryExecution().executedPlan()):
            context.cleaner().get().doCleanupShuffle(k, True)
    return kept


def shuffles(plan) -> list[int]:
    """Numbers of the shuffles that an executed plan made itself; those of cached tables are not its own."""
    if plan.nodeName() == "AdaptiveSparkPlan":
        return list(plan.context().shuffleIds())
    below = plan.children()
    return [*([plan.shuffleId()] if plan.nodeName() == "Exchange" else []), *(k for i in range(below.size()) for k in shuffles(below.apply(i)))]


def boxed(df: DataFrame, **columns) -> DataFrame:
    """Each row as a struct named ``row``, beside the given columns: no name of df can clash with theirs."""
    return df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"), *[c.alias(name) for name, c in columns.items()])


def unboxed(df: DataFrame, **outputs) -> DataFrame:
    """The columns of ``row`` and the outputs; an output replaces a column of its name."""
    taken = {name.lower() for name in outputs}
    own = [f.name for f in df.schema["row"].dataType.fields if f.name.lower() not in taken]
    return df.select(*[F.col(f"row.`{c}`").alias(c) for c in own], *[c.alias(name) for name, c in outputs.items()])


def encoded(texts: pd.Series) -> list[bytes]:
    return [t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b"" for t in texts]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of unsigned 64-bit integers."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Rolling:
    """A polynomial hash of byte strings: powers of an odd base modulo 2^64, grown on demand, and a number for each byte."""

    def __init__(self, base: int, numbers: np.ndarray) -> None:
        self.base, self.numbers = base, numbers
        self.up = self.down = np.ones(1, dtype=np.uint64)

    def need(self, n: int) -> None:
        if len(self.up) < n:
            inverse = np.uint64(pow(self.base, -1, 1 << 64))
            self.up = np.cumprod(np.r_[np.uint64(1), np.full(n, np.uint64(self.base))], dtype=np.uint64)
            self.down = np.cumprod(np.r_[np.uint64(1), np.full(n, inverse, dtype=np.uint64)], dtype=np.uint64)

    def prefixes(self, data: np.ndarray) -> np.ndarray:
        """Running hash: entry i covers the first i bytes."""
        self.need(len(data) + 1)
        out = np.zeros(len(data) + 1, dtype=np.uint64)
        np.cumsum(self.numbers[data] * self.up[: len(data)], out=out[1:])
        return out

    def spans(self, prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Hashes of byte spans that do not depend on where the spans lie."""
        return mix((prefix[ends] - prefix[starts]) * self.down[starts])


#: Two hashes that share nothing but their length.
FIRST = Rolling(0x9E3779B97F4A7C15, np.arange(1, 257, dtype=np.uint64))
SECOND = Rolling(0xD1342543DE82EF95, mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x2545F4914F6CDD1D)))


def word_hashes(data: bytes) -> np.ndarray:
    """One 64-bit hash for each white-space separated word of data."""
    return np.fromiter(map(xxh3_64_intdigest, data.split()), dtype=np.uint64)


def shingle_set(data: bytes, width: int) -> np.ndarray:
    """Sorted distinct hashes of the word shingles of lower-cased data.

    Fewer words than ``width`` give the whole sequence as one shingle; no word
    gives the empty set.
    """
    words = word_hashes(data.translate(LOWER))
    if not len(words):
        return words
    n = min(width, len(words))
    out = np.full(len(words) - n + 1, np.uint64(n))
    for k in range(n):
        out = mix(out * np.uint64(0xD6E8FEB86659FD93) + words[k : len(words) - n + 1 + k])
    return np.unique(out)


def worker_cache() -> dict:
    """A dict that lives as long as its Python worker."""
    return _CACHE


_CACHE: dict = {}


__all__ = ["FIRST", "LOWER", "SECOND", "SPACE", "Rolling", "boxed", "cut", "cut_clean", "cut_size", "encoded", "mix", "release", "shingle_set", "shuffles", "table", "unboxed", "word_hashes", "worker_cache"]
