"""Benchmark decontamination by a prefix-filtered containment join.

Items are cut into windows of ``width`` words. A window is a set of shingles,
pairs of neighbouring words (the word itself in a window of one), ordered by
rarity over all documents (ties by hash). A document that contains the window
must contain its rarest shingle, so that one alone is the join's necessary
prefix. Where a document has a prefix shingle, its place in the window fixes
where the window would start: starts where it would pass either end of the text
are dropped (length and position bound), the rest is compared by the hash of
the whole window and then word by word.

Items are taken in blocks whose index is measured in bytes and broadcast, so
what goes to an executor has a set bound however large the benchmark is; each
block costs two passes over the documents, one for rarity and one for the join.

Null and empty texts have no words and are not contaminated; very long texts
are read whole; repeated documents are judged as rows of their own; repeated
items count once for each item_id; a null item_id counts as no item but its
windows still hit; an empty benchmark contaminates nothing; an empty documents
table gives no rows; an output replaces a column of its name.
"""

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh3_64_intdigest

from chargepath.llm.common import boxed, cut, mix, unboxed

# A-Z lower-cased; ASCII other than letters and digits parts words; bytes over 7F are kept.
_TABLE = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b > 127 else 32 for b in range(256))
_STEP = np.uint64(0x9E3779B97F4A7C15)


def words(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_TABLE).split() if text else []


def hashes(w: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxh3_64_intdigest, w), dtype=np.uint64, count=len(w))


def shingles(h: np.ndarray, of_one: bool) -> np.ndarray:
    """The hash of each pair of neighbours, or of each word alone."""
    return mix(h ^ _STEP) if of_one else mix(h[:-1] * _STEP + h[1:])


def rolled(h: np.ndarray, n: int) -> np.ndarray:
    """The hash of each window of n words."""
    out = np.full(max(0, len(h) - n + 1), np.uint64(n))
    for k in range(n):
        out = mix(out * _STEP + h[k : len(h) - n + 1 + k])
    return out


class Sieve:
    """A bitmap that tells at once of most hashes that they are not among the known ones."""

    def __init__(self, known: np.ndarray) -> None:
        self.known = known
        bits = min(26, max(10, int(64 * len(known)).bit_length()))
        self.shift = np.uint64(64 - bits)
        self.table = np.zeros(1 << bits, dtype=bool)
        self.table[known >> self.shift] = True

    def places(self, s: np.ndarray) -> np.ndarray:
        """Where s holds a known hash."""
        at = np.flatnonzero(self.table[s >> self.shift])
        if not len(at):
            return at
        k = np.minimum(np.searchsorted(self.known, s[at]), len(self.known) - 1)
        return at[self.known[k] == s[at]]


class Batch:
    """The words of many texts end to end, and their hashes."""

    def __init__(self, texts) -> None:
        self.words = [words(t) for t in texts]
        self.sizes = np.array([len(w) for w in self.words], dtype=np.int64)
        self.ends = np.cumsum(self.sizes)
        self.h = hashes(list(chain.from_iterable(self.words)))

    @classmethod
    def parts(cls, texts: pd.Series, most: int = 256) -> Iterator["Batch"]:
        """A series in batches of a few texts, so that few words are held at a time."""
        for k in range(0, len(texts), most):
            yield cls(texts.iloc[k : k + most])

    def shingles(self, of_one: bool) -> np.ndarray:
        """Of the whole batch; a pair across two texts is 0."""
        s = shingles(self.h, of_one) if len(self.h) else self.h
        if not of_one and len(s):
            last = self.ends[:-1] - 1
            s[last[(last >= 0) & (last < len(s))]] = 0
        return s

    def own(self, k: int) -> np.ndarray:
        return self.h[self.ends[k] - self.sizes[k] : self.ends[k]]


@dataclass
class Index:
    """Windows in the order of their prefix shingles' hashes."""

    prefix: np.ndarray  # 64 bits
    offset: np.ndarray  # of the prefix shingle in the window
    length: np.ndarray  # in words
    whole: np.ndarray  # hash of the window
    texts: list[bytes]  # its words, joined by spaces
    ids: list[tuple[str, ...]]  # of the items that hold it

    @property
    def kinds(self) -> list[bool]:
        """Which shingles there are: pairs (False), words alone (True)."""
        return [one for one in (False, True) if ((self.length == 1) == one).any()]

    @property
    def nbytes(self) -> int:
        arrays = sum(a.nbytes for a in (self.prefix, self.offset, self.length, self.whole))
        return arrays + sum(len(t) + 33 for t in self.texts) + sum(56 + sum(len(i) + 49 for i in ids) for ids in self.ids)


def windows(items: list[tuple[str | None, str]], width: int) -> dict[bytes, set]:
    """Window -> the ids of the items that hold it."""
    out: dict[bytes, set] = {}
    for item_id, text in items:
        w = words(text)
        n = min(width, len(w))
        for k in range(len(w) - n + 1 if n else 0):
            ids = out.setdefault(b" ".join(w[k : k + n]), set())
            if item_id is not None:
                ids.add(item_id)
    return out


def vocabulary(found: dict[bytes, set]) -> np.ndarray:
    """The distinct shingles of windows, ascending."""
    parts = []
    for window in found:
        h = hashes(window.split(b" "))
        parts.append(shingles(h, len(h) == 1))
    return np.unique(np.concatenate(parts)) if parts else np.zeros(0, dtype=np.uint64)


def index(found: dict[bytes, set], known: np.ndarray, count: np.ndarray) -> Index:
    """The windows under their rarest shingles; known shingles and how often documents have them."""
    rows = []
    for window, ids in found.items():
        h = hashes(window.split(b" "))
        s = shingles(h, len(h) == 1)
        n = count[np.searchsorted(known, s)]
        at = int(np.lexsort((s, n))[0])
        rows.append((int(s[at]), at, len(h), int(rolled(h, len(h))[0]), window, tuple(sorted(ids))))
    rows.sort(key=lambda r: (r[0], r[4]))
    cols = list(zip(*rows, strict=True)) if rows else [()] * 6
    return Index(np.array(cols[0], dtype=np.uint64), np.array(cols[1], dtype=np.int32), np.array(cols[2], dtype=np.int32), np.array(cols[3], dtype=np.uint64), list(cols[4]), list(cols[5]))


def hits(w: list[bytes], by_prefix: Index, h: np.ndarray | None = None) -> tuple[set, np.ndarray | None]:
    """(item ids, mask) of a document's words, whose hashes may be given."""
    ids, mask = set(), None
    if not w or not len(by_prefix.prefix):
        return ids, mask
    h, wholes = hashes(w) if h is None else h, {}
    for of_one in by_prefix.kinds:
        s = shingles(h, of_one)
        lo, hi = np.searchsorted(by_prefix.prefix, s, "left"), np.searchsorted(by_prefix.prefix, s, "right")
        spots = np.flatnonzero(hi > lo)
        for part in np.array_split(spots, 1 + int((hi - lo)[spots].sum()) // 1_000_000) if len(spots) else ():
            many = (hi - lo)[part]
            at = np.repeat(part, many)
            k = np.repeat(hi[part] - np.cumsum(many), many) + np.arange(many.sum())
            start, n = at - by_prefix.offset[k], by_prefix.length[k]
            ok = (start >= 0) & (start + n <= len(w)) & ((n == 1) == of_one)
            start, n, k = start[ok], n[ok], k[ok]
            for length in np.unique(n):
                if length not in wholes:
                    wholes[length] = rolled(h, int(length))
                own = n == length
                for a, window in zip(start[own].tolist(), k[own].tolist(), strict=True) if own.any() else ():
                    if wholes[length][a] == by_prefix.whole[window] and b" ".join(w[a : a + length]) == by_prefix.texts[window]:
                        if mask is None:
                            mask = np.zeros(len(w), dtype=bool)
                        mask[a : a + length] = True
                        ids.update(by_prefix.ids[window])
    return ids, mask


def pieces(text: str | None, width: int, most: int) -> list[str]:
    """A text in pieces of up to ``most`` windows, which together hold each of its windows once."""
    w = words(text)
    return [b" ".join(w[k : k + most + width - 1]).decode("utf-8", "surrogatepass") for k in range(0, max(1, len(w) - width + 1), most)] if w else []


def _blocks(benchmark: DataFrame, max_bytes: int, width: int):
    """Windows of some items at a time, whose index is expected to keep to max_bytes; long items come in pieces."""
    block, size = [], 0
    for r in benchmark.select(F.col("item_id").cast("string").alias("i"), F.col("text").alias("t")).distinct().orderBy("i", "t").toLocalIterator():
        for piece in pieces(r.t, width, max(1, max_bytes // 1000)):
            # Each word starts a window of up to width words.
            need = len(piece.encode("utf-8", "surrogatepass")) * width + 200 * (piece.count(" ") + 1)
            if block and size + need > max_bytes:
                yield windows(block, width)
                block, size = [], 0
            block.append((r.i, piece))
            size += need
    if block:
        yield windows(block, width)


def rarity(docs: DataFrame, known, kinds: list[bool]) -> np.ndarray:
    """Occurrences over all documents of each known shingle (a broadcast ascending array)."""

    def counted(batches):
        sieve = Sieve(known.value)
        total = np.zeros(len(known.value), dtype=np.int64)
        for pdf in batches:
            for own in Batch.parts(pdf["text"]):
                for of_one in kinds:
                    s = own.shingles(of_one)
                    total += np.bincount(np.searchsorted(known.value, s[sieve.places(s)]), minlength=len(total))
        some = np.flatnonzero(total)
        yield pd.DataFrame({"k": some, "n": total[some]})

    rows = docs.select("text").mapInPandas(counted, "k long, n long").groupBy("k").agg(F.sum("n").alias("n"))
    out = np.zeros(len(known.value), dtype=np.int64)
    for r in rows.collect():  # at most one row for each known shingle
        out[r.k] = r.n
    return out


def contamination(docs: DataFrame, benchmark: DataFrame, width: int = 13, share: float = 0.05, max_bytes: int = 64 << 20) -> DataFrame:
    """docs -> docs + n_words, n_hit, n_items, items_sha256, contaminated."""
    context = docs.sparkSession.sparkContext
    rows = boxed(docs, text=F.col("text")).withColumns({"hit": F.array().cast("array<binary>"), "ids": F.array().cast("array<string>"), "n": F.lit(None).cast("long")})
    done = 0
    for found in _blocks(benchmark, max_bytes, width):
        if not found:
            continue
        known = context.broadcast(vocabulary(found))
        sizes = {w.count(b" ") == 0 for w in found}
        count = rarity(docs, known, sorted(sizes))
        by_prefix = index(found, known.value, count)
        if done:
            rows = cut(rows)  # more blocks than one: keep what was found so far
        rows, done = _pass(rows, context.broadcast(by_prefix)), done + 1
    if not done:
        rows = rows.withColumn("n", _sizes(F.col("text")))
    return _summed(rows, share)


def _sizes(text):
    @F.pandas_udf("long")
    def size(texts: pd.Series) -> pd.Series:
        return pd.Series([len(words(t)) for t in texts], dtype="int64")

    return size(text)


def _pass(rows: DataFrame, by_prefix) -> DataFrame:
    @F.pandas_udf("hit array<binary>, ids array<string>, n long")
    def probe(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        own, sieve = by_prefix.value, Sieve(np.unique(by_prefix.value.prefix))
        for texts in batches:
            out = []
            for batch in Batch.parts(texts):
                first = len(out)
                out += [([], [], n) for n in batch.sizes.tolist()]
                spots = [sieve.places(batch.shingles(of_one)) for of_one in own.kinds]
                for k in np.unique(np.searchsorted(batch.ends, np.concatenate(spots), side="right")).tolist():
                    ids, mask = hits(batch.words[k], own, batch.own(k))
                    if mask is not None:
                        out[first + k] = [np.packbits(mask).tobytes()], sorted(ids), len(mask)
            yield pd.DataFrame(out, columns=["hit", "ids", "n"])

    out = rows.withColumn("p", probe(F.col("text")))
    return out.withColumns({"hit": F.concat("hit", "p.hit"), "ids": F.array_union("ids", F.col("p.ids")), "n": F.col("p.n")}).drop("p")


def _summed(rows: DataFrame, share: float) -> DataFrame:
    @F.pandas_udf("long")
    def united(masks: pd.Series) -> pd.Series:
        def one(parts) -> int:
            if parts is None or not len(parts):
                return 0
            total = np.frombuffer(parts[0], dtype=np.uint8).copy()
            for p in parts[1:]:
                total |= np.frombuffer(p, dtype=np.uint8)
            return int(np.unpackbits(total).sum())

        return masks.map(one).astype("int64")

    out = rows.withColumn("u", united("hit"))
    limit = round(1 / share)
    n, hit = F.col("n"), F.col("u")
    return unboxed(
        out, n_words=n, n_hit=hit, n_items=F.size("ids").cast("long"), items_sha256=F.sha2(F.array_join(F.array_sort("ids"), ","), 256), contaminated=(hit > 0) & (limit * hit >= n))


__all__ = ["Index", "contamination", "hits", "index", "rarity", "vocabulary", "windows", "words"]
