"""Repeated substrings of a fixed byte length, by difference-cover samples and
suffix buckets.

A set D of offsets modulo v is a difference cover: for any two positions i and
j some k < v puts both i + k and j + k at offsets in D. So two equal strings
of ``length`` bytes hold a pair of equal samples, which are windows of
length - v + 1 bytes at the cover's positions.

1. Cover samples are ranked first: their windows are dealt into buckets by
   hash, a bucket is sorted in one task, and a sample that ties with no other
   is dropped. Suffixes that see only untied samples cannot repeat.
2. The suffixes left are dealt into buckets in turn, and each bucket is
   sorted by itself: the sort key is the hash of the suffix's first ``length``
   bytes.
3. Suffixes that tie are dealt and sorted once more by a second hash of the
   same bytes that shares nothing with the first; those that tie again repeat.
   One hash of 64 bits would call some 10^8 strings of 100 TB repeats that are
   none; two of them, none.
4. Bytes covered by tied suffixes are removed.

Text moves in packed batches of bounded size. A batch sends a bucket each of
its values once, with a flag for what it holds twice, and gets bit masks back;
so a passage in a third of all documents costs one value a batch, not one a
document, and no group is gathered anywhere. Texts with equal bytes are folded
before any of this: all but one take no part, and all of them are removed
whole.

Null and empty texts have no bytes; texts under ``length``
bytes can't repeat; repeated rows are copies of each other; an empty table gives no rows. A document
is the work of one task, whose memory is some 60 bytes for each byte of it.
"""

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chargepath.llm.common import FIRST, SECOND, cut_clean, encoded

#: A perfect difference cover: each difference but 0 modulo 133 comes up once.
PERIOD = 133


def difference_cover(period: int) -> tuple[int, ...]:
    """A cover by greedy search: smallest offsets that add most new differences."""
    known = _PERFECT.get(period)
    if known:
        return known
    cover, missing = [0], set(range(1, period))
    while missing:
        def gain(x: int) -> int:
            return len(missing & {d % period for c in cover for d in (x - c, c - x)})

        best = max(range(1, period), key=lambda x: (gain(x), -x))
        missing -= {d % period for c in cover for d in (best - c, c - best)}
        cover.append(best)
    return tuple(sorted(cover))


def _is_cover(cover: tuple[int, ...], period: int) -> bool:
    return {(a - b) % period for a in cover for b in cover} == set(range(period))


def _singer(q: int) -> tuple[int, ...]:
    """Exponents of a plane in the field of q**3 elements: a perfect cover modulo q*q + q + 1."""
    period = q * q + q + 1
    for c0 in range(1, q):
        for c1 in range(q):
            for c2 in range(q):
                x, seen = (1, 0, 0), []
                for e in range(period):
                    if x[2] == 0:
                        seen.append(e)
                    t = x[2]  # times X, with X**3 = c0 + c1 X + c2 X**2
                    x = (c0 * t % q, (x[0] + c1 * t) % q, (x[1] + c2 * t) % q)
                if len(seen) == q + 1 and _is_cover(tuple(seen), period):
                    return tuple(seen)
    raise ValueError(f"no cover for {q}")


_PERFECT = {q * q + q + 1: _singer(q) for q in (2, 3, 5, 7, 11)}


class Batch:
    """Documents of one packed row: their bytes end to end, and where each starts."""

    def __init__(self, blob: bytes, sizes: bytes) -> None:
        self.data = np.frombuffer(zstandard.ZstdDecompressor().decompress(blob), dtype=np.uint8)
        self.sizes = np.frombuffer(sizes, dtype=np.int64)
        self.ends = np.cumsum(self.sizes)
        self.starts = self.ends - self.sizes
        self._prefix: dict = {}

    def samples(self, use: np.ndarray, length: int, period: int, cover: tuple[int, ...]) -> np.ndarray:
        """Positions of cover samples in the documents marked in use, ascending."""
        window, out = length - period + 1, []
        steps = np.array(cover, dtype=np.int64)
        for s, e in zip(self.starts[use], self.ends[use], strict=True):
            if e - s >= length:
                at = (np.arange(0, e - s, period, dtype=np.int64)[:, None] + steps).ravel()
                out.append(s + at[at <= e - s - window])
        return np.concatenate(out) if out else np.zeros(0, dtype=np.int64)

    def hashes(self, at: np.ndarray, length: int, by=FIRST) -> np.ndarray:
        if by not in self._prefix:
            self._prefix = {by: by.prefixes(self.data)}  # one of them is held at a time
        return by.spans(self._prefix[by], at, at + length)

    def suffixes(self, tied: np.ndarray, length: int, period: int) -> np.ndarray:
        """Positions whose window of length bytes holds a tied sample, ascending."""
        reach = np.zeros(len(self.data) + 1, dtype=np.int32)
        doc = np.searchsorted(self.ends, tied, side="right")
        np.add.at(reach, np.maximum(tied - period + 1, self.starts[doc]), 1)
        np.add.at(reach, tied + 1, -1)
        ok = np.cumsum(reach[:-1]) > 0
        for e, n in zip(self.ends, self.sizes, strict=True):
            ok[max(e - length + 1, e - n) : e] = False
        return np.flatnonzero(ok)


def _packed(values: np.ndarray) -> bytes:
    """Ascending 64-bit values as compressed byte planes of their differences."""
    steps = np.diff(values, prepend=np.uint64(0))
    return zstandard.ZstdCompressor(1).compress(np.ascontiguousarray(steps.view(np.uint8).reshape(-1, 8).T).tobytes())


def _unpacked(data: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), dtype=np.uint8)
    return np.cumsum(np.ascontiguousarray(planes.reshape(8, -1).T).view(np.uint64).ravel(), dtype=np.uint64)


def _dealt(values: np.ndarray, buckets: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(bucket, its distinct values ascending, which of them come twice or more)."""
    own, count = np.unique(values, return_counts=True)
    cuts = np.searchsorted(own, np.arange(buckets, dtype=np.uint64) * np.uint64((1 << 64) // buckets))
    for b, (lo, hi) in enumerate(zip(cuts, [*cuts[1:], len(own)], strict=True)):
        if hi > lo:
            yield b, own[lo:hi], count[lo:hi] > 1


_SENT = "bucket int, batch long, vals binary, twice binary"
_BACK = "batch long, bucket int, ties binary"


def _ties(sent: DataFrame) -> DataFrame:
    """For each batch and bucket, a bit mask of the values that tie with another.

    A group holds the values of one bucket; the number of buckets follows the
    input, so a group has a bounded size.
    """

    def sort_bucket(pdf: pd.DataFrame) -> pd.DataFrame:
        own = [_unpacked(v) for v in pdf["vals"]]
        every = np.concatenate([*own, *(v[np.unpackbits(np.frombuffer(t, dtype=np.uint8), count=len(v)).astype(bool)] for v, t in zip(own, pdf["twice"], strict=True))])
        every.sort()
        tied = np.unique(every[1:][every[1:] == every[:-1]])
        del every

        def mask(v: np.ndarray) -> bytes:
            at = np.searchsorted(tied, v)
            return np.packbits(tied[np.minimum(at, len(tied) - 1)] == v).tobytes() if len(tied) else b""

        return pd.DataFrame({"batch": pdf["batch"], "bucket": pdf["bucket"], "ties": [mask(v) for v in own]})

    return sent.groupBy("bucket").applyInPandas(sort_bucket, _BACK)


def _by_batch(ties: DataFrame) -> DataFrame:
    """batch -> the masks of its buckets; at most one for each bucket."""
    return ties.where("length(ties) > 0").groupBy("batch").agg(F.map_from_entries(F.collect_list(F.struct("bucket", "ties"))).alias("masks"))


def _tied(values: np.ndarray, masks: dict | None, buckets: int) -> np.ndarray:
    """Which of the values tie, by the masks that came back."""
    if not masks:
        return np.zeros(len(values), dtype=bool)
    found = [own[np.unpackbits(np.frombuffer(masks[b], dtype=np.uint8), count=len(own)).astype(bool)] for b, own, _ in _dealt(values, buckets) if b in masks]
    tied = np.concatenate(found) if found else np.zeros(0, dtype=np.uint64)
    if not len(tied):
        return np.zeros(len(values), dtype=bool)
    return tied[np.minimum(np.searchsorted(tied, values), len(tied) - 1)] == values


def _sent(rows: list[tuple[int, int, np.ndarray, np.ndarray]]) -> pd.DataFrame:
    return pd.DataFrame([(b, batch, _packed(own), np.packbits(twice).tobytes()) for b, batch, own, twice in rows], columns=["bucket", "batch", "vals", "twice"])


def _roles(batch: Batch, firsts) -> tuple[np.ndarray, np.ndarray]:
    """(documents that take part, documents that have a copy elsewhere)."""
    use, copied = np.zeros(len(batch.sizes), dtype=bool), np.ones(len(batch.sizes), dtype=bool)
    for f in firsts if firsts is not None else ():
        use[f["row"]], copied[f["row"]] = True, f["copied"]
    return use, copied


def _pack(docs: DataFrame, names: list[str], batch_bytes: int) -> DataFrame:
    """Rows of about batch_bytes: batch, blob, sizes, names (digests of texts), rows (the key columns)."""
    kinds = {f.name: f.dataType.simpleString() for f in docs.schema.fields}
    schema = f"batch long, blob binary, sizes binary, names binary, rows array<struct<{', '.join(f'`{n}`: {kinds[n]}' for n in names)}>>"

    def packed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        part, nth, size = TaskContext.get().partitionId(), 0, 0
        rows, data = [], []

        def flush() -> pd.DataFrame:
            return pd.DataFrame({
                "batch": [(part << 32) + nth], "blob": [zstandard.ZstdCompressor(3).compress(b"".join(data))], "sizes": [np.array([len(d) for d in data], dtype=np.int64).tobytes()],
                "names": [b"".join(hashlib.blake2b(d, digest_size=16).digest() for d in data)], "rows": [rows]})

        for pdf in batches:
            for row, d in zip(pdf["_row"], encoded(pdf["_text"]), strict=True):
                if data and (size + len(d) > batch_bytes or len(data) >= 1 << 16):
                    yield flush()
                    rows, data, size, nth = [], [], 0, nth + 1
                rows.append(row)
                data.append(d)
                size += len(d)
        if data:
            yield flush()

    return docs.select(F.struct(*names).alias("_row"), F.col("text").alias("_text")).mapInPandas(packed, schema)


def _placed(table: DataFrame) -> DataFrame:
    """The packed rows dealt and sorted by batch once and kept so: joins by batch move only what comes back.

    Spark notes how a checkpoint is dealt only if the plan behind it is not adaptive.
    A task that runs again must pack the same rows in the same order.
    """
    conf = table.sparkSession.conf
    adaptive = conf.get("spark.sql.adaptive.enabled")
    conf.set("spark.sql.adaptive.enabled", "false")
    try:
        return cut_clean(table.repartition(int(conf.get("spark.sql.shuffle.partitions")), "batch").sortWithinPartitions("batch"))
    finally:
        conf.set("spark.sql.adaptive.enabled", adaptive)


def _firsts(table: DataFrame) -> DataFrame:
    """batch -> its rows that are the first of their text, each with whether there is a copy."""

    def listed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for batch, names in zip(pdf["batch"], pdf["names"], strict=True):
                n = len(names) // 16
                yield pd.DataFrame({"batch": np.full(n, batch), "row": np.arange(n), "name": [names[16 * k : 16 * k + 16] for k in range(n)]})

    named = table.select("batch", "names").mapInPandas(listed, "batch long, row long, name binary")
    firsts = named.groupBy("name").agg(F.min(F.struct("batch", "row")).alias("f"), F.count("*").alias("n"))
    # One entry at most for each document of a batch.
    return firsts.groupBy(F.col("f.batch").alias("batch")).agg(F.collect_list(F.struct(F.col("f.row").alias("row"), (F.col("n") > 1).alias("copied"))).alias("firsts"))


def remove_repeats(docs: DataFrame, key: list[str], length: int = 200, period: int = PERIOD, batch_mb: int = 4, bucket_mb: int = 32, with_text: bool = False) -> DataFrame:
    """key columns + n_bytes, n_removed, n_spans, kept_sha256 [, kept (binary)]; one row for each row of docs."""
    names = [f.name for f in docs.schema.fields if f.name in key]
    kinds = {f.name: f.dataType.simpleString() for f in docs.schema.fields}
    cover, window = difference_cover(period), length - period + 1
    if window < 1:
        raise ValueError("the cover's period must not pass the length")
    if docs._jdf.queryExecution().executedPlan().nodeName() == "AdaptiveSparkPlan":
        # Rows out of a shuffle or a cache may come in another order when read again.
        docs = cut_clean(docs.select(*dict.fromkeys([*names, "text"])))
    table = _placed(_pack(docs, names, batch_mb << 20))
    table = table.join(cut_clean(_firsts(table)), "batch", "left")
    # Bytes of text by four times their packed size, so buckets follow the input.
    volume = 4 * (table.agg(F.sum(F.length("blob"))).first()[0] or 0)
    sample_buckets = 8 + int(volume * len(cover) / period * 8 / (bucket_mb << 20))
    suffix_buckets = sure_buckets = 8 + int(volume * 2 / (bucket_mb << 20))

    def sample(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for r in pdf.itertuples():
                b = Batch(r.blob, r.sizes)
                at = b.samples(_roles(b, r.firsts)[0], length, period, cover)
                yield _sent([(k, r.batch, own, twice) for k, own, twice in _dealt(b.hashes(at, window), sample_buckets)])

    def suffixes(r) -> tuple[Batch, np.ndarray, np.ndarray]:
        """A batch, its suffixes that may repeat, and which of its documents have copies."""
        b = Batch(r.blob, r.sizes)
        use, copied = _roles(b, r.firsts)
        at = b.samples(use, length, period, cover)
        return b, b.suffixes(at[_tied(b.hashes(at, window), r.ranks, sample_buckets)], length, period), copied

    def suffix(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for r in pdf.itertuples():
                b, at, _ = suffixes(r)
                yield _sent([(k, r.batch, own, twice) for k, own, twice in _dealt(b.hashes(at, length), suffix_buckets)])

    def tied(r) -> tuple[Batch, np.ndarray, np.ndarray]:
        """A batch, its suffixes that tie by the first hash, and which of its documents have copies."""
        b, at, copied = suffixes(r)
        return b, at[_tied(b.hashes(at, length), r.ties, suffix_buckets)], copied

    def confirm(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for r in pdf.itertuples():
                b, at, _ = tied(r)
                yield _sent([(k, r.batch, own, twice) for k, own, twice in _dealt(b.hashes(at, length, SECOND), sure_buckets)])

    def cleared(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for r in pdf.itertuples():
                b, at, copied = tied(r)
                hit = at[_tied(b.hashes(at, length, SECOND), r.sure, sure_buckets)]
                change = np.zeros(len(b.data) + 1, dtype=np.int32)
                np.add.at(change, hit, 1)
                np.add.at(change, hit + length, -1)
                drop, out = np.cumsum(change[:-1]) > 0, []
                for k, (s, e) in enumerate(zip(b.starts, b.ends, strict=True)):
                    own, gone = b.data[s:e], drop[s:e]
                    if copied[k] and e - s >= length:
                        gone = np.ones(e - s, dtype=bool)
                    left = own[~gone].tobytes()
                    out.append((r.rows[k], len(own), int(gone.sum()), int(gone[:1].sum() + (gone[1:] & ~gone[:-1]).sum()), hashlib.sha256(left).hexdigest(), left if with_text else None))
                yield pd.DataFrame(out, columns=["row", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    part = ("batch", "blob", "sizes", "firsts")
    ranks = cut_clean(_by_batch(_ties(table.select(*part).mapInPandas(sample, _SENT)))).withColumnRenamed("masks", "ranks")
    table = table.join(ranks, "batch", "left")
    ties = cut_clean(_by_batch(_ties(table.select(*part, "ranks").mapInPandas(suffix, _SENT)))).withColumnRenamed("masks", "ties")
    table = table.join(ties, "batch", "left")
    sure = cut_clean(_by_batch(_ties(table.where("ties IS NOT NULL").select(*part, "ranks", "ties").mapInPandas(confirm, _SENT)))).withColumnRenamed("masks", "sure")
    rows = f"row struct<{', '.join(f'`{n}`: {kinds[n]}' for n in names)}>, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"
    out = table.join(sure, "batch", "left").mapInPandas(cleared, rows)
    return out.select(*[F.col(f"row.`{n}`").alias(n) for n in names], "n_bytes", "n_removed", "n_spans", "kept_sha256", *["kept"] * with_text)
