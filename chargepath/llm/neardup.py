"""Near-duplicate classes by a multi-index Hamming join over MinHash signatures.

A text becomes a set of word shingles; texts of equal word sequences are one
class from the start. A class has a signature of ``symbols`` b-bit MinHash
values, split into chunks. By the pigeonhole principle, two signatures that
differ in at most ``chunks * (errors + 1) - 1`` symbols agree in some chunk up
to ``errors`` symbols; the allowed errors are enumerated by leaving each
combination of symbols out, so such pairs always share a key. With 32 symbols,
8 chunks and one error that covers a distance of 15 of 32, where a pair of
similarity 0.8 lies at 6.4 on average with a deviation of 2.3. Pairs that share
a key are compared in full if they differ in at most 7 of the 32 symbols, or if
they lie within the threshold of a longer signature: 144 of 512 four-bit
symbols, of which at most 50 among the first 128. That threshold is what makes
two texts with one passage in common no candidates; a pair of similarity 0.8
lies at 96 and 24 with deviations of 8.8 and 4.4, and passes it with a chance to
fail of less than one in a million, as it does to share no key.

Pairs inside a key are never all emitted. First each class is compared with
the nearest leader (lowest class) of its keys, then with the other leaders, and
only where a key still holds different components are the signatures across
them compared, block by block; near pairs, each in one key that it shares,
leave a block as a list of leaders for each class, never as rows. Texts are
compared by the hashes of their shingles, and what these call similar is
confirmed on the words themselves. Rounds are cut in the shared checkpoint
folder.

Null texts and texts without words have the empty set and are linked with
nothing. A row without doc_id belongs to its class but cannot name it; if no
row of a component has one, component_id is null and all its rows are kept.
Repeated rows and ids are in one class or two as their texts say. Very long
texts are read whole; tables without rows give no rows. Only doc_id and text
are read, so other columns can't clash.
"""

import hashlib
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from chargepath.llm.common import LOWER, cut, cut_size, encoded, mix, release, shingle_set

SYMBOLS, CHUNKS, ERRORS = 32, 8, 1
#: Pairs up to this distance always share a key; those up to the second are compared whatever the longer signature says.
MAX_DISTANCE, SURE = CHUNKS * (ERRORS + 1) - 1, CHUNKS - 1
#: Four-bit symbols of the longer signature, those looked at first, and the most in which other compared pairs differ.
LONG, SHORT = 512, 128
NEAR_LONG, NEAR = 144, 50  # at similarity 0.8 they differ in 96 and 24 on average, with a deviation of 8.8 and 4.4
#: Classes in a block of a key, and so leaders of a group that a task compares; their shingles, and members of a group.
BLOCK, GROUP_SHINGLES, GROUP_MEMBERS = 512, 1_000_000, 512
#: Near pairs that a block holds before it lets them go.
HELD_PAIRS = 1 << 17
#: Words of confirmed texts that are held at a time, some 200 bytes each.
CONFIRM_WORDS = 150_000


def _salts(n: int) -> np.ndarray:
    return mix(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


_FIRST = ((_salts(LONG) >> np.uint64(32)).astype(np.uint32) | np.uint32(1))[:, None]
_SECOND = _FIRST ^ np.uint32(0x2C1B3C6C)


def signature(shingles: np.ndarray, block: int = 256) -> bytes:
    """Signature of a set of 64-bit hashes: 32 MinHash symbols of 16 bits, then 512 of 4 bits."""
    small = (shingles >> np.uint64(32)).astype(np.uint32)
    low = np.full(LONG, np.uint32(0xFFFFFFFF))
    for k in range(0, len(small), block):
        x = _FIRST * small[None, k : k + block]
        x ^= x >> np.uint32(15)
        x *= _SECOND
        np.minimum(low, x.min(axis=1), out=low)
    symbols = mix(low.astype(np.uint64))
    nibbles = ((symbols >> np.uint64(20)) & np.uint64(15)).astype(np.uint8)
    return (symbols[:SYMBOLS] & np.uint64(0xFFFF)).astype("<u2").tobytes() + (nibbles[::2] << 4 | nibbles[1::2]).tobytes()


def chunk_keys(signatures: np.ndarray, chunks: int = CHUNKS, errors: int = ERRORS) -> np.ndarray:
    """One row of 64-bit keys for each row of signatures: every chunk under every choice of left-out symbols."""
    n, symbols = signatures.shape
    width = symbols // chunks
    parts = signatures.reshape(n, chunks, width).astype(np.uint64) + np.uint64(1)
    out = []
    for left_out in combinations(range(width), errors):
        key = np.full((n, chunks), np.uint64(len(out) + 1)) + np.arange(chunks, dtype=np.uint64) * np.uint64(64)
        for k in range(width):
            key = mix(key * np.uint64(0x9E3779B97F4A7C15) + (np.uint64(0) if k in left_out else parts[:, :, k]))
        out.append(key)
    return np.concatenate(out, axis=1).view(np.int64)


def shingles_of(data: bytes, width: int) -> frozenset:
    """The word shingles of lower-cased data themselves."""
    words = data.translate(LOWER).split()
    n = min(width, len(words))
    return frozenset(zip(*(words[k:] for k in range(n)), strict=False)) if n else frozenset()


def _alike(shared, a, b, percent: int):
    """Whether sets of sizes a and b with so many shared elements are similar."""
    return 100 * shared >= percent * (a + b - shared)


class Leaders:
    """Texts with which many others are compared, by one index over all their shingles."""

    def __init__(self, width: int, percent: int) -> None:
        self.width, self.percent, self.at = width, percent, {}
        self.data, self.sets, self.values, self.exact, self.held = [], [], None, {}, 0

    def add(self, name: int, data: bytes) -> None:
        self.at[name] = len(self.data)
        self.data.append(data)
        self.sets.append(shingle_set(data, self.width))
        self.values = None

    def similar(self, data: bytes, names) -> list[int]:
        """Those of the named leaders that are similar to a text."""
        own, ask = shingle_set(data, self.width), [n for n in names if n in self.at]
        if not ask or not len(own):
            return []
        if self.values is None:
            every, owner = np.concatenate(self.sets), np.repeat(np.arange(len(self.sets)), [len(s) for s in self.sets])
            order = np.argsort(every, kind="stable")
            self.values, self.owner, self.sizes = every[order], owner[order], np.array([len(s) for s in self.sets])
        lo, hi = np.searchsorted(self.values, own, "left"), np.searchsorted(self.values, own, "right")
        count = hi - lo
        spots = np.repeat(hi - np.cumsum(count), count) + np.arange(count.sum())
        shared = np.bincount(self.owner[spots], minlength=len(self.sets))
        at = np.array([self.at[n] for n in ask])
        close = _alike(shared[at], self.sizes[at], len(own), self.percent) & (self.sizes[at] > 0)
        return self._confirmed(data, [n for n, ok in zip(ask, close.tolist(), strict=True) if ok])

    def _confirmed(self, data: bytes, names: list[int]) -> list[int]:
        """The same on the words; sets of leaders are kept up to a bound."""
        if not names:
            return []
        own, out = shingles_of(data, self.width), []
        for n in names:
            other = self.exact.get(n)
            if other is None:
                other = shingles_of(self.data[self.at[n]], self.width)
                if self.held + len(other) > CONFIRM_WORDS:
                    self.exact, self.held = {}, 0
                self.exact[n], self.held = other, self.held + len(other)
            if _alike(len(own & other), len(own), len(other), self.percent):
                out.append(n)
        return out


def _name(data: bytes) -> bytes:
    """16 bytes that stand for the lower-cased word sequence of data."""
    return hashlib.blake2b(b" ".join(data.translate(LOWER).split()), digest_size=16).digest()


def _sketch(texts: pd.Series, width: pd.Series) -> pd.DataFrame:
    out, known = [], {}
    for data, w in zip(encoded(texts), width, strict=True):
        s = shingle_set(data, int(w))
        if not len(s):
            out.append((0, None, None))
            continue
        name = _name(data)
        if name not in known:
            known[name] = signature(s)
        out.append((len(s), name, known[name]))
    return pd.DataFrame(out, columns=["n_shingles", "cls", "sig"])


def sketches(docs: DataFrame, key: list[str], width: int) -> DataFrame:
    """key columns -> + n_shingles, cls (16 bytes that name the word sequence; null without words), sig."""
    sketch = F.pandas_udf(_sketch, "n_shingles long, cls binary, sig binary")
    rows = docs.select(*key, sketch(F.col("text"), F.lit(width)).alias("_s"))
    return rows.select(*key, "_s.n_shingles", "_s.cls", "_s.sig")


def _keys(classes: DataFrame) -> DataFrame:
    """classes(id, sig) -> (key, id, nth), nth the number of the key within its class."""

    def keyed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            if len(pdf):
                keys = chunk_keys(np.frombuffer(b"".join(x[: 2 * SYMBOLS] for x in pdf["sig"]), dtype="<u2").reshape(len(pdf), -1))
                yield pd.DataFrame({"key": keys.ravel(), "id": np.repeat(pdf["id"].to_numpy(), keys.shape[1]), "nth": np.tile(np.arange(keys.shape[1], dtype=np.int32), len(pdf))})

    return classes.mapInPandas(keyed, "key long, id long, nth int")


def _compare(wanted: DataFrame, texts: DataFrame, width: int, percent: int) -> DataFrame:
    """wanted(home, salt, member, id, leads) and texts(id, text) -> similar pairs (lead, id).

    A group is all rows of a (home, salt). Its leaders come first (member 0)
    and their sets stay while the members stream past; ``leads`` names the
    leaders of the group with which a member is compared.
    """
    rows = wanted.join(texts, "id").repartition("home", "salt").sortWithinPartitions("home", "salt", "member")

    def compared(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        group, own = None, None
        for pdf in batches:
            found = []
            for home, salt, member, i, leads, data in zip(pdf["home"], pdf["salt"], pdf["member"], pdf["id"], pdf["leads"], encoded(pdf["text"]), strict=True):
                if group != (home, salt):
                    group, own = (home, salt), Leaders(width, percent)
                if not member:
                    own.add(i, data)
                else:
                    found += [(lead, i) for lead in own.similar(data, leads)]
            yield pd.DataFrame(found, columns=["lead", "id"], dtype="int64")

    return rows.select("home", "salt", "member", "id", "leads", "text").mapInPandas(compared, "lead long, id long")


def _verify(pairs: DataFrame, texts: DataFrame, width: int, percent: int, chunk: int = 200) -> DataFrame:
    """pairs(lead, id), lead != id, and texts(id, text) -> those pairs that are similar.

    A leader and its members are a group; large groups are dealt over several
    tasks with a copy of the leader each.
    """
    pairs = pairs.withColumn("salt", F.pmod(F.xxhash64("id"), F.ceil(F.count("*").over(Window.partitionBy("lead", F.pmod("id", F.lit(64)))) / chunk)) * 64 + F.pmod("id", F.lit(64)))
    small = pairs.groupBy("lead").agg(F.count("*").alias("n"))
    pairs = pairs.join(small, "lead").withColumn("salt", F.when(F.col("n") <= chunk, F.lit(0).cast("long")).otherwise(F.col("salt"))).drop("n")
    leaders = pairs.select("lead", "salt").distinct().select(F.col("lead").alias("home"), "salt", F.lit(0).alias("member"), F.col("lead").alias("id"), F.array().cast("array<long>").alias("leads"))
    members = pairs.select(F.col("lead").alias("home"), "salt", F.lit(1).alias("member"), "id", F.array("lead").alias("leads"))
    return _compare(leaders.union(members), texts, width, percent)


def components(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """nodes(id), edges(u, v) -> (id, comp), comp the least id that is connected.

    Each step hangs every component on its least neighbour and follows the
    links to their ends, then contracts the edges; the edges left shrink
    geometrically.
    """
    labels = nodes.select("id", F.col("id").alias("comp"))
    edges = cut_size(edges.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).where("u <> v").distinct())
    while not edges.isEmpty():
        up = cut_size(edges.groupBy(F.col("v").alias("c")).agg(F.min("u").alias("p")))
        while True:
            a, b = up.alias("a"), up.alias("b")
            jumped = cut_size(a.join(b, F.col("a.p") == F.col("b.c"), "left").select(F.col("a.c"), F.coalesce("b.p", "a.p").alias("p"), F.col("b.p").isNotNull().alias("moved")))
            up = jumped.drop("moved")
            if jumped.where("moved").isEmpty():
                break
        labels = cut_size(labels.join(up, F.col("comp") == F.col("c"), "left").select("id", F.coalesce("p", "comp").alias("comp")))
        for end in ("u", "v"):
            edges = edges.join(up, F.col(end) == F.col("c"), "left").withColumn(end, F.coalesce("p", end)).select("u", "v")
        edges = cut_size(edges.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).where("u <> v").distinct())
    return labels


def _distance(a: str, b: str, longs: int, bits: int):
    """Differing symbols of ``bits`` bits of two array columns of longs."""
    low = sum(1 << k for k in range(0, 64, bits))
    out = F.lit(0)
    for k in range(longs):
        x = F.get(a, F.lit(k)).bitwiseXOR(F.get(b, F.lit(k)))
        # The low bit of each field tells whether any bit of the field is set.
        s = bits // 2
        while s:
            x = x.bitwiseOR(F.shiftrightunsigned(x, s))
            s //= 2
        out = out + F.bit_count(x.bitwiseAND(F.lit(low)))
    return out


def _longs(sig, start: int, count: int):
    """``count`` longs of a binary column from byte ``start`` on."""
    return F.array(*[F.conv(F.hex(F.substring(sig, start + 8 * k + 1, 8)), 16, -10).cast("long") for k in range(count)])


def _near(percent: int):
    """Whether rows with sizes na, nb, key symbols ka, kb and first symbols sa, sb are to be compared."""
    within = (_distance("ka", "kb", SYMBOLS // 4, 16) <= SURE) | (_distance("sa", "sb", SHORT // 16, 4) <= NEAR)
    return (100 * F.least("na", "nb") >= percent * F.greatest("na", "nb")) & within


def _differing(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Differing four-bit symbols of each row of two arrays of unsigned longs."""
    x = a ^ b
    x |= x >> np.uint64(2)
    x |= x >> np.uint64(1)
    return np.bitwise_count(x & np.uint64(0x1111111111111111)).sum(axis=1)


def _to_compare(keys: np.ndarray, front: np.ndarray, back: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Pairs within the sure distance, and those beyond it that are near in the longer signature."""
    ok = (keys[i] != keys[j]).sum(axis=1) <= SURE
    far = np.flatnonzero(~ok)
    far = far[_differing(front[i[far]], front[j[far]]) <= NEAR]
    far = far[_differing(front[i[far]], front[j[far]]) + _differing(back[i[far]], back[j[far]]) <= NEAR_LONG]
    ok[far] = True
    return ok


def first_shared(a: np.ndarray, b: np.ndarray, chunks: int = CHUNKS, errors: int = ERRORS) -> np.ndarray:
    """For rows of two arrays of key symbols, the number of the first key that both have; -1 without any."""
    width = a.shape[1] // chunks
    same = (a == b).reshape(len(a), chunks, width)
    agree = []
    for left_out in combinations(range(width), errors):
        used = [k for k in range(width) if k not in left_out]
        agree.append(same[:, :, used].all(axis=2))
    agree = np.concatenate(agree, axis=1)
    return np.where(agree.any(axis=1), agree.argmax(axis=1), -1)


def _whole_groups(batches: Iterator[pd.DataFrame], by: list[str]) -> Iterator[pd.DataFrame]:
    """The rows of ``batches``, those of equal ``by``, which adjoin, in one frame."""
    rest = None
    for pdf in batches:
        pdf = pdf if rest is None else pd.concat((rest, pdf), ignore_index=True)
        if len(pdf):
            names = pdf[by].to_numpy()
            other = np.flatnonzero((names != names[-1]).any(axis=1))
            start = other[-1] + 1 if len(other) else 0
            if start:
                yield pdf[:start]
            rest = pdf[start:]
    if rest is not None:
        yield rest


def _ahead(group: np.ndarray, rows: int = 1 << 15) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All index pairs i < j of equal group (equal groups adjoin), a bounded number at a time."""
    starts = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    sizes = np.diff(np.r_[starts, len(group)])
    behind = np.repeat(starts + sizes, sizes) - np.arange(len(group)) - 1
    at, step = np.flatnonzero(behind), 1
    while len(at):
        for k in range(0, len(at), rows):
            yield at[k : k + rows], at[k : k + rows] + step
        step += 1
        at = at[behind[at] >= step]


def _across(members: DataFrame, percent: int) -> DataFrame:
    """Near pairs of different components, as rows (home, salt, member, id, leads) for ``_compare``.

    members(key, lo, hi, block, nth, first, id, comp, n, sig, home, salt): the
    classes of a key are dealt into blocks, and a row goes to each pair of
    blocks (lo, hi) with its own. A pair of one home, the largest key of both,
    is taken there; any other in the first key that it shares. Where a class
    leads that key the pair was tried before.
    """
    by, short = ["key", "lo", "hi"], 2 * SYMBOLS + SHORT // 2

    def found(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in _whole_groups(batches, by):
            sig = np.frombuffer(b"".join(pdf["sig"]), dtype=np.uint8).reshape(len(pdf), -1)
            keys = np.ascontiguousarray(sig[:, : 2 * SYMBOLS]).view("<u2")
            front, back = np.ascontiguousarray(sig[:, 2 * SYMBOLS : short]).view(np.uint64), np.ascontiguousarray(sig[:, short:]).view(np.uint64)
            block, nth, first, ids, comp, n, home, salt = (pdf[c].to_numpy() for c in ("block", "nth", "first", "id", "comp", "n", "home", "salt"))
            names = pdf[by].to_numpy()
            within = names[:, 1] == names[:, 2]
            group = np.cumsum(np.r_[True, (names[1:] != names[:-1]).any(axis=1)])
            out, held = [], 0

            def rows() -> pd.DataFrame:
                """The held pairs: each higher class with the lower ones that lead its groups, and those themselves."""
                i, j = (np.concatenate(x) for x in zip(*out, strict=True))
                order = np.lexsort((i, ids[j], salt[i], home[i]))
                i, j = i[order], j[order]
                names = np.stack((home[i], salt[i], ids[j]))
                starts = np.flatnonzero(np.r_[True, (names[:, 1:] != names[:, :-1]).any(axis=0)])
                alone = np.unique(i)
                return pd.DataFrame({
                    "home": np.r_[home[i[starts]], home[alone]], "salt": np.r_[salt[i[starts]], salt[alone]], "member": np.r_[np.ones(len(starts), np.int32), np.zeros(len(alone), np.int32)],
                    "id": np.r_[ids[j[starts]], ids[alone]], "leads": [*np.split(ids[i], starts[1:]), *[ids[:0]] * len(alone)]})

            for i, j in _ahead(group):
                for test in (
                    lambda i, j: (comp[i] != comp[j]) & ~(first[i] | first[j]) & (within[i] | (block[i] != block[j])) & (100 * np.minimum(n[i], n[j]) >= percent * np.maximum(n[i], n[j])),
                    lambda i, j: _to_compare(keys, front, back, i, j),
                    lambda i, j: np.where(home[i] == home[j], names[i, 0] == home[i], first_shared(keys[i], keys[j]) == nth[i]),
                ):
                    ok = test(i, j)
                    i, j = i[ok], j[ok]
                if len(i):
                    out.append((np.where(ids[i] < ids[j], i, j), np.where(ids[i] < ids[j], j, i)))
                    held += len(i)
                if held > HELD_PAIRS:
                    yield rows()
                    out, held = [], 0
            if out:
                yield rows()

    near = members.repartition(*by).sortWithinPartitions(*by).mapInPandas(found, "home long, salt long, member int, id long, leads array<long>")
    rows = cut(near.groupBy("home", "salt", "member", "id").agg(F.array_distinct(F.flatten(F.collect_list("leads"))).alias("leads")))
    # Groups of many members are dealt over several tasks, with their leaders in each.
    parts = rows.where("member = 1").groupBy("home", "salt").agg(F.ceil(F.count("*") / GROUP_MEMBERS).alias("parts"))
    rows = rows.join(parts, ["home", "salt"])
    part = F.explode(F.when(F.col("member") == 0, F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).otherwise(F.array(F.pmod(F.xxhash64("id", F.lit(2)), "parts"))))
    return rows.withColumn("part", part).select("home", F.xxhash64("salt", "part").alias("salt"), "member", "id", "leads")


def link(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """docs -> (doc_id, n_shingles, component_id, kept), one row for each row of docs.

    The keys and the limits of the longer signature are made for a similarity of
    80 percent; below it they would drop similar pairs.
    """
    if percent < 80:
        raise ValueError("percent must be 80 or more")
    rows = cut(sketches(docs, ["doc_id"], width))
    # A class is named by its least doc_id; where it has none, by a negative hash of its set.
    named = rows.where("cls IS NOT NULL").groupBy("cls").agg(F.min("doc_id").alias("least"), F.min("sig").alias("sig"), F.min("n_shingles").alias("n"))
    named = cut(named.select("cls", F.coalesce("least", -F.abs(F.xxhash64("cls")) - 1).alias("id"), F.col("least").isNull().alias("unnamed"), "sig", "n"))
    # One doc_id may stand for texts of several classes; a class id must be its own.
    order = Window.partitionBy("id").orderBy("cls")
    named = cut(named.withColumn("nth", F.row_number().over(order)).select(
        "cls", F.col("id").alias("least"), "unnamed", "sig", "n", F.when(F.col("nth") == 1, F.col("id")).otherwise(-F.abs(F.xxhash64("cls")) - 1).alias("id")))
    keys = _keys(named.select("id", "sig"))
    lead = keys.groupBy("key").agg(F.min("id").alias("lead"), F.max("id").alias("last")).where("lead <> last").select("key", "lead")
    keys = cut(keys.join(lead, "key"))
    with_partner = keys.select("id").distinct()
    # The texts that any step compares move once.
    texts = cut(_texts(docs, named.join(with_partner, "id", "left_semi")))
    sigs = cut(named.join(with_partner, "id", "left_semi").select("id", "n", _longs(F.col("sig"), 0, SYMBOLS // 4).alias("k"), _longs(F.col("sig"), 2 * SYMBOLS, SHORT // 16).alias("s")))
    # First the nearest leader of a class, then the others.
    one, other = sigs.select("id", F.col("n").alias("na"), F.col("k").alias("ka"), F.col("s").alias("sa")), sigs.select(F.col("id").alias("lead"), F.col("n").alias("nb"), F.col("k").alias("kb"), F.col("s").alias("sb"))
    shared = keys.where("lead <> id").select("id", "lead").distinct().join(one, "id").join(other, "lead").where(_near(percent))
    shared = cut(shared.select("id", "lead", _distance("sa", "sb", SHORT // 16, 4).alias("far")))
    tried = cut(shared.groupBy("id").agg(F.min(F.struct("far", "lead")).alias("x")).select("id", F.col("x.lead").alias("lead")))
    edges = cut(_verify(tried, texts, width, percent))
    labels = components(edges.select(F.col("lead").alias("u"), F.col("id").alias("v")), named.select("id"))
    rest = cut(_apart(shared.select("id", "lead"), labels).join(tried, ["lead", "id"], "left_anti"))
    if not rest.isEmpty():
        more = cut(_verify(rest, texts, width, percent))
        edges = edges.union(more)
        labels = components(edges.select(F.col("lead").alias("u"), F.col("id").alias("v")), named.select("id"))
    release(docs.sparkSession)  # shuffle files of the rounds behind
    # Keys that still hold several components: compare across them.
    members = keys.select("key", "id", "nth", (F.col("id") == F.col("lead")).alias("first")).join(labels.join(named.select("id", "n"), "id"), "id")
    mixed = members.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("many"), F.sum("n").alias("all_n")).where("lo <> hi")
    members = cut(members.join(mixed.drop("lo", "hi"), "key"))
    if not members.isEmpty():
        # Compared texts meet at the largest key of their leader, so that few copies of them are sent.
        parts = F.ceil(F.greatest(F.col("many") / BLOCK, F.col("all_n") / GROUP_SHINGLES))
        homes = members.groupBy("id").agg(F.max(F.struct("many", "key", parts.alias("parts"))).alias("x"))
        whole = named.select("id", "sig").join(homes.select("id", F.col("x.key").alias("home"), F.pmod(F.xxhash64("id"), F.col("x.parts")).alias("salt")), "id")
        blocks = F.ceil(F.col("many") / BLOCK)
        dealt = members.withColumns({"block": F.pmod(F.xxhash64("id"), blocks), "other": F.explode(F.sequence(F.lit(0).cast("long"), blocks - 1))})
        dealt = dealt.select("key", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "block", "nth", "first", "id", "comp", "n").join(whole, "id")
        across = cut(_across(dealt, percent))
        if not across.isEmpty():
            edges = edges.union(_compare(across, texts, width, percent))
            labels = components(edges.select(F.col("lead").alias("u"), F.col("id").alias("v")), named.select("id"))
    # The least doc_id of the whole component.
    classes = named.join(labels, "id").select("cls", "comp", F.when(~F.col("unnamed"), F.col("least")).alias("least"))
    low = classes.groupBy("comp").agg(F.min("least").alias("component_id"))
    classes = classes.join(low, "comp").select("cls", "component_id")
    out = rows.select("doc_id", "n_shingles", "cls").join(classes, "cls", "left")
    component = F.when(F.col("cls").isNull(), F.col("doc_id")).otherwise(F.col("component_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, component.isNull()).alias("kept"))


def _apart(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """pairs(lead, id) whose ends lie in different components."""
    a = labels.select(F.col("id").alias("lead"), F.col("comp").alias("ca"))
    b = labels.select("id", F.col("comp").alias("cb"))
    return pairs.join(a, "lead").join(b, "id").where("ca <> cb").select("lead", "id")


def _texts(docs: DataFrame, named: DataFrame) -> DataFrame:
    """(id, text): one text for each of the classes, found by the class's least doc_id.

    Where a doc_id is missing or repeated, texts are found by the name of their
    word sequence instead; well-formed tables have no such rows.
    """
    some = docs.where("text IS NOT NULL")
    odd = some.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 OR doc_id IS NULL")
    if odd.isEmpty():
        return some.select(F.col("doc_id").alias("id"), "text").join(named.select("id"), "id", "left_semi")

    @F.pandas_udf("binary")
    def name(texts: pd.Series) -> pd.Series:
        return pd.Series([_name(d) for d in encoded(texts)], dtype=object)

    whole = some.select(name("text").alias("cls"), "text").join(named.select("cls", "id"), "cls")
    return whole.groupBy("id").agg(F.min("text").alias("text"))
