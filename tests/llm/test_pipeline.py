"""The pipeline's stages one by one, and as a whole, against brute force."""

import collections
import math
import random
import re

import pytest

import corpus_pipeline
from chargepath.llm import pii, quality

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = re.compile("[^\x20\x09-\x0d]+")


def rows_of(df):
    return sorted((tuple(r) for r in df.collect()), key=repr)


@pytest.fixture(scope="module")
def corpus():
    """Documents with missing, repeated and conflicting ids, copies, junk, contamination and personal data."""
    rng = random.Random(31)
    common = "the of and to in a is that for it".split()
    vocabulary = [*common * 4, *("".join(rng.choice("abcdeimnorst") for _ in range(rng.randint(2, 8))) for _ in range(300))]
    prose = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    item = prose(40)
    texts = [prose(rng.randint(60, 200)) for _ in range(40)]
    for t in texts[:10]:
        w = t.split(" ")
        w[rng.randrange(len(w))] = "changed"
        texts += [" ".join(w), t]
    texts += [f"{prose(60)} {item} {prose(20)}", f"{prose(80)} write john.doe@mail.example.com or 10.1.2.3 {prose(10)}", "# $ % " * 60, "one two three " * 40, "short text", None, "", prose(30_000)]
    rows = []
    for k, t in enumerate(texts):
        i = None if k % 11 == 0 else 5 if k % 9 == 0 else k
        rows.append((i, t, None if k % 13 == 0 else "en", ["a", "b", None][k % 3], len(t or "")))
    rows += rows[3:6]  # repeated rows
    return rows, [(1, item), (2, None), (None, prose(13))]


def brute_quality(rows):
    """Base rules, then Jensen-Shannon distances from references of the rows that pass them."""
    def base(t):
        w = WORDS.findall(t or "")
        at = collections.defaultdict(list)
        for k in range(len(w) - 2):
            at[tuple(w[k : k + 3])].append(k)
        repeat = len({j for spots in at.values() if len(spots) > 1 for k in spots for j in range(k, k + 3)})
        return len(w) < 50 or 100 * repeat > 50 * len(w), len(w)

    def histograms(t):
        t = t or ""
        chars = [len(re.sub(p, "", t)) for p in quality.CLASSES.values()]
        words = collections.Counter(x for w in WORDS.findall(t) if (x := w.rstrip(".,;:!?").lower()) in quality.COMMON)
        return [*chars, len(t) - sum(chars)], words

    def distance(p, q):
        total = 0.0
        for a, b in zip(p, q, strict=True):
            m = (a + b) / 2
            total += (a * math.log(a / m) if a else 0) + (b * math.log(b / m) if b else 0)
        return math.sqrt(max(total, 0.0) / 2 / math.log(2))

    share = lambda xs: [x / sum(xs) for x in xs]
    refs = {}
    for r in rows:
        if not base(r[1])[0]:
            chars, words = histograms(r[1])
            own = refs.setdefault(r[2], ([0] * 7, collections.Counter()))
            own[0][:] = [a + b for a, b in zip(own[0], chars, strict=True)]
            own[1].update(words)
    out = []
    for r in rows:
        failed, n = base(r[1])
        if failed:
            continue
        (chars, words), (all_chars, all_words) = histograms(r[1]), refs[r[2]]
        near = distance(share(chars), share(all_chars))
        names = sorted(all_words)
        by_word = distance(share([words[x] for x in names]), share([all_words[x] for x in names])) if words else 1.0
        if n < 80 or not (near > 0.25 or (by_word > 0.8 and all_words)):
            out.append(r)
    return out


def shingles(t):
    w = [x.lower() for x in WORDS.findall(t or "")]
    n = min(5, len(w))
    return frozenset(tuple(w[k : k + n]) for k in range(len(w) - n + 1)) if n else frozenset()


def groups(rows):
    """Rows by the component of similar texts; rows without words are alone."""
    sets, comp = [shingles(r[1]) for r in rows], list(range(len(rows)))
    def find(k):
        while comp[k] != k:
            k = comp[k]
        return k
    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                comp[max(x, y)] = min(x, y)
    out = collections.defaultdict(list)
    for k, r in enumerate(rows):
        out[find(k)].append(r)
    return list(out.values())


def test_each_stage_equals_brute_force(spark, corpus, tmp_path):
    rows, items = corpus
    spark.createDataFrame(items, "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    docs = spark.createDataFrame(rows, SCHEMA)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality rules", "near duplicates", "decontamination", "personal data", "mixing"]
    (_, rules), (_, near), (_, clean), (_, personal), (_, mix) = corpus_pipeline.STAGES

    kept = brute_quality(rows)
    got = corpus_pipeline.cut(rules(spark, docs, str(tmp_path)))
    assert rows_of(got) == sorted(kept, key=repr) and 30 < len(kept) < len(rows)

    one = rows_of(corpus_pipeline.cut(near(spark, got, str(tmp_path))))
    want = groups(kept)
    first = lambda r: (r[0] is None, r[0] if r[0] is not None else 0, r[1] or "")
    assert one == sorted((min(g, key=first) for g in want), key=repr) and len(one) < len(kept)

    spread = spark.createDataFrame(one, SCHEMA)
    cleaned = rows_of(clean(spark, spread, str(tmp_path)))
    dirty = [r for r in one if r not in cleaned]
    assert len(dirty) == 1 and items[0][1] in dirty[0][1] and set(cleaned) <= set(one)

    masked = rows_of(personal(spark, spark.createDataFrame(cleaned, SCHEMA), str(tmp_path)))
    want = []
    for r in cleaned:
        found = pii.spans(r[1] or "")[1]
        t = pii.masked(r[1], found) if found else r[1]
        want.append((r[0], t, *r[2:4], len(t)))
    assert masked == sorted(want, key=repr) and any("<EMAIL>" in r[1] and "<IP>" in r[1] and "john.doe" not in r[1] for r in masked)

    mixed = mix(spark, spark.createDataFrame(masked, SCHEMA), str(tmp_path)).collect()
    size = collections.Counter()
    for r in masked:
        size[r[3]] += len(WORDS.findall(r[1] or ""))
    taken = collections.Counter()
    for r in mixed:
        taken[r.source] += r.taken
        assert r.taken > 0 and r["size"] == len(WORDS.findall(r.text)) and r.taken <= 2 * r["size"] and r.source_size == size[r.source]
    assert all(abs(taken[r.source] - r.target) <= 1 for r in mixed)
    assert abs(sum({r.source: r.target for r in mixed}.values()) - min(1.5 * sum(size.values()), 2 * sum(size.values()))) < 1


def test_the_whole_pipeline_and_empty_tables(spark, corpus, tmp_path):
    rows, items = corpus
    spark.createDataFrame(items, "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    spark.createDataFrame(rows, SCHEMA).write.parquet(str(tmp_path / "documents.parquet"))
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert 20 < len(out) < len(rows) and not any(items[0][1] in r.text for r in out)
    assert all(len(g) == 1 for g in groups([tuple(r)[:5] for r in out]))
    empty = spark.createDataFrame([], SCHEMA)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, str(tmp_path)).count() == 0
