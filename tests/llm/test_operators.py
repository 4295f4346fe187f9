import collections
import hashlib
import pathlib
import random
import re
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from chargepath.llm import decontam, licenses, mixing, neardup, pii, quality, substrings, tokens, toxicity, urls

WORDS = re.compile("[^\x20\x09-\x0d]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def make(spark, texts):
    return spark.createDataFrame([(k, t, "en", "s", len(t or "")) for k, t in enumerate(texts)], SCHEMA)


@pytest.fixture(scope="module")
def texts():
    rng = random.Random(5)
    vocabulary = ["".join(rng.choice("abcdeé") for _ in range(rng.randint(1, 6))) for _ in range(400)]
    base = [" ".join(rng.choices(vocabulary, k=rng.randint(60, 200))) for _ in range(25)]
    out = [*base, None, "", " \n\t", "one", "Two words", "x" * 5000]
    for t in base[:12]:
        w = t.split(" ")
        for _ in range(3):
            own = list(w)
            for _ in range(rng.randint(0, 6)):
                own[rng.randrange(len(own))] = rng.choice(vocabulary)
            out.append(" ".join(own))
    return [*out, base[3], base[3], f"{base[0][:250]} {base[1][40:300]}"]


def test_near_duplicates_equal_brute_force(spark, texts):
    def shingles(t):
        w = [x.lower() for x in WORDS.findall(t or "")]
        n = min(4, len(w))
        return frozenset(tuple(w[k : k + n]) for k in range(len(w) - n + 1)) if n else frozenset()

    sets = [shingles(t) for t in texts]
    comp = list(range(len(texts)))
    for _ in texts:
        for a in range(len(texts)):
            for b in range(a):
                if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                    comp[a] = comp[b] = min(comp[a], comp[b])
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in neardup.link(make(spark, texts), 4).collect()}
    assert got == {k: (len(sets[k]), comp[k], comp[k] == k) for k in range(len(texts))}


def test_near_duplicates_with_missing_and_repeated_ids(spark):
    t = " ".join(f"w{k}" for k in range(50))
    rows = spark.createDataFrame([(None, t), (None, t), (4, t), (4, "other text here today"), (None, "alone and without any id")], "doc_id long, text string")
    got = [(r.doc_id, r.component_id, r.kept) for r in neardup.link(rows, 4).collect()]
    assert len(got) == 5 and (4, 4, True) in got and got.count((None, 4, False)) == 2 and (None, None, True) in got


def test_near_duplicates_refuse_a_similarity_they_would_miss(spark):
    with pytest.raises(ValueError):
        neardup.link(make(spark, ["a b c d e"]), 4, percent=79)


def test_substrings_equal_brute_force(spark, texts):
    data = [(t or "").encode() for t in texts]
    seen = collections.Counter(d[k : k + 200] for d in data for k in range(len(d) - 199))
    want = {}
    for k, d in enumerate(data):
        gone = bytearray(len(d))
        for at in range(len(d) - 199):
            if seen[d[at : at + 200]] > 1:
                gone[at : at + 200] = b"\1" * 200
        kept = bytes(c for c, g in zip(d, gone) if not g)
        want[k] = (len(d), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(kept).hexdigest())
    got = substrings.remove_repeats(make(spark, texts), ["doc_id"]).collect()
    assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got} == want
    dealt = substrings.remove_repeats(make(spark, texts).repartition(3, "doc_id"), ["doc_id"]).collect()
    assert sorted(dealt) == sorted(got)


def test_substrings_hold_no_shuffle_files_of_earlier_steps(spark, monkeypatch):
    """Not even if no garbage is collected meanwhile; and the last step moves masks, not texts."""
    manager = spark.sparkContext._jsc.sc().env().blockManager().diskBlockManager()

    def dealt():
        files = manager.getAllFiles()
        return {f.getName(): f.length() for f in (files.apply(k) for k in range(files.size())) if f.getName().startswith("shuffle_")}

    monkeypatch.setattr(substrings, "release", lambda _: None, raising=False)
    rng = random.Random(9)
    texts = [f"{k} " + rng.randbytes(1500).hex() for k in range(600)]
    docs, before = make(spark, [*texts, *(f"x{t[:500]}" for t in texts)]), dealt()
    out = substrings.remove_repeats(docs, ["doc_id"], batch_mb=1)
    assert not dealt().keys() - before.keys()
    assert sum(r.n_removed > 0 for r in out.collect()) == 1200
    assert sum(n for f, n in dealt().items() if f not in before) < 300_000


@pytest.mark.parametrize("period", [7, 13, 31, 57, 133, 20])
def test_difference_covers(period):
    cover = substrings.difference_cover(period)
    assert substrings._is_cover(cover, period)


def test_token_counts_equal_the_library(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    rng = random.Random(2)
    odd = ["a\x1cb", "<|endoftext|>x <|startoftext|>", "ΑΣ ΑΣ. İx", "don't it's 'S", "é ́x", "日本語。12a", "", " \n", *("".join(rng.choice("aB'sΣ ,.!́é \x1d9t<|endoftext|>") for _ in range(50)) for _ in range(300))]
    want = [len(library.encode(t, add_special_tokens=False).ids) for t in odd]
    for chunk in (1 << 16, 3):
        got = tokens.count_tokens(make(spark, odd), chunk=chunk).orderBy("doc_id").collect()
        assert [r.n_tokens for r in got] == want


def test_base_spans_equal_plain_patterns():
    rng = random.Random(4)
    for _ in range(3000):
        t = "".join(rng.choice(["a", "9", "4111 1111 1111 1111", ".", "@", "-", " ", "+1 (555) 123-4567", "x.y@b.co", "10.0.0.1", "é", "%"]) for _ in range(12))
        want = [m.span() for m in pii.EMAIL.finditer(t)]
        assert pii.emails(t) == want
        base, every = pii.spans(t)
        assert set(base) <= set(every)


def test_disguises_map_back():
    for text, found in (
        ("mail john (at) mail dot example dot com now", "john (at) mail dot example dot com"), ("to jоhn@mаil.com x", "jоhn@mаil.com"), ("to john at mail.example.com now", "john at mail.example.com"),
        ("x john arroba mail punto com.", "john arroba mail punto com"), ("call plus one two three four five six seven eight nine zero", "plus one two three four five six seven eight nine zero"),
        ("ip 192 dot 168 dot 0 dot 1 ok", "192 dot 168 dot 0 dot 1"), ("at 192[.]168[.]1[.]2", "192[.]168[.]1[.]2"), ("one nine two dot one six eight dot zero dot one", "one nine two dot one six eight dot zero dot one"),
        ('token = "04dbebab91ab85687d33eeaaf9ac699e1188f962"', "04dbebab91ab85687d33eeaaf9ac699e1188f962")):
        base, every = pii.spans(text)
        assert not base and [text[a:b] for _, a, b in every] == [found]
    assert pii.spans("we meet at noon. dot the i, one two. look at this. Example, 12 dot 5, a token of thanks = none") == ([], [])


def test_base_spans_of_very_long_digit_runs():
    t = "1.2.3." + "0" * 5000 + " 9.9.9.256"
    assert pii.spans(t)[0] == [("ip", 0, 5006)]
    for part in ("1", "one ", " at", "(", "a1", "+1", "1.", "a@", "x dot ", "token=", "a at b.cc ", "4111-"):
        start = time.process_time()
        pii.spans(part * (1_000_000 // len(part)) + " 1.1")
        assert time.process_time() - start < 10  # quadratic scans would take minutes


def test_personal_data_query_equals_the_patterns(spark, texts):
    """All columns of the contract against plain patterns."""
    ip, card = re.compile(r"[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)"), re.compile(r"[0-9](?:[\x20-]?[0-9])+")
    rng = random.Random(8)
    odd = ["".join(rng.choice(["a", "9", "0", "4111 1111 1111 1111", ".", "@", "-", " ", "+1 (555) 123-4567", "x.y@b.co", "10.0.0.1", "255", "é", "%"]) for _ in range(30)) for _ in range(300)]
    data = [*odd, *texts, None, ""]
    got = {r.doc_id: r for r in pii.find_pii(make(spark, data)).select("doc_id", *pii.counts(F.col("base_spans")), "base_spans", "spans").collect()}
    for k, t in enumerate(data):
        t = t or ""
        want = [("email", *m.span()) for m in pii.EMAIL.finditer(t)]
        want += [("ip", *m.span()) for m in ip.finditer(t) if all(int(p) < 256 for p in m[0].split("."))]
        want += [("card", *m.span()) for m in card.finditer(t) if 12 <= len(d := re.sub("[^0-9]", "", m[0])) <= 19 and pii.luhn(d)]
        want += [("phone", *m.span()) for m in pii.PHONE.finditer(t) if 9 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
        want.sort(key=lambda s: (s[1], pii.KINDS.index(s[0])))
        joined = [f"{a}:{b}:{c}" for a, b, c in want]
        assert got[k].base_spans == ",".join(joined) and set(joined) <= set(got[k].spans.split(",")) | set(joined[:0])
        assert [got[k][f"n_{x}"] for x in pii.KINDS] == [sum(s[0] == x for s in want) for x in pii.KINDS]


def test_words_that_defeat_polynomial_hashes_are_not_linked(spark):
    a = "a"
    for _ in range(11):
        a += a.translate(str.maketrans("ab", "ba"))
    rows = spark.createDataFrame([(1, a), (2, a.translate(str.maketrans("ab", "ba"))), (3, a.upper())], "doc_id long, text string")
    assert {(r.doc_id, r.component_id) for r in neardup.link(rows, 4).collect()} == {(1, 1), (2, 2), (3, 1)}
    leaders = neardup.Leaders(4, 80)
    leaders.add(1, b"a b c d e")
    leaders.sets = [neardup.shingle_set(b"v w x y z", 4)]  # as if all hashes were equal
    assert leaders.similar(b"v w x y z", [1]) == [] and neardup.Leaders(4, 80).similar(b"a b", [1]) == []


def test_every_pair_within_the_sure_distance_is_compared():
    rng = np.random.default_rng(3)
    keys = rng.integers(0, 1 << 16, (2, neardup.SYMBOLS), dtype=np.uint16)
    keys[1, neardup.SURE :] = keys[0, neardup.SURE :]
    far = np.arange(2 * 8, dtype=np.uint64).reshape(2, 8) * np.uint64(0x9E3779B97F4A7C15)
    ok = neardup._to_compare(keys, far, np.tile(far, 3), np.array([0]), np.array([1]))
    assert ok.tolist() == [True]


def test_quality_equals_brute_force(spark, texts):
    more = [*texts, "a b c a b c a b c", "l one\nl one\n\n \nl one", "# x $ y <z>", "w " * 30]
    got = {r.doc_id: r for r in quality.judge(make(spark, more), ["doc_id"]).collect()}
    assert len(got) == len(more)
    for k, t in enumerate(more):
        w = WORDS.findall(t or "")
        at = collections.defaultdict(list)
        for i in range(len(w) - 2):
            at[tuple(w[i : i + 3])].append(i)
        repeat = len({j for spots in at.values() if len(spots) > 1 for i in spots for j in range(i, i + 3)})
        lines = [x for x in (t or "").split("\n") if WORDS.search(x)]
        r = got[k]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), sum((t or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), repeat)
        assert r.base_failed == (len(w) < 50 or 100 * repeat > 50 * len(w))


def test_decontamination(spark):
    item = " ".join(f"word{k}" for k in range(20))
    docs = ["so " + item.upper() + " end", "word0 word1 word2", " ".join(item.split()[:12]), None, "short one here", " ".join(["z"] * 400) + " short  item"]
    bench = spark.createDataFrame([(7, item), (9, "short item"), (None, ""), (10, None)], "item_id long, text string")
    for block in (64 << 20, 6000):
        got = [(r.n_words, r.n_hit, r.n_items, r.contaminated) for r in decontam.contamination(make(spark, docs), bench, max_bytes=block).orderBy("doc_id").collect()]
        assert got == [(22, 20, 1, True), (3, 0, 0, False), (12, 0, 0, False), (0, 0, 0, False), (3, 0, 0, False), (402, 2, 1, False)]


def test_mix_meets_targets(spark):
    rng = random.Random(1)
    rows = [(k, "w " * rng.randint(0, 60), "en", rng.choice(["a", "b", None, "c"]), 0) for k in range(400)]
    docs = spark.createDataFrame(rows, SCHEMA)
    got = mixing.mix_sources(docs, mixing.word_count(docs["text"])).collect()
    assert len(got) == 400 and all(0 <= r.taken <= 2 * r.size for r in got)
    total = sum(r.size for r in got)
    by = collections.defaultdict(list)
    for r in got:
        by[r.source].append(r)
    assert abs(sum(own[0].target for own in by.values()) - 1.5 * total) < 1e-6
    for own in by.values():
        assert own[0].source_size == sum(r.size for r in own) and abs(sum(r.taken for r in own) - own[0].target) <= 1
    again = mixing.mix_sources(docs.repartition(3), mixing.word_count(docs["text"])).collect()
    assert sorted((r.doc_id, r.taken) for r in again) == sorted((r.doc_id, r.taken) for r in got)


def test_word_count(spark):
    odd = [None, "", " ", "a", " a", "a ", "\n a\tb \r\nc\x0b\x0cd ", "a\xa0b", "  a  b  "]
    got = make(spark, odd).withColumn("n", mixing.word_count(F.col("text")))
    assert {r.doc_id: r.n for r in got.collect()} == {k: len(WORDS.findall(t or "")) for k, t in enumerate(odd)}


def test_urls(spark):
    odd = [None, "no-scheme.net/x", "http://", "https://A.B.Net?x=1", "http://x.example.net/en/1", "http://example.com/de/#a", "http://sub.example.com/de", "ftp://q.org/fr/a?b", "http://badnet/x"]
    pages = spark.createDataFrame(list(enumerate(odd)), "page_id long, url string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge(pages).collect()}
    assert got[0] == got[1] == ("", "", None, "allow")
    assert got[4] == ("x.example.net", "/en/1", "example.net/en/", "allow")
    assert got[5] == ("example.com", "/de/", "example.com/de/", "block")
    assert got[6][2] is None and got[8][2] is None and got[7][2:] == ("org/fr/", "allow")
    assert got[3] == ("a.b.net", "", None, got[3][3])


def test_licenses(spark):
    docs = make(spark, [licenses.KNOWN["MIT"].upper().replace(",", " ,"), "Copyright (c) 2020 A. Person\n" + licenses.KNOWN["ISC"], "text\n  Released under the MIT Licence!\nmore", None, ""])
    got = [(r.license, r.notices) for r in licenses.scan(docs).orderBy("doc_id").collect()]
    assert got[0][0] == "MIT" and got[1][0] == "ISC" and got[2] == (None, "notice:MIT") and got[3] == got[4] == (None, "")


def test_standard_licence_files(spark):
    mit = "MIT License\n\nCopyright (c) 2020 A. Person\n\n" + licenses.KNOWN["MIT"].replace(". ", ".\n\n")
    bodies = {
        "MIT": [mit, mit.replace("2020 ", ""), mit.replace("MIT License", "The MIT License (MIT)"), mit.replace("Copyright (c) 2020 A. Person", "© Some Body")],
        "BSD-3-Clause": ["BSD 3-Clause License\n\nCopyright (c) Some Body\nAll rights reserved.\n\n" + licenses.KNOWN["BSD-3-Clause"]],
        "Unlicense": [licenses.KNOWN["Unlicense"].replace("non-commercial", "noncommercial")],
    }
    folder = pathlib.Path("/usr/share/common-licenses")
    files = {"GPL-3.0": "GPL-3", "LGPL-2.1": "LGPL-2.1", "Apache-2.0": "Apache-2.0", "MPL-2.0": "MPL-2.0", "CC0-1.0": "CC0-1.0"}
    for name, file in files.items():
        if (folder / file).exists():
            bodies[name] = [(folder / file).read_text(), "\t" + (folder / file).read_text().upper().replace("\n", "\r\n")]
    want = [(name, text) for name, some in bodies.items() for text in some]
    got = licenses.scan(make(spark, [t for _, t in want])).orderBy("doc_id").collect()
    assert [r.license for r in got] == [n for n, _ in want]


def test_licence_scan_of_odd_rows(spark):
    docs = make(spark, [None, "", "MIT License", "licence licence LICENCE", "x\n// SPDX-License-Identifier: MPL-2.0\n" * 3, "é" * 200_000]).withColumns({"digest": F.lit(1), "row": F.lit(2), "known": F.lit(3)})
    twice = docs.union(docs)
    got = licenses.scan(twice).orderBy("doc_id").collect()
    assert len(got) == 12 and all(r["row"] == 2 and r["known"] == 3 and r.license is None for r in got)
    assert [r.notices for r in got[::2]] == ["", "", "", "", "notice:SPDX:MPL-2.0", ""]
    canonical = spark.createDataFrame([("licence licence LICENCE",)], "t string").select(licenses.canonical(F.col("t")).alias("c")).first().c
    assert canonical == "license license license" and licenses.scan(docs.where("false")).count() == 0


def test_notices_in_other_spellings(spark):
    lines = ["Licenced under the Apache License, Version 2.0.", "  * LICENCED under CC BY 4.0.", "é Licensed under CC BY 4.0."]
    got = [r.notices for r in licenses.scan(make(spark, [f"text\n{x}\nmore" for x in lines])).orderBy("doc_id").collect()]
    assert got == ["notice:Apache-2.0", "notice:CC-BY-4.0", ""]


def test_toxicity_learns_stems():
    rows = [(f"the day is fine {k}", 0) for k in range(60)] + [(f"you are such an idiot {k}", 1) for k in range(20)]
    g = toxicity.fit(rows)
    assert g.score("what an idiot") > 0.7 > 0.3 > g.score("what a day") and 0 <= g.score(None) <= 1
    assert toxicity.fit([]).score("") >= 0


def test_empty_tables(spark):
    none = spark.createDataFrame([], SCHEMA)
    assert neardup.link(none).count() == 0
    assert substrings.remove_repeats(none, ["doc_id"]).count() == 0
    assert quality.judge(none, ["doc_id"]).count() == 0
    assert mixing.mix_sources(none, mixing.word_count(none["text"])).count() == 0
    assert urls.judge(spark.createDataFrame([], "page_id long, url string")).count() == 0
    assert decontam.contamination(none, spark.createDataFrame([], "item_id long, text string")).count() == 0


def test_first_shared_key_is_the_first_equal_key():
    rng = np.random.default_rng(5)
    a = rng.integers(0, 1 << 16, (200, neardup.SYMBOLS), dtype=np.uint16)
    b = np.where(rng.random(a.shape) < 0.5, a, rng.integers(0, 1 << 16, a.shape, dtype=np.uint16))
    same = neardup.chunk_keys(a) == neardup.chunk_keys(b)
    want = {k: int(row.argmax()) if row.any() else -1 for k, row in enumerate(same)}
    assert dict(enumerate(neardup.first_shared(a, b).tolist())) == want
    assert len(set(want.values())) > 8


def test_pairs_ahead_are_all_pairs_of_a_group():
    group = np.array([1, 1, 1, 2, 3, 3, 4, 4, 4, 4])
    got = sorted((int(a), int(b)) for i, j in neardup._ahead(group, 3) for a, b in zip(i, j, strict=True))
    assert got == [(a, b) for a in range(10) for b in range(a + 1, 10) if group[a] == group[b]]


def test_near_duplicates_in_a_dense_group_of_near_misses(spark, monkeypatch):
    monkeypatch.setattr(neardup, "BLOCK", 7)
    monkeypatch.setattr(neardup, "GROUP_MEMBERS", 3)
    monkeypatch.setattr(neardup, "HELD_PAIRS", 5)
    rng = np.random.default_rng(11)
    # Half of the texts are chained copies, half keep about 0.75 to 0.85 of a common text.
    base = [f"w{k}" for k in range(120)]
    texts, last = [], base
    for k in range(120):
        words = list(last if k % 2 else base)
        for at in rng.choice(len(words), 2 if k % 2 else 3 + k % 3, replace=False):
            words[at] = f"x{k}_{at}"
        last = words if k % 2 else last
        texts.append(" ".join(words))
    sets = [{tuple(t.split()[k : k + 4]) for k in range(117)} for t in texts]
    comp, links = list(range(120)), 0
    changed = True
    while changed:
        changed = False
        for a in range(120):
            for b in range(a):
                if 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                    links += 1
                    if comp[a] != comp[b]:
                        comp[a] = comp[b] = min(comp[a], comp[b])
                        changed = True
    got = {r.doc_id: r.component_id for r in neardup.link(make(spark, texts), 4).collect()}
    assert links and 1 < len(set(comp)) < 120
    assert got == dict(enumerate(comp))


def test_near_duplicate_stage_keeps_one_row_of_each_group(spark):
    a, b, c, d = (" ".join(f"{x}{k}" for k in range(60)) for x in "abcd")
    rows = [(1, a), (1, b), (1, b + " more"), (2, c), (3, c), (None, a), (None, d), (None, d), (None, None), (4, "")]
    docs = spark.createDataFrame([(k, t, "en", "s", len(t or "")) for k, t in rows], SCHEMA)
    got = sorted(((r.doc_id, r.text) for r in corpus_pipeline.near_duplicate_stage(spark, docs, "").collect()), key=repr)
    assert got == sorted([(1, a), (1, b), (2, c), (None, d), (None, None), (4, "")], key=repr)


def test_merge_transducer_equals_the_merge_table():
    """Random merge tables over few letters, every short piece."""
    import itertools

    rng = random.Random(12)
    for _ in range(40):
        tokens_, merges = ["a", "b", "c", "a.", "b.", "c."], []
        for _ in range(10):
            pair = rng.choice(tokens_), rng.choice(tokens_)
            if not pair[0].endswith(".") and pair[0] + pair[1] not in tokens_ and len(pair[0] + pair[1]) < 7:
                merges.append(pair)
                tokens_.append(pair[0] + pair[1])
        machine = tokens.MergeTransducer(merges, tokens_[:6], most=30)
        for n in range(1, 7):
            for letters in itertools.product("abc", repeat=n):
                symbols = [*letters[:-1], letters[-1] + "."]
                assert machine.count(symbols) == len(machine.merged(tuple(symbols))), (merges, symbols)


def test_token_counts_of_nulls_and_long_texts(spark):
    from tokenizers import Tokenizer
    import public_tokenizers

    library = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    rng = random.Random(3)
    long = ["x" * 300_000, "word é日 <|endoftext|> " * 30_000, "".join(rng.choice("abcdé .") for _ in range(200_000))]
    data = [None, "", *long, long[2]]
    rows = make(spark, data).withColumn("row", F.lit(1)).withColumn("n_bytes", F.lit("old"))
    got = tokens.count_tokens(rows).orderBy("doc_id").collect()
    assert [r.n_tokens for r in got] == [len(library.encode(t or "", add_special_tokens=False).ids) for t in data]
    assert [r.n_bytes for r in got] == [len((t or "").encode()) for t in data] and all(r["row"] == 1 for r in got)


def naive_clause(g, words):
    """The grammar by windows of words, without machines."""
    total = 0.0
    for k, w in enumerate(words):
        value = max((v for s, v in g.stems.items() if (w == s[:-1] if s.endswith("$") else w.startswith(s))), default=0.0)
        threat = w in toxicity.THREATS
        if not value and not threat:
            continue
        if threat and any(x in toxicity.TARGETS for x in words[max(0, k - 3) : k + 4]):
            value = max(value, 1.0)
        if any(x in toxicity.TARGETS for x in words[max(0, k - 4) : k + 5]):
            value *= 1.25
        if any(x in toxicity.NEGATIONS for x in words[max(0, k - 3) : k]):
            value *= 0.6
        if any(x in toxicity.REPORTS for x in words[:k]):
            value *= 0.7
        total += value
    return total


def test_composed_machines_equal_the_naive_grammar():
    g = toxicity.Grammar({"idiot$": 1.0, "mor": 0.5, "moro": 0.8, "scum$": 1.2, "you$": 0.1})
    rng = random.Random(6)
    vocabulary = ["idiot", "moron", "more", "scum", "you", "they", "not", "never", "said", "kill", "beat", "the", "day", "a", "idiots", "zzz"]
    for _ in range(4000):
        words = rng.choices(vocabulary, weights=[1] * 11 + [6] * 5, k=rng.randint(0, 25))
        assert abs(g.clause(words) - naive_clause(g, words)) < 1e-9, words
    start = time.process_time()
    g.features("idiot " * 400_000)  # one clause without a stop
    assert time.process_time() - start < 10


def test_toxicity_of_nulls_ties_and_empty_tables(spark):
    rows = make(spark, [None, "", "you are an idiot", "you are an idiot", "a fine day", "idiot " * 50_000]).withColumn("score", F.lit("old"))
    g = toxicity.fit([(f"the day is fine {k}", 0) for k in range(60)] + [(f"you are such an idiot {k}", 1) for k in range(20)])
    got = toxicity.score_toxicity(rows, g).orderBy("doc_id").collect()
    assert got[0].score == got[1].score == got[4].score < 0.3 and got[2].score == got[3].score > 0.7
    assert [r.predicted for r in got[:5]] == [0, 0, 1, 1, 0] and 0 <= got[5].score <= 1
    assert toxicity.score_toxicity(rows.where("false"), g).count() == 0
    labels = spark.createDataFrame([(k, 0, k % 2) for k in range(6)] + [(None, 0, 1), (2, 1, None)], "doc_id long, quality int, toxic int")
    train = toxicity.training_rows(rows.select("doc_id", "text"), labels, 100)
    assert 0 < len(train) <= 6 and toxicity.training_rows(rows.select("doc_id", "text"), labels.where("false"), 100) == []


def test_mix_of_equal_rows_conflicting_ids_and_clashing_names(spark, monkeypatch):
    rows = [(7, "w " * 10, "en", "a", 0)] * 301 + [(7, "v " * 10, "en", "a", 0), (None, "u " * 9, "en", None, 0), (None, None, None, None, None), (8, "", "en", "b", 0)] + [(k, "x y z", "en", "b", 0) for k in range(10, 60)]
    docs = spark.createDataFrame(rows, SCHEMA).withColumns({"size": F.lit("old"), "nth": F.lit(1), "edge": F.lit(2)})
    runs = []
    for parts, ranges, most in ((1, 20_000, 200_000), (7, 5, 0)):
        got = mixing.mix_sources(docs.repartition(parts), mixing.word_count(F.col("text")), range_rows=ranges, max_broadcast=most).collect()
        assert len(got) == len(rows) and all(0 <= r.taken <= 2 * r["size"] and r.nth == 1 and r.edge == 2 for r in got)
        for name in ("a", "b", None):
            own = [r for r in got if r.source == name]
            assert own[0].source_size == sum(r["size"] for r in own) and abs(sum(r.taken for r in own) - own[0].target) <= 1
        runs.append(sorted((repr(r.doc_id), r.text or "", r.taken) for r in got))
    again = mixing.mix_sources(docs.repartition(3), mixing.word_count(F.col("text"))).collect()
    assert sorted((repr(r.doc_id), r.text or "", r.taken) for r in again) == runs[0]


def test_url_mining_is_bounded_by_equal_tokens(spark):
    template = "http://spam.example.org/" + "/".join(f"t{chr(97 + k)}x" for k in range(24)) + "/{}"
    rows = [(k, template.format("page")) for k in range(60)] + [(100 + k, f"http://casino.host{k}.example.org/page/{k}") for k in range(40)] + [(200 + k, f"http://a{k}.example.net/x/casino/{k}") for k in range(40)]
    rows += [(300, None), (301, ""), (302, "http://" + "q" * 100_000 + ".org/fr/x"), (303, "http://plain.example.org/y")]
    pages = spark.createDataFrame(rows, "page_id long, url string").withColumns({"host": F.lit("old"), "row": F.lit(1)})
    got = {r.page_id: r for r in urls.judge(pages).collect()}  # 2^24 item sets without the merging of equal tokens
    assert len(got) == len(rows) and all(r["row"] == 1 for r in got.values())
    assert {got[100 + k].verdict for k in range(40)} == {"block"} and {got[100 + k]["rule"] for k in range(40)} == {None}
    assert got[0].verdict == "allow" and got[303].verdict == "allow" and got[300].verdict == "allow" and got[302]["rule"] == "org/fr/"
    given = urls.judge(pages.select("page_id", "url"), labels=F.when(F.col("url").contains("spam."), "block")).collect()
    assert {r.verdict for r in given if r.page_id < 60} == {"block"}


def test_url_rules_equal_brute_force(spark):
    rng = random.Random(10)
    hosts = ["example.net", "x.example.net", "EXAMPLE.com", "a.b.org", "org", "net", "badnet", "example.com.", ""]
    odd = ["".join((rng.choice(["http://", "https://", "://", "", "a://b://"]), rng.choice(hosts), rng.choice(["", "/", "/en/", "/de/x", "/fr/", "/fr", "/EN/"]), rng.choice(["", "?q=/de/", "#/en/", "é"]))) for _ in range(400)]
    pages = spark.createDataFrame(list(enumerate(odd)), "page_id long, url string")
    got = {r.page_id: r for r in urls.judge(pages).collect()}
    for k, u in enumerate(odd):
        rest = u.split("://", 1)[1] if "://" in u else ""
        host = re.match("[^/?#]*", rest)[0]
        path = re.match("[^?#]*", rest[len(host) :])[0]
        host = host.translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
        fits = [(h + p, v) for h, p, v in urls.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        rule, verdict = max(fits, key=lambda f: len(f[0]), default=(None, None))
        r = got[k]
        assert (r.host, r.path, r["rule"]) == (host, path, rule), u
        assert r.verdict == (verdict or ("allow" if r.mined is None else r.verdict)) and r.verdict in urls.VERDICTS


def test_decontamination_equals_brute_force(spark):
    rng = random.Random(21)
    vocabulary = ["".join(rng.choice("abé1") for _ in range(rng.randint(1, 3))) for _ in range(25)]
    phrase = lambda n: "".join(rng.choice(vocabulary) + rng.choice([" ", "  ", ", ", "-", ".\n"]) for _ in range(n))
    items = [(k % 9, phrase(rng.choice([0, 1, 2, 5, 13, 20, 40]))) for k in range(25)] + [(None, phrase(14)), (3, None)]
    docs = [None, "", *(phrase(rng.randint(0, 60)) for _ in range(120))]
    docs += [f"{phrase(5)}{items[rng.randrange(25)][1].upper()} {phrase(rng.randint(0, 300))}" for _ in range(80)] + [phrase(13) * 4000]
    plain = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
    cut_up = lambda t: plain.findall((t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))
    wins = {}
    for i, t in items:
        w = cut_up(t)
        n = min(13, len(w))
        for k in range(len(w) - n + 1 if n else 0):
            wins.setdefault(tuple(w[k : k + n]), set()).update(() if i is None else (str(i),))
    want = []
    for t in docs:
        w = cut_up(t)
        hit, ids = set(), set()
        for n in {len(x) for x in wins}:
            for k in range(len(w) - n + 1):
                if (found := wins.get(tuple(w[k : k + n]))) is not None:
                    hit.update(range(k, k + n))
                    ids |= found
        want.append((len(w), len(hit), len(ids), hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    bench = spark.createDataFrame(items, "item_id long, text string")
    table = make(spark, docs).withColumns({"n_words": F.lit("old"), "hit": F.lit(1), "row": F.lit(2)})
    for size in (64 << 20, 30_000):  # one block, and many
        got = decontam.contamination(table, bench, max_bytes=size).orderBy("doc_id").collect()
        assert [(r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) for r in got] == want
        assert all(r.hit == 1 and r["row"] == 2 for r in got)
    for found in decontam._blocks(bench, 30_000, 13):
        known = decontam.vocabulary(found)
        assert decontam.index(found, known, np.zeros(len(known))).nbytes < 60_000
    assert decontam.contamination(table, bench.where("false")).where("contaminated OR n_hit > 0").isEmpty()


#: Names that operators use inside or return.
CLASHING = ("row", "n", "p", "u", "hit", "ids", "score", "predicted", "size", "source_size", "target", "taken", "range", "digest", "other", "n_words", "n_bytes", "n_tokens", "over_limit", "kept", "spans",
            "base_spans", "masked", "pii", "license", "notices", "known", "host", "path", "rule", "verdict", "mined", "found", "tokens", "explicit", "_w", "_x", "_n", "_lang", "_failed", "component_id", "cls", "sig", "batch", "blob")


@pytest.mark.parametrize("name", ["urls", "pii", "quality", "mixing", "tokens", "toxicity", "neardup", "decontam", "licenses", "substrings"])
def test_clashing_columns_nulls_repeats_and_empty_tables(spark, name):
    rng = random.Random(17)
    prose = lambda n: " ".join(rng.choice(["the", "of", "idiot", "you", "alpha", "beta", "x1", "at", "10.0.0.1"]) for _ in range(n))
    texts = [prose(rng.randint(40, 150)) for _ in range(12)] + [None, "", "one", prose(3000)]
    rows = [(k, t, "en", "s", 1, f"http://h{k}.example.org/{k}") for k, t in enumerate(texts)] + [(None, texts[0], None, None, None, None), (5, texts[5], "en", "s", 1, None), (5, texts[5], "en", "s", 1, None)]
    docs = spark.createDataFrame(rows, SCHEMA + ", url string")
    bench = spark.createDataFrame([(1, texts[1][:200]), (None, None)], "item_id long, text string")
    grammar = toxicity.fit([(f"the day is fine {k}", 0) for k in range(60)] + [(f"you are such an idiot {k}", 1) for k in range(20)])
    act, outputs = {
        "urls": (lambda d: urls.judge(d), ("host", "path", "rule", "verdict", "mined")),
        "pii": (lambda d: pii.find_pii(d, mask=True), ("base_spans", "spans", "masked")),
        "quality": (lambda d: quality.judge(d, d.columns), ("n_words", "word_chars", "n_repeat_words", "base_failed", "kept")),
        "mixing": (lambda d: mixing.mix_sources(d, mixing.word_count(F.col("text"))), ("size", "source_size", "target")),
        "tokens": (lambda d: tokens.count_tokens(d), ("n_bytes", "n_tokens", "over_limit")),
        "toxicity": (lambda d: toxicity.score_toxicity(d, grammar), ("score", "predicted")),
        "neardup": (lambda d: neardup.link(d), ("n_shingles", "component_id", "kept")),
        "decontam": (lambda d: decontam.contamination(d, bench), ("n_words", "n_hit", "n_items", "items_sha256", "contaminated")),
        "licenses": (lambda d: licenses.scan(d), ("digest", "license", "notices")),
        "substrings": (lambda d: substrings.remove_repeats(d, ["doc_id"]), ("n_bytes", "n_removed", "n_spans", "kept_sha256")),
    }[name]
    crowded = docs.withColumns({c: F.lit(f"old {c}") for c in CLASHING})
    show = lambda d: sorted((tuple(r) for r in act(d).select("doc_id", *outputs).collect()), key=repr)
    plain = show(docs)
    assert len(plain) == len(rows) and show(crowded) == plain
    if name not in ("neardup", "substrings"):
        kept = act(crowded).columns
        assert len(kept) == len({c.lower() for c in kept}) and set(docs.columns) <= set(kept)
    assert act(crowded.where("false")).count() == 0
    none = docs.select(*[F.lit(None).cast(t).alias(c) for c, t in docs.dtypes])
    assert len(show(none)) == len(rows)
