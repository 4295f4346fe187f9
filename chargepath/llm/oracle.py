"""DuckDB SQL that gives the rows of three queries by plain means."""

from __future__ import annotations

from chargepath.llm import quality

_LOWER = "translate(coalesce({e}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORDS = "regexp_extract_all({e}, '[^\\x20\\x09-\\x0D]+')"

#: Every window of an item against every window of a document.
DECONTAMINATION = f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all({_LOWER.format(e='text')}, '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM documents),
i AS (SELECT DISTINCT item_id::VARCHAR AS item, regexp_extract_all({_LOWER.format(e='text')}, '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM benchmark),
s AS (SELECT item, w, least(13, len(w)) AS n FROM i WHERE len(w) > 0),
win AS (SELECT DISTINCT item, n, array_to_string(w[k : k + n - 1], ' ') AS t FROM (SELECT *, unnest(range(1, len(w) - n + 2)) AS k FROM s)),
dw AS (SELECT r, k, n, array_to_string(w[k : k + n - 1], ' ') AS t FROM (SELECT r, w, n, unnest(range(1, len(w) - n + 2)) AS k FROM d, (SELECT DISTINCT n FROM win))),
hit AS (SELECT DISTINCT r, k, n, item FROM dw JOIN win USING (n, t)),
words AS (SELECT r, count(DISTINCT p) AS n_hit FROM (SELECT r, unnest(range(k, k + n)) AS p FROM hit) GROUP BY r),
items AS (SELECT r, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS names FROM hit WHERE item IS NOT NULL GROUP BY r)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN words USING (r) LEFT JOIN items USING (r)"""

#: Pairs by common shingles, similarity by set sizes, components by the least label that reaches a document.
NEAR_DUPLICATES = f"""
WITH RECURSIVE d AS (SELECT doc_id, {_WORDS.format(e=_LOWER.format(e='text'))} AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[k : k + least(4, len(w)) - 1], ' ') AS t FROM (SELECT *, unnest(range(1, len(w) - least(4, len(w)) + 2)) AS k FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
pairs AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS shared FROM s a JOIN s b ON a.t = b.t AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (SELECT a, b FROM pairs JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * shared >= 80 * (x.n + y.n - shared)),
c(doc_id, low) USING KEY (doc_id) AS (SELECT doc_id, doc_id FROM d UNION
  SELECT l.b, min(c.low) FROM c JOIN links l ON l.a = c.doc_id JOIN recurring.c o ON o.doc_id = l.b WHERE c.low < o.low GROUP BY l.b)
SELECT c.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, c.low AS component_id, c.low = c.doc_id AS kept FROM c LEFT JOIN n USING (doc_id)"""


#: Every string of 200 bytes, in hexadecimal, against all others; what is left between the runs is put together again.
SUBSTRINGS = """
WITH d AS (SELECT row_number() OVER () AS r, doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
p AS (SELECT r, k, md5(substr(h, (2 * k + 1)::BIGINT, 400)) AS m FROM (SELECT r, h, unnest(range(0, length(h) // 2 - 199)) AS k FROM d)),
hit AS (SELECT r, k FROM p WHERE m IN (SELECT m FROM p GROUP BY m HAVING count(*) > 1)),
isle AS (SELECT r, k, sum(fresh) OVER (PARTITION BY r ORDER BY k) AS g FROM (SELECT r, k, CASE WHEN k <= lag(k) OVER (PARTITION BY r ORDER BY k) + 200 THEN 0 ELSE 1 END AS fresh FROM hit)),
spans AS (SELECT r, min(k) AS lo, max(k) + 200 AS hi FROM isle GROUP BY r, g),
gaps AS (SELECT s.r, lo, hi, substr(h, (2 * coalesce(lag(hi) OVER (PARTITION BY s.r ORDER BY lo), 0) + 1)::BIGINT, (2 * (lo - coalesce(lag(hi) OVER (PARTITION BY s.r ORDER BY lo), 0)))::BIGINT) AS piece FROM spans s JOIN d USING (r)),
sums AS (SELECT r, sum(hi - lo)::BIGINT AS n_removed, count(*) AS n_spans, string_agg(piece, '' ORDER BY lo) AS front, max(hi) AS last FROM gaps GROUP BY r)
SELECT doc_id, (length(h) // 2)::BIGINT AS n_bytes, coalesce(n_removed, 0)::BIGINT AS n_removed, coalesce(n_spans, 0)::BIGINT AS n_spans, sha256(unhex(coalesce(front || substr(h, (2 * last + 1)::BIGINT), h))) AS kept_sha256
FROM d LEFT JOIN sums USING (r)"""


def _quality() -> str:
    common = ", ".join(f"'{w}'" for w in quality.COMMON)
    names = [*quality.CLASSES, "other"]
    kept = ", ".join("length(regexp_replace(t, '{}', '', 'g')) AS c_{}".format(p.replace("'", "''"), c) for c, p in quality.CLASSES.items())
    sums = ", ".join(f"sum(c_{c})::DOUBLE AS q_{c}" for c in names)
    p, q = "(c_{0} / chars::DOUBLE)", "(q_{0} / q_all)"
    term = lambda a, b: f"CASE WHEN {a} > 0 THEN {a} * ln({a} / (({a} + {b}) / 2)) ELSE 0 END + CASE WHEN {b} > 0 THEN {b} * ln({b} / (({a} + {b}) / 2)) ELSE 0 END"
    classes = " + ".join(f"({term(p.format(c), q.format(c))})" for c in names)
    return f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, lang, coalesce(text, '') AS t FROM documents),
w AS (SELECT *, {_WORDS.format(e='t')} AS w, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS lines, length(t) AS chars, {kept} FROM d),
g AS (SELECT r, k, w[k] || ' ' || w[k + 1] || ' ' || w[k + 2] AS g FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS k FROM w)),
rep AS (SELECT r, count(DISTINCT p) AS n FROM (SELECT r, unnest([k, k + 1, k + 2]) AS p FROM (SELECT *, count(*) OVER (PARTITION BY r, g) AS c FROM g) WHERE c > 1) GROUP BY r),
f AS (SELECT w.*, chars - ({' + '.join(f'c_{c}' for c in quality.CLASSES)}) AS c_other, len(w) AS n, coalesce(rep.n, 0) AS rep, len(w) < 50 OR 100 * coalesce(rep.n, 0) > 50 * len(w) AS failed FROM w LEFT JOIN rep USING (r)),
cw AS (SELECT r, lang, failed, x, count(*) AS k FROM (SELECT r, lang, failed, lower(rtrim(unnest(w), '.,;:!?')) AS x FROM f) WHERE x IN ({common}) GROUP BY ALL),
refs AS (SELECT lang, {sums}, sum(chars)::DOUBLE AS q_all FROM f WHERE NOT failed GROUP BY lang),
words AS (SELECT lang, x, sum(k)::DOUBLE AS q FROM cw WHERE NOT failed GROUP BY lang, x),
own AS (SELECT r, lang, sum(k)::DOUBLE AS n FROM cw GROUP BY r, lang),
total AS (SELECT lang, sum(q) AS q FROM words GROUP BY lang),
pq AS (SELECT o.r, coalesce(c.k, 0) / o.n AS p, v.q / t.q AS q FROM own o JOIN words v ON v.lang IS NOT DISTINCT FROM o.lang JOIN total t ON t.lang IS NOT DISTINCT FROM o.lang LEFT JOIN cw c ON c.r = o.r AND c.x = v.x
  UNION ALL SELECT c.r, c.k / o.n, 0 FROM cw c JOIN own o USING (r) JOIN total t ON t.lang IS NOT DISTINCT FROM o.lang LEFT JOIN words v ON v.x = c.x AND v.lang IS NOT DISTINCT FROM c.lang WHERE v.x IS NULL),
by_word AS (SELECT r, sqrt(greatest(sum({term('p', 'q')}), 0) / (2 * ln(2))) AS far FROM pq GROUP BY r),
j AS (SELECT f.*, q_all, t.q AS known, CASE WHEN q_all IS NOT NULL AND chars > 0 THEN sqrt(greatest({classes}, 0) / (2 * ln(2))) ELSE 0 END AS far_class, CASE WHEN q_all IS NOT NULL THEN coalesce(b.far, 1) ELSE 1 END AS far_word
  FROM f LEFT JOIN refs ON refs.lang IS NOT DISTINCT FROM f.lang LEFT JOIN total t ON t.lang IS NOT DISTINCT FROM f.lang LEFT JOIN by_word b ON b.r = f.r)
SELECT doc_id, n::BIGINT AS n_words, (chars - c_space)::BIGINT AS word_chars, c_sign::BIGINT AS n_symbols, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, rep::BIGINT AS n_repeat_words, failed AS base_failed,
  round(far_class, 6) AS class_distance, round(far_word, 6) AS common_distance, NOT failed AND NOT (n >= 80 AND (far_class > 0.25 OR (far_word > 0.8 AND known IS NOT NULL))) AS kept FROM j"""


QUALITY = _quality()
