"""DuckDB SQL that states what the operator queries return, for those that SQL can express."""

from __future__ import annotations

from seedspread.llm.licenses import PHRASES, TEMPLATES
from seedspread.llm.text import LOWER, UPPER

FOLDED = f"translate(coalesce(text, ''), '{UPPER}', '{LOWER}')"
WORDS = rf"regexp_extract_all({FOLDED}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"


def licenses() -> str:
    places = ", ".join(
        f"[i FOR i IN range(len(w)) IF w[i+1:i+{len(p.split(' '))}] = {p.split(' ')}] AS p{k}" for k, p in enumerate(PHRASES))
    labels = ", ".join(f"CASE WHEN len(p{k}) > 0 THEN '{label}' END" for k, label in enumerate(PHRASES.values()))
    every = " || ".join(f"p{k}" for k in range(len(PHRASES)))
    # what meets 80 percent of n words holds one of any n - need + 1 of them
    longest = lambda s: (own := sorted(set(s.split(" ")), key=lambda x: (-len(x), x)))[: len(own) - (4 * len(own) + 4) // 5 + 1]
    some = lambda found: f"{found}::VARCHAR[]"
    templates = ", ".join(f"({n}, '{label}', string_split('{s}', ' '), {some(marks.split())}, string_split('{bars}', ' '), {some(marks.split()[:1] + longest(s))})" for n, (label, s, marks, bars) in enumerate(TEMPLATES))
    return rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, {WORDS} AS w FROM documents),
b AS (SELECT *, {places} FROM d),
t(id, label, sentence, marks, bars, anchors) AS (VALUES {templates}),
spots AS (SELECT r, w, unnest(range(1, len(w) + 1)) AS i FROM d),
blocks AS (SELECT r, id, label, sentence, list_distinct(sentence) AS words, marks, bars, list_distinct(w[greatest(1, i - len(sentence)):i + len(sentence)]) AS s FROM spots JOIN t ON list_contains(anchors, w[i])),
hits AS (SELECT r, id, label, len(list_intersect(words, s)) / len(words) AS c FROM blocks
  WHERE list_has_all(s, marks) AND NOT list_has_any(s, bars) AND 100 * len(list_intersect(words, s)) >= 80 * len(words)),
more AS (SELECT r, list(DISTINCT label) AS more, max(c) AS best, count(DISTINCT id) AS n_templates FROM hits GROUP BY r)
SELECT b.doc_id, len(w)::BIGINT AS n_words, len({every})::BIGINT AS n_base, list_min({every})::BIGINT AS first_word, list_max({every})::BIGINT AS last_word,
  coalesce(array_to_string(list_sort(list_distinct([{labels}])), ','), '') AS base_labels,
  coalesce(array_to_string(list_sort(list_distinct([{labels}] || coalesce(more, []))), ','), '') AS labels,
  CASE WHEN len({every}) > 0 THEN 1.0 ELSE coalesce(best, 0.0) END::DOUBLE AS score, coalesce(n_templates, 0)::BIGINT AS n_templates
FROM b LEFT JOIN more USING (r)"""


DECONTAMINATE = rf"""
WITH i AS (SELECT item_id::VARCHAR AS item, {WORDS} AS w FROM benchmark),
win AS (SELECT DISTINCT item, w[k:k + 9] AS p FROM (SELECT item, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS k FROM i WHERE len(w) > 0)),
d AS (SELECT row_number() OVER () AS r, doc_id, {WORDS} AS w FROM documents),
spots AS (SELECT r, k, n, w[k:k + n - 1] AS p FROM (SELECT r, w, unnest(range(1, len(w) + 1)) AS k FROM d), (SELECT DISTINCT len(p) AS n FROM win) WHERE k + n - 1 <= len(w)),
hit AS (SELECT r, k, n, item FROM spots JOIN win USING (p)),
per AS (SELECT r, count(DISTINCT pos) AS n_hit FROM (SELECT r, unnest(range(k, k + n)) AS pos FROM hit) GROUP BY r),
its AS (SELECT r, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS items FROM hit GROUP BY r)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN per USING (r) LEFT JOIN its USING (r)"""


MIX = r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size, md5('0:' || coalesce(doc_id::VARCHAR, '')) AS h FROM documents),
s0 AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
s1 AS (SELECT *, (row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 + 1 AS weight, 3 * source_size AS cap FROM s0),
s2 AS (SELECT *, (SELECT sum(source_size) FROM s0)::DOUBLE AS budget, coalesce(sum(cap) OVER b, 0)::DOUBLE AS cap_before, ((SELECT sum(weight) FROM s1) - coalesce(sum(weight) OVER b, 0))::DOUBLE AS left_weight
  FROM s1 WINDOW b AS (ORDER BY cap::DOUBLE / weight, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
s3 AS (SELECT *, cap::DOUBLE / weight < (budget - cap_before) / left_weight AS clamped FROM s2),
s4 AS (SELECT source, source_size, CASE WHEN clamped THEN cap::DOUBLE ELSE weight * (((budget) - (SELECT min(cap_before) FROM s3 WHERE NOT clamped)) / (SELECT max(left_weight) FROM s3 WHERE NOT clamped)) END AS target FROM s3),
s5 AS (SELECT *, CASE WHEN source_size > 0 THEN target / source_size ELSE 0.0 END AS rate FROM s4),
o AS (SELECT d.*, source_size, target, floor(rate) AS whole, (rate - floor(rate)) * source_size AS wanted,
  sum(size) OVER (PARTITION BY d.source ORDER BY h, size ROWS UNBOUNDED PRECEDING) - size / 2 AS middle
  FROM d JOIN s5 ON d.source IS NOT DISTINCT FROM s5.source)
SELECT doc_id, size, source_size, target, (size * (whole + CASE WHEN middle <= wanted THEN 1 ELSE 0 END))::BIGINT AS taken, source FROM o"""


NEAR_DUPLICATES = rf"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all({FOLDED}, '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT doc_id, list_distinct([array_to_string(w[i:i + 4], ' ') FOR i IN range(1, greatest(len(w) - 4, 1) + 1)]) AS s FROM d WHERE len(w) > 0),
n AS (SELECT doc_id, len(s)::BIGINT AS n FROM s),
e AS (SELECT doc_id, unnest(s) AS x FROM s),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM e a JOIN e b ON a.x = b.x AND a.doc_id <> b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n na ON a = na.doc_id JOIN n nb ON b = nb.doc_id WHERE 100 * k >= 75 * (na.n + nb.n - k)),
r(v, c) AS (SELECT doc_id, doc_id FROM d UNION SELECT l.b, r.c FROM r JOIN l ON l.a = r.v)
SELECT d.doc_id, coalesce(n, 0)::BIGINT AS n_shingles, min(c) AS component_id, d.doc_id = min(c) AS kept
FROM d LEFT JOIN n USING (doc_id) JOIN r ON r.v = d.doc_id GROUP BY d.doc_id, n"""


ARCHIVE = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
q AS (SELECT page_id, strlen(h)::BIGINT AS payload_bytes, sha256(h) AS payload_digest, min(page_id) OVER (PARTITION BY h) AS first FROM p)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN payload_bytes >= 100 AND first < page_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN payload_bytes >= 100 AND first < page_id THEN first END AS refers_to FROM q"""


VECTORS = """
WITH RECURSIVE v AS (SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings),
g AS (SELECT * FROM v WHERE vec_id IS NOT NULL AND label IS NOT NULL AND e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND list_dot_product(e, e) > 0),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM g a JOIN g b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
  WHERE list_dot_product(a.e, b.e) / sqrt(list_dot_product(a.e, a.e)) / sqrt(list_dot_product(b.e, b.e)) >= 0.98),
r(v, c) AS (SELECT vec_id, vec_id FROM v UNION SELECT l.b, r.c FROM r JOIN l ON l.a = r.v),
n AS (SELECT a, count(*) AS n FROM l GROUP BY a), c AS (SELECT v, min(c) AS c FROM r GROUP BY v)
SELECT vec_id, coalesce(n, 0)::BIGINT AS n_links, c AS component_id, vec_id = c AS kept FROM v JOIN c ON v.vec_id = c.v LEFT JOIN n ON n.a = v.vec_id"""
