"""Queries of the corpus operators and the SQL that gives the same rows."""

from __future__ import annotations

from . import licences, mixing, nearcopies, pieces, quality, secrets, sharding, substrings, toxicity, vectors

QUERIES = {
    "op1_source_mix": mixing.op1,
    "op2_repeated_passages": substrings.op2,
    "op3_toxicity": toxicity.op3,
    "op4_pieces": pieces.op4,
    "op5_licences": licences.op5,
    "op6_quality_rules": quality.op6,
    "op7_vector_links": vectors.op7,
    "op8_shards": sharding.op8,
    "op9_secrets": secrets.op9,
    "op10_near_copies": nearcopies.op10,
}


def queries() -> dict:
    return dict(QUERIES)


PASSAGES = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
h AS (SELECT doc_id, i, md5(array_to_string(w[i : i + 34], ' ')) AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 33)) AS i FROM d WHERE len(w) >= 35)),
g AS (SELECT DISTINCT doc_id, unnest(range(i, i + 35)) AS j FROM h WHERE k IN (SELECT k FROM h GROUP BY k HAVING count(*) > 1)),
x AS (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS j FROM d),
y AS (SELECT x.doc_id, count(g.j) AS n_removed, string_agg(word, ' ' ORDER BY x.j) FILTER (g.j IS NULL) AS kept FROM x LEFT JOIN g ON g.doc_id = x.doc_id AND g.j = x.j GROUP BY x.doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN y ON y.doc_id = d.doc_id
"""
LINKS = """
WITH RECURSIVE v AS (SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL),
l AS MATERIALIZED (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.e, b.e) >= 0.93),
r(n, c) AS (SELECT vec_id, vec_id FROM embeddings UNION SELECT l.b, r.c FROM r JOIN l ON l.a = r.n AND r.c < l.b),
k AS (SELECT n, min(c) AS c FROM r GROUP BY n)
SELECT vec_id, (SELECT count(*) FROM l WHERE l.a = vec_id) AS n_links, c AS component_id, vec_id = c AS kept FROM embeddings JOIN k ON n = vec_id
"""

MIX = r"""
WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
  (CAST(CAST('0x' || substr(md5('mix|' || coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 12) AS BIGINT) AS DOUBLE) + 0.5) / 281474976710656.0 AS u FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS r FROM d GROUP BY source),
w AS (SELECT source, source_size, [3, 1, 2][CAST(r % 3 AS BIGINT) + 1] AS weight FROM s),
l AS (SELECT *, coalesce(sum(source_size) OVER before, 0) AS full_before, sum(weight) OVER after AS weight_after, sum(source_size) OVER () AS everything, row_number() OVER room AS place FROM w
  WINDOW room AS (ORDER BY source_size / weight, weight, source NULLS LAST), before AS (ORDER BY source_size / weight, weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING),
  after AS (ORDER BY source_size / weight, weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)),
v AS (SELECT *, (1.5::DOUBLE * everything::DOUBLE - 2.0::DOUBLE * full_before::DOUBLE) / weight_after::DOUBLE AS level FROM l),
f AS (SELECT min(place) AS place FROM v WHERE level * weight <= 2.0::DOUBLE * source_size),
t AS (SELECT v.source, v.source_size, CASE WHEN v.place >= f.place THEN g.level * v.weight ELSE 2.0::DOUBLE * v.source_size END AS target FROM v, f LEFT JOIN v g ON g.place = f.place),
p AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END AS whole FROM t),
x AS (SELECT *, target - whole * source_size AS rest FROM p),
b AS (SELECT d.source, CAST(floor(4.0::DOUBLE * sqrt(size::DOUBLE)) AS BIGINT) AS wb, sum(size) AS words, sum(size * size)::DOUBLE AS mass, max(size) AS top, any_value(rest) AS rest FROM d JOIN x ON d.source IS NOT DISTINCT FROM x.source GROUP BY 1, 2),
c AS (SELECT source, wb, top, greatest(0.0::DOUBLE, (rest - coalesce(sum(words) OVER (PARTITION BY source ORDER BY wb DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::DOUBLE)
  / nullif(sum(mass) OVER (PARTITION BY source ORDER BY wb DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING), 0)) AS c FROM b),
m AS (SELECT source, max(wb) AS from_bin, arg_max(c, wb) AS c FROM c WHERE c * top < 1.0 GROUP BY source),
z AS (SELECT d.*, x.source_size, x.target, x.whole, x.rest, least(1.0::DOUBLE - 1e-9::DOUBLE, greatest(1e-9::DOUBLE, CASE WHEN floor(4.0::DOUBLE * sqrt(size::DOUBLE)) > m.from_bin THEN 1.0::DOUBLE ELSE coalesce(m.c * size::DOUBLE, 0.0::DOUBLE) END)) AS chance
  FROM d JOIN x ON d.source IS NOT DISTINCT FROM x.source LEFT JOIN m ON d.source IS NOT DISTINCT FROM m.source),
o AS (SELECT *, u / (1.0::DOUBLE - u) * ((1.0::DOUBLE - chance) / chance) AS odds FROM z),
q AS (SELECT *, row_number() OVER k AS n, sum(size) OVER (k ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS sofar FROM (SELECT *, odds / (1.0::DOUBLE + odds) AS q FROM o) WINDOW k AS (PARTITION BY source ORDER BY q, doc_id NULLS FIRST, size)),
e AS (SELECT source, min(n) AS cut, min(rest - (sofar - size)) FILTER (n = first_out) AS gap FROM (SELECT *, min(n) FILTER (sofar > rest) OVER (PARTITION BY source) AS first_out FROM q) WHERE sofar > rest GROUP BY source),
y AS (SELECT q.source, arg_min(n, (abs(gap - size), q.q, n)) AS closing FROM q JOIN e ON q.source IS NOT DISTINCT FROM e.source WHERE n >= cut AND size > 0 AND abs(gap - size) < gap GROUP BY q.source)
SELECT doc_id, size, source_size, target, CAST(size * (whole + CASE WHEN rest > 0 AND (e.cut IS NULL OR n < e.cut OR n = y.closing) THEN 1 ELSE 0 END) AS BIGINT) AS taken
FROM q LEFT JOIN e ON q.source IS NOT DISTINCT FROM e.source LEFT JOIN y ON q.source IS NOT DISTINCT FROM y.source
"""


def oracle_sql() -> dict[str, str]:
    """SQL for those that it can express in a reasonable time; README says how each of the others is tested."""
    return {"op1_source_mix": MIX, "op2_repeated_passages": PASSAGES, "op7_vector_links": LINKS}
