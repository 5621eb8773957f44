"""Queries of the operators in this subpackage and, where SQL can express them, their DuckDB SQL."""

from __future__ import annotations

from pathq.llm.html import op5_html_text
from pathq.llm.language import op8_language_id
from pathq.llm.licenses import BASE, LICENSES, scan
from pathq.llm.mixing import op4_mixing
from pathq.llm.near_dedup import op10_near_dedup
from pathq.llm.packing import op1_packing
from pathq.llm.search import op2_nearest
from pathq.llm.tokens import op6_token_ids
from pathq.llm.vectors import op9_near_vectors
from pathq.llm.warc import op7_warc


def op3_licenses(spark, sf_dir: str):
    return scan(spark, spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


QUERIES = {
    "op1_packing": op1_packing,
    "op2_nearest": op2_nearest,
    "op3_licenses": op3_licenses,
    "op4_mixing": op4_mixing,
    "op5_html_text": op5_html_text,
    "op6_token_ids": op6_token_ids,
    "op7_warc": op7_warc,
    "op8_language_id": op8_language_id,
    "op9_near_vectors": op9_near_vectors,
    "op10_near_dedup": op10_near_dedup,
}

_TEMPLATES = ", ".join(f"({i}, '{t.label}', {str(t.base).lower()}, '{t.text}')" for i, t in enumerate(BASE + LICENSES))

#: Components over ``link(a, b)`` and ``node(id)``, by plain recursion: for tables whose groups are small.
_COMPONENTS = """both_ways AS (SELECT a, b FROM link UNION SELECT b, a FROM link),
reach(a, b) AS (SELECT id, id FROM node UNION SELECT reach.a, both_ways.b FROM reach JOIN both_ways ON reach.b = both_ways.a),
least AS (SELECT a AS id, min(b) AS component FROM reach GROUP BY a)"""

ORACLES = {
    # all pairs that share a shingle, whole texts, no hashing
    "op10_near_dedup": f"""
WITH RECURSIVE worded AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
runs AS (
  SELECT doc_id, unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i, w FROM worded WHERE len(w) > 0),
grams AS (SELECT DISTINCT doc_id AS id, array_to_string(w[i:i + 3], ' ') AS g FROM runs),
size AS (SELECT id, count(*) AS n FROM grams GROUP BY id),
shared AS (SELECT x.id AS a, y.id AS b, count(*) AS n FROM grams x JOIN grams y ON x.g = y.g AND x.id < y.id GROUP BY ALL),
link AS (SELECT a, b FROM shared JOIN size p ON p.id = a JOIN size q ON q.id = b WHERE 100 * shared.n >= 80 * (p.n + q.n - shared.n)),
node AS (SELECT DISTINCT doc_id AS id FROM documents), {_COMPONENTS}
SELECT doc_id, coalesce(n, 0)::BIGINT AS n_shingles, component AS component_id, doc_id = component AS kept
FROM documents JOIN least ON least.id = doc_id LEFT JOIN size ON size.id = doc_id""",
    # all pairs of vectors
    "op9_near_vectors": f"""
WITH RECURSIVE good AS (
  SELECT vec_id AS id, embedding::DOUBLE[] AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
link AS (SELECT x.id AS a, y.id AS b FROM good x JOIN good y ON x.id < y.id AND len(x.v) = len(y.v) WHERE list_cosine_similarity(x.v, y.v) >= 0.9),
node AS (SELECT DISTINCT vec_id AS id FROM embeddings), {_COMPONENTS},
n AS (SELECT id, count(*) AS n FROM (SELECT a AS id FROM link UNION ALL SELECT b FROM link) GROUP BY id)
SELECT vec_id, coalesce(n, 0)::BIGINT AS n_links, component AS component_id, vec_id = component AS kept
FROM embeddings JOIN least ON least.id = vec_id LEFT JOIN n ON n.id = vec_id""",
    "op7_warc": """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS body FROM pages),
d AS (SELECT page_id, octet_length(body) AS n, sha1(body) AS h FROM p),
g AS (SELECT h, max(page_id) AS top FROM d WHERE n >= 1000 GROUP BY h)
SELECT d.page_id, n::BIGINT AS payload_bytes, d.h AS payload_digest,
       CASE WHEN top IS NULL OR top = d.page_id THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN top <> d.page_id THEN top END AS refers_to
FROM d LEFT JOIN g ON d.h = g.h AND n >= 1000""",
    "op3_licenses": f"""
WITH worded AS (
  SELECT doc_id, row_number() OVER () AS rid,
         regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                            '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w
  FROM documents),
templates(tid, label, base, body) AS (VALUES {_TEMPLATES}),
tw AS (SELECT tid, label, base, string_split(body, ' ') AS w FROM templates),
tg AS (SELECT tid, label, base, len(w) - 1 AS n_grams, unnest(range(1, len(w))) AS i, w FROM tw),
tpos AS (SELECT tid, label, base, n_grams, i - 1 AS t, w[i] AS w1, w[i + 1] AS w2 FROM tg),
dpos AS (SELECT rid, unnest(range(1, len(w))) AS i, w FROM worded),
dgram AS (SELECT rid, i - 1 AS p, w[i] AS w1, w[i + 1] AS w2 FROM dpos),
hits AS (SELECT rid, tid, label, base, n_grams, p, t, p - t AS diagonal FROM dgram JOIN tpos USING (w1, w2)),
diags AS (
  SELECT rid, tid, label, base, n_grams, diagonal, count(*) AS n, min(p) AS first, max(p) AS last, list(DISTINCT t) AS ts
  FROM hits GROUP BY ALL),
places AS (
  SELECT rid, label, true AS base, first AS start, 1.0::DOUBLE AS cover FROM diags WHERE base AND n = n_grams),
opened AS (
  SELECT *, CASE WHEN coalesce(diagonal - lag(diagonal) OVER o > 2 OR first > lag(last) OVER o + n_grams, true) THEN 1 ELSE 0 END AS opens
  FROM diags WHERE NOT base WINDOW o AS (PARTITION BY rid, tid ORDER BY diagonal, first)),
numbered AS (SELECT *, sum(opens) OVER (PARTITION BY rid, tid ORDER BY diagonal, first) AS span FROM opened),
merged AS (
  SELECT rid, label, false AS base, min(first) AS start,
         len(list_distinct(flatten(list(ts))))::DOUBLE / n_grams AS cover
  FROM numbered GROUP BY rid, tid, label, n_grams, span),
found AS (SELECT * FROM places UNION ALL SELECT * FROM merged WHERE cover >= 0.8),
per_doc AS (
  SELECT rid, count(*) FILTER (base) AS n_base, min(start) FILTER (base) AS first_word, max(start) FILTER (base) AS last_word,
         string_agg(DISTINCT label, ',' ORDER BY label) FILTER (base) AS base_labels,
         string_agg(DISTINCT label, ',' ORDER BY label) AS labels, count(*) AS n_spans,
         max(CASE WHEN base THEN 0.0 ELSE cover END) AS best
  FROM found GROUP BY rid)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_base, 0)::BIGINT AS n_base, first_word::BIGINT AS first_word,
       last_word::BIGINT AS last_word, coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels,
       least(1.0, greatest(coalesce(best, 0.0), coalesce(n_base, 0) * 0.5))::DOUBLE AS score,
       coalesce(n_spans, 0)::BIGINT AS n_spans
FROM worded LEFT JOIN per_doc USING (rid)""",
}
