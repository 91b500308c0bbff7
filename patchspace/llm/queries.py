"""The registered queries of this subpackage: name -> (spark, sf_dir) -> DataFrame."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from patchspace.llm import annuli, chosen_path, katz, media, mixing, packing, quality, template, token_shards, warc


OP4 = """
WITH v AS (
  SELECT vec_id, [floor(64 * x::DOUBLE)::BIGINT for x in embedding] AS e FROM embeddings
  WHERE embedding IS NOT NULL
    AND len([x for x in embedding if x IS NOT NULL AND isfinite(x)]) = len(embedding)),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id, list_inner_product(q.e, c.e)::BIGINT AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0),
r AS (
  SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS k, vec_id, score FROM s)
SELECT query_id, k::INTEGER AS rank, vec_id, score FROM r WHERE k <= 20
"""

OP3 = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
d AS (SELECT page_id, octet_length(encode(html))::BIGINT AS payload_bytes, sha256(html) AS payload_digest FROM p),
f AS (SELECT *, CASE WHEN payload_bytes >= 100 THEN min(page_id) OVER (PARTITION BY payload_digest) END AS first_id FROM d)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN page_id <> first_id THEN first_id END AS refers_to FROM f
"""

# shingles as sets of (word, word, word); links from counts of common shingles; components by recursion
OP9 = """
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS words FROM documents),
s AS (SELECT doc_id, CASE WHEN len(words) = 0 THEN [] WHEN len(words) < 3 THEN [array_to_string(words, ' ')]
    ELSE list_distinct([words[i] || ' ' || words[i + 1] || ' ' || words[i + 2] for i in range(1, len(words) - 1)]) END AS shingles FROM w),
n AS (SELECT doc_id, len(shingles)::BIGINT AS n FROM s),
u AS (SELECT doc_id, unnest(shingles) AS shingle FROM s),
links AS (SELECT a.doc_id AS a, b.doc_id AS b FROM u a JOIN u b ON a.shingle = b.shingle AND a.doc_id < b.doc_id
  JOIN n x ON x.doc_id = a.doc_id JOIN n y ON y.doc_id = b.doc_id
  GROUP BY a.doc_id, b.doc_id, x.n, y.n HAVING 100 * count(*) >= 85 * (x.n + y.n - count(*))),
both_ways AS (SELECT a, b FROM links UNION SELECT b, a FROM links),
reach(id, node) AS (SELECT doc_id, doc_id FROM n UNION SELECT r.id, l.b FROM reach r JOIN both_ways l ON l.a = r.node)
SELECT n.doc_id, n.n AS n_shingles, min(r.node)::BIGINT AS component_id, n.doc_id = min(r.node) AS kept FROM n JOIN reach r ON r.id = n.doc_id GROUP BY n.doc_id, n.n
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_source_mix": mixing.op1,
        "op2_media_sequences": media.op2,
        "op3_warc": warc.op3,
        "op4_pivot_annuli": annuli.op4,
        "op5_template_text": template.op5,
        "op6_quality": quality.op6,
        "op7_katz": katz.op7,
        "op8_packing": packing.op8,
        "op9_chosen_path": chosen_path.op9,
        "op10_token_shards": token_shards.op10,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op3_warc": OP3,
        "op4_pivot_annuli": OP4,
        "op9_chosen_path": OP9,
    }
