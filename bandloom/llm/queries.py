"""The registered queries of the training-data operators, and their DuckDB twins where SQL can say the same."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import functions as F

from bandloom.llm import bpe, chat, decontaminate, langid, maglev, maxscore, quality, simhash, toxicity, warc
from bandloom.runtime import table


def op1_maxscore_topk(spark, sf_dir):
    return maxscore.top_k(table(spark, sf_dir, "embeddings"))


def op2_simhash_near_dedup(spark, sf_dir):
    return simhash.simhash_dedup(table(spark, sf_dir, "documents"))


def op3_spaced_seed_decontamination(spark, sf_dir):
    return decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_chat_format(spark, sf_dir):
    planted = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"))
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    return chat.chat_digest(chat.format_chat(rows.unionByName(planted)))


def op5_toxicity(spark, sf_dir):
    return toxicity.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_bpe(spark, sf_dir):
    return bpe.bpe_encode(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op7_warc(spark, sf_dir):
    return warc.warc_round_trip(table(spark, sf_dir, "pages"))


def op8_maglev_sharding(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id")
    return maglev.place(docs, F.col("doc_id")).select("doc_id", "slot", "shard")


def op9_quality(spark, sf_dir):
    return quality.quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_language_id(spark, sf_dir):
    return langid.language_id(table(spark, sf_dir, "documents"))


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    f.__name__: f
    for f in (
        op1_maxscore_topk, op2_simhash_near_dedup, op3_spaced_seed_decontamination, op4_chat_format, op5_toxicity, op6_bpe,
        op7_warc, op8_maglev_sharding, op9_quality, op10_language_id, pipeline,
    )
}

OP1_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NOT NULL AND isfinite(x))) = len(embedding)
), s AS (
  SELECT q.vec_id AS query_id, q.v AS query, d.vec_id, CAST(coalesce(list_sum(list_transform(list_zip(q.v, d.v), lambda p: p[1] * p[2])), 0) AS BIGINT) AS score
  FROM (SELECT DISTINCT * FROM v WHERE vec_id % 50 = 0) q JOIN v d ON q.vec_id <> d.vec_id AND len(q.v) = len(d.v)
), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id, query ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""

OP4_SQL = """
WITH c AS (
  SELECT conv_id, turn, role, text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'
), t AS (
  SELECT conv_id, turn, role, coalesce(text, '') AS text,
    row_number() OVER w AS i, role IS NOT DISTINCT FROM lag(role) OVER w AS same
  FROM c WINDOW w AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, coalesce(text, ''))
), e AS (
  SELECT *, length(text) + length(regexp_replace(text, '[^\\\\<\\[\\]]', '', 'g')) AS text_chars,
    coalesce(length(role) + length(regexp_replace(role, '[^\\\\<\\[\\]]', '', 'g')), 2) AS role_chars
  FROM t
)
SELECT conv_id, CAST(count(*) AS BIGINT) AS n_turns,
  sha256(string_agg(coalesce(role, '') || chr(10) || text || chr(10), '' ORDER BY i)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY i) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(text_chars + CASE WHEN same AND i > 1 THEN 5 ELSE role_chars + 9 END) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""

OP7_SQL = """
WITH p AS (
  SELECT page_id, sha1(coalesce(html, '')) AS h, CAST(octet_length(encode(coalesce(html, ''))) AS BIGINT) AS payload_bytes FROM pages
), g AS (SELECT h, max(page_id) AS top FROM p GROUP BY h),
d AS (
  SELECT h, list_reduce(list_prepend('', list_transform(range(32), lambda k: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + CAST(
    (CAST('0x' || substr(h, 1 + 10 * CAST(floor(k / 8) AS BIGINT), 10) AS BIGINT) >> CAST(35 - 5 * (k % 8) AS BIGINT)) & 31 AS BIGINT), 1))), lambda a, b: a || b) AS payload_digest
  FROM g
)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = top OR top IS NULL THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id = top THEN NULL ELSE top END AS refers_to
FROM p JOIN g USING (h) JOIN d USING (h)
"""

ORACLES = {"op1_maxscore_topk": OP1_SQL, "op4_chat_format": OP4_SQL, "op7_warc": OP7_SQL}
