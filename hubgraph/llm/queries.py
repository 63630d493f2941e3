"""Queries over the ten operators and the pipeline, with the SQL that can express them."""

from __future__ import annotations

from hubgraph.llm import chat, ctw, decontam, knn, langid, packing, secrets, simhash, suffix, toxicity
from hubgraph.llm.common import table


def ranks_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def op1_suffix_array_dedup(spark, sf_dir):
    return suffix.remove_repeats(table(spark, sf_dir, "documents")).drop("kept")


def op2_language_id(spark, sf_dir):
    return langid.language_report(table(spark, sf_dir, "documents"))


def op3_secret_scan(spark, sf_dir):
    return secrets.secret_report(table(spark, sf_dir, "documents"))


def op4_chat_format(spark, sf_dir):
    return chat.chat_report(table(spark, sf_dir, "conversations"))


def op5_simhash_near_dedup(spark, sf_dir):
    return simhash.near_duplicate_report(table(spark, sf_dir, "documents"))


def op6_decontamination(spark, sf_dir):
    return decontam.contamination_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op7_packing(spark, sf_dir):
    return packing.pack(table(spark, sf_dir, "documents"), ranks_path())


def op8_top_k(spark, sf_dir):
    return knn.top_k(table(spark, sf_dir, "embeddings"))


def op9_lm_score(spark, sf_dir):
    return ctw.scoring_report(table(spark, sf_dir, "documents"))


def op10_toxicity(spark, sf_dir):
    return toxicity.toxicity_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_suffix_array_dedup, op2_language_id, op3_secret_scan, op4_chat_format, op5_simhash_near_dedup, op6_decontamination, op7_packing, op8_top_k, op9_lm_score, op10_toxicity, pipeline)}

_CONTROL = "replace(replace(replace({}, '~', '~0'), '<', '~1'), '[', '~2')"
ORACLES = {
    "op4_chat_format": f"""
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]'
  UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
sized AS (
  SELECT *, length({_CONTROL.format("text")}) AS body, 8 + length(replace({_CONTROL.format("role")}, chr(10), '~3')) + 8 AS head FROM turns),
placed AS (
  SELECT *, sum(head + body + 7) OVER (PARTITION BY conv_id ORDER BY turn, role, text ROWS UNBOUNDED PRECEDING) - 7 AS stop FROM sized)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(head + body + 7)::BIGINT AS formatted_chars,
  count(*) FILTER (role = 'assistant') AS n_examples,
  coalesce(sum(stop) FILTER (role = 'assistant'), 0)::BIGINT AS expanded_chars
FROM placed GROUP BY conv_id""",
    "op8_top_k": """
WITH ready AS (
  SELECT vec_id, row_number() OVER () AS rid, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT q.rid, q.vec_id AS query_id, c.vec_id AS vec_id, list_inner_product(q.v, c.v)::BIGINT AS score
  FROM ready q JOIN ready c ON q.vec_id % 20 = 0 AND c.rid <> q.rid),
ranked AS (
  SELECT query_id, (row_number() OVER (PARTITION BY rid ORDER BY score DESC, vec_id))::INTEGER AS rank, vec_id, score FROM scored)
SELECT * FROM ranked WHERE rank <= 20""",
}
