"""Queries of the text operators over whole tables, with SQL where it can express them."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subvote.llm import chat_format, exact_dedup, language_id, mixing, ngram_join, packing, quality_rules, substring_dedup, token_counts, token_files
from subvote.llm._store import documents

HELD_OUT = "crc32(cast(doc_id as string)) % 5 = 0"


def op1_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.join(documents(spark, sf_dir), k=3, percent=90)


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.groups(documents(spark, sf_dir)).drop("n_code_points", "n_tied")


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    field = quality_rules.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality_rules.judge(docs, field)


def op4_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = F.lit("</s>[INST] ok [/INST]").alias("text")
    rows = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    extra = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), said)
    chats = chat_format.format_chats(rows.unionByName(extra).withColumn("parts", chat_format.text_part(F.col("text"))))
    turns = chat_format.read_turns(F.col("formatted"))
    digest = lambda c: F.sha2(F.encode(c, "utf-8"), 256)
    chats = chats.withColumn("_loss", chat_format.read_loss(F.col("formatted"), F.col("loss_spans"))).withColumn("_turns", turns)
    said_all = F.array_join(F.transform("_turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return chats.select(
        "conv_id", F.size("_turns").cast("long").alias("n_turns"), digest(said_all).alias("turns_sha256"),
        F.length("_loss").cast("long").alias("loss_chars"), digest(F.col("_loss")).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"), end_id=2, capacity=4096)


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken")


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    profiles = language_id.fit(docs, f"not ({HELD_OUT})")
    out = language_id.predict(docs, profiles)
    return out.select("doc_id", F.expr(f"coalesce({HELD_OUT}, false)").alias("held_out"), "lang_pred", "score")


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    manifest = token_files.write_token_files(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"), end_id=0)
    return token_files.read_token_files(manifest, manifest._subvote_folder)


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"), limit=2048)


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.remove_repeats(documents(spark, sf_dir), size=20).drop("kept_text")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    listed = (
        op1_ngram_jaccard_join, op2_exact_dedup, op3_quality_rules, op4_chat_format, op5_packing,
        op6_mixing, op7_language_id, op8_token_files, op9_token_counts, op10_substring_dedup,
    )
    return {f.__name__: f for f in listed}


_OP2 = r"""
WITH t AS (
  SELECT doc_id, length(coalesce(text, '')) AS n_chars, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS norm
  FROM documents
), g AS (
  SELECT norm, count(*) AS group_size, min({'c': -n_chars, 'i': doc_id}) AS best FROM t GROUP BY norm
)
SELECT t.doc_id, best.i AS keep_id, group_size, (t.doc_id = best.i AND -t.n_chars = best.c) AS kept, sha256(norm) AS text_sha256
FROM t JOIN g USING (norm)
"""

_OP4 = r"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]'
  UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), e AS (
  SELECT *, length(replace(text, '\', '\\')) + (length(text) - length(replace(text, '<s>', ''))) / 3 + (length(text) - length(replace(text, '</s>', ''))) / 4
    + (length(text) - length(replace(text, '[INST]', ''))) / 6 + (length(text) - length(replace(text, '[/INST]', ''))) / 7
    + (length(text) - length(replace(text, '<|', ''))) / 2 AS n
  FROM c
)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(n + length(role) + 23)::BIGINT AS formatted_chars
FROM e GROUP BY conv_id
"""

_OP6 = r"""
WITH t AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size, md5(coalesce(doc_id::VARCHAR, '')) AS k FROM documents
), s AS (
  SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS i FROM t GROUP BY source
), w AS (
  SELECT *, ([3.0, 1.0, 2.0])[((i - 1) % 3) + 1]::DOUBLE AS w, source_size * 2.0::DOUBLE AS cap, (sum(source_size) OVER () * 1.5::DOUBLE)::DOUBLE AS budget FROM s
), f AS (
  SELECT *, (budget - coalesce(sum(cap) OVER o, 0)) / (sum(w) OVER () - coalesce(sum(w) OVER o, 0)) AS level
  FROM w WINDOW o AS (ORDER BY cap / w, i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
), l AS (
  SELECT arg_min(level, (cap / w, i)) AS level FROM f WHERE level <= cap / w
), g AS (
  SELECT source, source_size, least(cap, coalesce(w * l.level, cap)) AS target FROM f LEFT JOIN l ON true
), r AS (
  SELECT t.*, g.source_size, g.target, floor(target)::BIGINT AS goal,
    coalesce(sum(size) OVER (PARTITION BY t.source ORDER BY k, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before
  FROM t JOIN g ON t.source IS NOT DISTINCT FROM g.source
), e AS (
  SELECT *, CASE WHEN source_size > 0 THEN goal // source_size ELSE 0 END AS epochs FROM r
)
SELECT doc_id, size::BIGINT AS size, source_size, target, (epochs * size + greatest(0, least(size, goal - epochs * source_size - before)))::BIGINT AS taken FROM e
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_exact_dedup": _OP2, "op4_chat_format": _OP4, "op6_mixing": _OP6}
