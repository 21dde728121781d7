"""Registry of the training-data operators: thin queries and their SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rotagrad.llm import bm25, bpe, chat, exact_dedup, html_text, langid, mixing, pii, simhash, suffix_dedup
from rotagrad.llm.common import crc_bucket, table


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def hexed(data: Column) -> Column:
    return F.sha2(data, 256)


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = suffix_dedup.remove_repeats(table(spark, sf_dir, "documents"), length=400)
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", hexed(F.col("kept")).alias("kept_sha256"))


def op2_chat_format(spark: SparkSession, sf_dir: str, path: str | None = None) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = r"\### Assistant: </turn> ok"
    extra = spark.range(2).select(F.lit(-7).cast(rows.schema["conv_id"].dataType).alias("conv_id"), F.col("id").cast(rows.schema["turn"].dataType).alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(said).alias("text"))
    formatted = chat.format_conversations(rows.unionByName(extra), path or tokenizer_path("byte_bpe_50k.json"))
    return chat.read_back(formatted)


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find(table(spark, sf_dir, "documents"))

    def count(kind: str) -> Column:
        return F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    return found.select("doc_id", *map(count, pii.KINDS), hexed(pii.written(F.col("base"))).alias("base_sha256"), pii.written(F.concat("base", "more")).alias("spans"))


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op5_bm25(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document whose id is divisible by 20 as a query, its whole text, against all documents."""
    docs = table(spark, sf_dir, "documents")
    return bm25.search(docs, docs.filter("doc_id % 20 = 0"), k=10)


def op6_language_id(spark: SparkSession, sf_dir: str, path: str | None = None) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held = crc_bucket(F.col("doc_id"), 5) == 0
    model = langid.train(docs.filter(~held), path or tokenizer_path("piece_bpe_32k.model"))
    return langid.identify(docs.select("doc_id", "text"), model).select("doc_id", held.alias("held_out"), "lang_pred", "score")


def op7_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(table(spark, sf_dir, "documents"))


def op8_bpe(spark: SparkSession, sf_dir: str, path: str | None = None) -> DataFrame:
    out = bpe.encode(table(spark, sf_dir, "documents"), path or tokenizer_path("byte_bpe_50k.tiktoken"), decode_back=True)
    return out.select("doc_id", "n_tokens", hexed(F.col("ids")).alias("ids_sha256"), hexed(F.col("decoded")).alias("decoded_sha256"))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op10_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"))


def queries() -> dict:
    return {
        "op1_suffix_dedup": op1_suffix_dedup,
        "op2_chat_format": op2_chat_format,
        "op3_pii": op3_pii,
        "op4_simhash": op4_simhash,
        "op5_bm25": op5_bm25,
        "op6_language_id": op6_language_id,
        "op7_exact_dedup": op7_exact_dedup,
        "op8_bpe": op8_bpe,
        "op9_mixing": op9_mixing,
        "op10_html": op10_html,
    }


def oracle_sql() -> dict[str, str]:
    return {"op2_chat_format": OP2, "op7_exact_dedup": OP7}


OP7 = r"""
WITH d AS (
  SELECT doc_id, regexp_replace(coalesce(text, ''), '[ \t\n\x0B\f\r]+', ' ', 'g') AS norm FROM documents
)
SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id IS NOT DISTINCT FROM min(doc_id) OVER w AS kept, sha256(norm) AS text_sha256
FROM d WINDOW w AS (PARTITION BY norm)
"""

OP2 = r"""
WITH rows AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'
), sized AS (
  SELECT *, length(text) + (length(text) - length(replace(text, '\', '')))
    + coalesce(list_sum(list_transform(regexp_extract_all(text, '#{3,}'), lambda m: length(m) - 2)), 0)
    + (length(text) - length(replace(text, '</turn>', ''))) // 7 AS n_text,
    length(role) + (length(role) - length(replace(replace(role, '\', ''), ':', '')))
    + coalesce(list_sum(list_transform(regexp_extract_all(role, '#{3,}'), lambda m: length(m) - 2)), 0)
    + (length(role) - length(replace(role, '</turn>', ''))) // 7 AS n_role
  FROM rows
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(14 + n_text + n_role) AS BIGINT) AS formatted_chars
FROM sized GROUP BY conv_id
"""
