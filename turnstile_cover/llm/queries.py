"""One thin query for each operator over its whole table: digests derived from the operator's real output."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from .chat import format_chats
from .decontam import decontaminate
from .html_extract import extract
from .jaccard_join import near_duplicates
from .langid import fit, fold, identify
from .lm import score
from .packing import pack
from .pii import KINDS, listed, sanitise
from .quality import repetition
from .substring_dedup import remove_repeats


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    held_out = F.coalesce(fold("doc_id", 4) == 2, F.lit(False))
    model = fit(documents.where(~held_out).select("text", "lang"))
    return identify(documents, model).select("doc_id", held_out.alias("held_out"), "lang_pred", "score")


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = repetition(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "broken_rule", "dup_line_chars", *[c for c in out.columns if c.startswith("dup_") and c[4:].isdigit()])


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = sanitise(table(spark, sf_dir, "documents"), with_text=False)
    counts = [F.size(k).cast("long").alias(f"n_{k}") for k in KINDS]
    return out.select("doc_id", *counts, F.sha2(listed(tuple(KINDS)), 256).alias("base_sha256"), listed((*KINDS, "term")).alias("spans"))


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", F.array_sort("items")), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def op5_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = remove_repeats(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken"))


def op7_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = extract(table(spark, sf_dir, "pages"), keep=("url",))
    return out.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))


def op8_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    held_out = F.coalesce(fold("doc_id", 10) == 0, F.lit(False))
    out = score(documents, documents.where(~held_out))
    return out.select("doc_id", held_out.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op9_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = near_duplicates(table(spark, sf_dir, "documents"), words=3, percent=90)
    return out.select("doc_id", "n_shingles", "component_id")


#: Production schemas of op10: for each tool its arguments, their JSON types and whether they must be there.
TOOLS = {
    "search": {"query": ("string", True), "limit": ("integer", False)},
    "calculate": {"expression": ("string", True)},
    "fetch": {"url": ("string", True), "headers": ("object", False)},
    "run_code": {"language": ("string", True), "source": ("string", True), "timeout": ("number", False)},
}


def op10_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return format_chats(table(spark, sf_dir, "conversations"), TOOLS)


QUERIES = {f.__name__: f for f in (op1_language_id, op2_quality_rules, op3_pii, op4_decontamination, op5_substring_dedup, op6_packing, op7_html_extraction, op8_lm_scoring, op9_ngram_jaccard_join, op10_chat_formatting)}
#: Messages of tables without tool calls, as the given ones are; tests hold linking against brute force.
OP10_SQL = """
SELECT conv_id, turn, coalesce(role, '') AS role, CAST(0 AS BIGINT) AS n_calls, CAST(0 AS BIGINT) AS n_linked, CAST(0 AS BIGINT) AS n_faulty,
       coalesce(role, '') = 'tool' AS is_orphan,
       '{"content":' || CAST(to_json(coalesce(text, '')) AS VARCHAR) || ',"conv_id":' || conv_id || ',"role":' || CAST(to_json(coalesce(role, '')) AS VARCHAR)
       || ',"tool_calls":[],"turn":' || turn || '}' AS line
FROM conversations
"""
ORACLE_SQL: dict[str, str] = {"op10_chat_formatting": OP10_SQL}
