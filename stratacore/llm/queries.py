"""The registered queries of the training-data operators and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import op1_quality, op2_links, op10_decontaminate, op3_token_file, op4_pieces, op5_language, op6_jaccard, op7_lines, op8_windows, op9_personal, sqltext
from .common import table

WORD_TOKENIZER = "word_bpe_49k.json"
PIECE_MODEL = "piece_bpe_32k.model"


def op1_quality_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = op1_quality.judged(table(spark, sf_dir, "documents", "doc_id", "text", "lang"))
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op7_lines_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = op7_lines.dedup_lines(table(spark, sf_dir, "documents", "doc_id", "text"))
    return rows.select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("kept_sha256"))


def op2_links_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = op2_links.judged_pages(table(spark, sf_dir, "pages", "page_id", "url", "html"))
    return rows.select("page_id", "host", "path", "rule", "verdict")


def op10_decontaminate_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with the items that occur in it."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    rows = op10_decontaminate.contamination(docs, table(spark, sf_dir, "benchmark", "item_id", "text"))
    return rows.select("doc_id", (F.size("item_ids") > 0).alias("contaminated"), "item_ids", "distances")


def op6_jaccard_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op6_jaccard.jaccard_components(table(spark, sf_dir, "documents", "doc_id", "text"))


def op8_windows_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op8_windows.without_repeats(table(spark, sf_dir, "documents", "doc_id", "text"), digest=True).withColumnRenamed("kept", "kept_sha256")


def op9_personal_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op9_personal.personal_digests(table(spark, sf_dir, "documents", "doc_id", "text"))


def op5_language_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op5_language.predicted(table(spark, sf_dir, "documents", "doc_id", "text", "lang"), public_tokenizers.path(PIECE_MODEL))


def op3_token_file_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = op3_token_file.token_file_path(spark)
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    op3_token_file.write_token_file(docs, path, public_tokenizers.path(WORD_TOKENIZER), end_id=2)
    return op3_token_file.token_digests(spark, path)


def op4_pieces_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op4_pieces.piece_digests(table(spark, sf_dir, "documents", "doc_id", "text"), public_tokenizers.path(PIECE_MODEL))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_quality": op1_quality_query,
    "op2_links": op2_links_query,
    "op3_token_file": op3_token_file_query,
    "op4_pieces": op4_pieces_query,
    "op5_language": op5_language_query,
    "op6_jaccard": op6_jaccard_query,
    "op7_lines": op7_lines_query,
    "op8_windows": op8_windows_query,
    "op9_personal": op9_personal_query,
    "op10_decontaminate": op10_decontaminate_query,
}

ORACLE_SQL: dict[str, str] = {
    "op1_quality": sqltext.OP1,
    "op2_links": sqltext.OP2,
    "op6_jaccard": sqltext.OP6,
    "op7_lines": sqltext.OP7,
    "op8_windows": sqltext.OP8,
}
