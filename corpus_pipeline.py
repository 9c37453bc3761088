"""A corpus preparation pipeline out of the training-data operators.

Stages: quality rules, line dedup, n-gram Jaccard join, benchmark decontamination, piece encoding. Every stage takes
(spark, docs, sf_dir), works on all rows its predecessor kept, and its result is written as Parquet and reread. All
but the last return the columns of documents, which travel as one struct, so that extra columns may have any name.
Rows with one doc_id (or none) are one document where duplicates are looked for.
"""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stratacore.llm import op1_quality, op4_pieces, op6_jaccard, op7_lines, op10_decontaminate
from stratacore.llm.common import drop_written, packed, table, unpacked, written
from stratacore.llm.queries import PIECE_MODEL


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep."""
    return op1_quality.kept_documents(docs)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, without the lines that a larger doc_id keeps; n_chars follows the new text."""
    out = op7_lines.dedup_lines(docs.select(packed(docs), "doc_id", "text"))
    new = {"text": F.col("text"), "n_chars": F.char_length("text").cast("long")}
    return out.select(*[new.get(c, F.col("row")[f"c{k}"]).alias(c) for k, c in enumerate(docs.columns)])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest doc_id of each class of similar documents."""
    stays = op6_jaccard.jaccard_components(docs).where("doc_id <=> component_id").select("doc_id").distinct()
    rows = docs.select(packed(docs))
    return unpacked(rows.join(stays, rows["row"][f"c{docs.columns.index('doc_id')}"].eqNullSafe(stays["doc_id"]), "left_semi"), docs.columns)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark item occurs."""
    found = op10_decontaminate.contamination(docs.select(packed(docs), "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))
    return unpacked(found.where(F.size("item_ids") == 0), docs.columns)


def piece_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of what is left."""
    return op4_pieces.piece_digests(docs, public_tokenizers.path(PIECE_MODEL))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_rules", quality_rules),
    ("line_dedup", line_dedup),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("piece_encoding", piece_encoding),
]

#: Shingle sets, edit distances and the piece model are out of SQL's reach; tests/llm holds a brute-force version.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        before, docs = docs, written(stage(spark, docs, sf_dir), f"pipeline-{name}")
        drop_written(before)
    return docs
