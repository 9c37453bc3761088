"""Helpers shared by the training-data operators: text columns, and the written tables of `runtime`."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..runtime import drop_written, new_path, remove, shared_dir, written

__all__ = ["ascii_lower", "drop_written", "let", "new_path", "packed", "remove", "shared_dir", "table", "unpacked", "words", "written"]

#: The white space that separates words, as a character class body.
SPACE = r"\x20\x09-\x0D"
SPACE_CHARS = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def ascii_lower(c: Column) -> Column:
    """A-Z only; pure ASCII strings take the vectorised lower()."""
    return F.when(F.octet_length(c) == F.char_length(c), F.lower(c)).otherwise(F.translate(c, UPPER, LOWER))


def words(c: Column) -> Column:
    """The non-empty runs between white space."""
    return F.array_remove(F.split(c, f"[{SPACE}]+"), "")


def let(value: Column, body) -> Column:
    """body(value) with value evaluated once per row, even when body uses it inside a lambda."""
    return F.element_at(F.transform(F.array(value), body), 1)


def packed(docs: DataFrame) -> Column:
    """All columns as one struct `row` (fields c0, c1, ..), out of the way of an operator's own names."""
    return F.struct(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns)]).alias("row")


def unpacked(rows: DataFrame, names: list[str]) -> DataFrame:
    """The columns that `packed` put into `row`."""
    return rows.select(*[F.col("row")[f"c{k}"].alias(c) for k, c in enumerate(names)])
