"""Column functions: portable and fast edge hashes, levels, h-index; their SQL registration."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TWO52 = 1 << 52


def edge_u52(src: Column, dst: Column, seed: int | str = 0, kind: str = "xxhash64") -> Column:
    """A whole number in [0, 2^52), a pure function of seed and endpoints; md5 is the same in other engines."""
    if kind == "md5":
        return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), src.cast("string"), dst.cast("string"))), 1, 13), 16, 10).cast("long")
    return F.shiftrightunsigned(F.xxhash64(F.lit(str(seed)), src, dst), 12)


def edge_uniform(src: Column, dst: Column, seed: int | str = 0, kind: str = "xxhash64") -> Column:
    return edge_u52(src, dst, seed, kind) / F.lit(float(TWO52))


def drawn(src: Column, dst: Column, rate: float, seed: int | str = 0, kind: str = "xxhash64") -> Column:
    """Whether an edge's hash lies at most at the rate: edge_uniform(..) <= rate by whole numbers, md5 by its digits."""
    most = int(rate * TWO52)
    if kind == "md5" and most < TWO52:
        return F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), src.cast("string"), dst.cast("string"))), 1, 13) <= F.lit(f"{most:013x}")
    return edge_u52(src, dst, seed, kind) <= F.lit(most)


def first_level(u52: Column, rates: list[float]) -> Column:
    """The first level whose rate reaches u, by comparing whole numbers (no logarithm to round)."""
    out = F.lit(len(rates) - 1)
    for k in range(len(rates) - 2, -1, -1):
        out = F.when(u52 <= F.lit(int(rates[k] * TWO52)), k).otherwise(out)
    return out.cast("int")


def h_index(values: Column) -> Column:
    """Largest h such that h of the array's numbers are at least h; 0 for an empty array."""
    ranked = F.zip_with(F.sort_array(values, False), F.sequence(F.lit(1), F.size(values)), lambda v, k: F.least(v.cast("long"), k.cast("long")))
    return F.when(F.size(values) > 0, F.array_max(ranked)).otherwise(F.lit(0).cast("long"))


def sketch_label(raw: Column, rate: Column, eps: float, cap: Column) -> Column:
    return (1 - eps) * F.least(raw.cast("double"), cap) / rate


HISTOGRAM_BINS, HISTOGRAM_WIDTH = 5, 10


@F.pandas_udf(T.ArrayType(T.LongType()))
def core_histogram(values: pd.Series) -> list:
    """Grouped aggregate: how many corenesses lie in each of HISTOGRAM_BINS bins of HISTOGRAM_WIDTH, the last one open."""
    bins = (values.dropna() // HISTOGRAM_WIDTH).clip(upper=HISTOGRAM_BINS - 1).astype("int64")
    return [int((bins == k).sum()) for k in range(HISTOGRAM_BINS)]


@F.udtf(returnType=T.StructType([T.StructField("id", T.StringType()), T.StructField("coreness", T.LongType()), T.StructField("step", T.LongType())]))
class PeelOrder:
    """Table function over an edge table (src, dst), for graphs that one task holds: removal order with coreness."""

    def __init__(self):
        self.edges: list[tuple[str, str]] = []

    def eval(self, row: Row):
        self.edges.append((row["src"], row["dst"]))

    def terminate(self):
        from ..operators.peel import local_labels

        ids = sorted({x for e in self.edges for x in e})
        number = {x: k for k, x in enumerate(ids)}
        ends = np.array([(number[a], number[b]) for a, b in self.edges], np.int64).reshape(-1, 2)
        label, turn = local_labels(ends[:, 0], ends[:, 1], len(ids), np.zeros(len(ids), bool))
        yield from zip(ids, label.tolist(), turn.tolist(), strict=True)


def peel_table(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """(id string, coreness, step) by the table function."""
    spark.udtf.register("peel_order", PeelOrder)
    rows = edges.select(F.col("src").cast("string").alias("src"), F.col("dst").cast("string").alias("dst"))
    return spark.sql("SELECT * FROM peel_order(TABLE(SELECT * FROM {edges}) WITH SINGLE PARTITION)", edges=rows)


def register(spark: SparkSession) -> None:
    """SQL functions: edge_uniform(src, dst, seed), h_index(array), sketch_label(raw, rate, eps, cap),
    first_level(u52, rates), core_histogram(coreness), and the table function peel_order(TABLE edges)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION first_level(u52 BIGINT, rates ARRAY<DOUBLE>) RETURNS INT RETURN least(size(rates) - 1, size(filter(rates, r -> CAST(r * 4503599627370496D AS BIGINT) < u52)))")
    spark.udf.register("core_histogram", core_histogram)
    spark.udtf.register("peel_order", PeelOrder)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION edge_uniform(src BIGINT, dst BIGINT, seed BIGINT) RETURNS DOUBLE RETURN shiftrightunsigned(xxhash64(cast(seed AS STRING), src, dst), 12) / 4503599627370496D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION h_index(v ARRAY<BIGINT>) RETURNS BIGINT RETURN CASE WHEN size(v) > 0 THEN array_max(zip_with(sort_array(v, false), sequence(1L, cast(size(v) AS BIGINT)), (a, k) -> least(a, k))) ELSE 0L END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sketch_label(raw DOUBLE, rate DOUBLE, eps DOUBLE, cap DOUBLE) RETURNS DOUBLE RETURN (1 - eps) * least(raw, cap) / rate")
