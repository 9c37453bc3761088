"""Accuracy, space and load measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.sketch import Sketch
from ..sources import degrees

POINTS = (0.5, 0.6, 0.7, 0.8, 0.9)


def relative_error(label: Column, exact: Column, signed: bool = False) -> Column:
    diff = label - exact
    return (diff if signed else F.abs(diff)) / exact


def error_percentiles(labels: DataFrame, exact: DataFrame, least: int = 5, most: int | None = None, approximate: bool = False) -> DataFrame:
    """One row (vertices, p50 .. p90) of the relative error over vertices with coreness in [least, most]."""
    both = labels.join(exact, "id").where(F.col("coreness") >= max(least, 1))
    both = both if most is None else both.where(F.col("coreness") <= most)
    err = relative_error(F.col("label"), F.col("coreness"))
    points = F.array(*map(F.lit, POINTS))
    agg = F.percentile_approx(err, points, 100_000) if approximate else F.percentile(err, points)
    row = both.agg(F.count(F.lit(1)).alias("vertices"), agg.alias("p"))
    return row.select("vertices", *[F.round(F.col("p")[k], 6).alias(f"p{int(100 * q)}") for k, q in enumerate(POINTS)])


def approximation_factor(labels: DataFrame, exact: DataFrame, eps: float) -> DataFrame:
    """(least, greatest label / coreness, share within [1 - 2 eps, 1])."""
    r = F.col("label") / F.col("coreness")
    both = labels.join(exact, "id").where("coreness > 0")
    return both.agg(F.min(r).alias("least"), F.max(r).alias("greatest"), F.avg(((r >= 1 - 2 * eps - 1e-9) & (r <= 1 + 1e-9)).cast("double")).alias("within"))


def space_report(sketch: Sketch, edges: int) -> list[tuple]:
    """(largest level, all levels, their shares of the input)."""
    return [(sketch.space_max(), sketch.space_sum(), sketch.space_max() / edges, sketch.space_sum() / edges)]


def degree_concentration(edges: DataFrame, sample: DataFrame, p: float, f: float, eps: float, direction: str = "both") -> DataFrame:
    """Counts of vertices that keep or break the degree promises of a sample at rate p with threshold f.

    dense: degree >= f must satisfy |d_H - p d_G| <= eps d_H; sparse: degree < f must have d_H < 2 p f;
    seen_dense: d_H >= 2 p f must have degree >= 2 (1 - eps) f; seen_sparse: d_H < 2 p f must have d_G <= 2 (1 + eps) f.
    """
    def one(e: DataFrame, name: str) -> DataFrame:
        if direction == "both":
            return degrees(e).withColumnRenamed("degree", name)
        return e.groupBy(F.col("dst" if direction == "in" else "src").alias("id")).agg(F.count(F.lit(1)).alias(name))

    return _degree_promises(one(edges, "g").join(one(sample, "h"), "id", "left").fillna(0, ["h"]), p, f, eps)


def drawn_concentration(ends: DataFrame, p: float, f: float, eps: float) -> DataFrame:
    """The same counts from rows (id, kept), one for each edge of a vertex: one pass, nothing of the edges is shuffled."""
    return _degree_promises(ends.groupBy("id").agg(F.count(F.lit(1)).alias("g"), F.count_if("kept").alias("h")), p, f, eps)


def _degree_promises(d: DataFrame, p: float, f: float, eps: float) -> DataFrame:
    g, h = F.col("g"), F.col("h")
    close = F.abs(h - p * g) <= eps * h
    count = lambda where, ok, name: [F.count(F.when(where, 1)).alias(name), F.count(F.when(where & ~ok, 1)).alias(f"{name}_broken")]
    return d.agg(*count(g >= f, close, "dense"), *count(g < f, h < 2 * p * f, "sparse"), *count(h >= 2 * p * f, close & (g >= 2 * (1 - eps) * f), "seen_dense"), *count(h < 2 * p * f, g <= 2 * (1 + eps) * f, "seen_sparse"))


def band_check(labels: DataFrame, exact: DataFrame, n: int, eps: float) -> DataFrame:
    """Per level: settled vertices, and how many leave the coreness band of that level."""
    both = labels.join(exact, "id")
    high = F.lit(2 * (1 + eps) * n) / F.pow(F.lit(2.0), F.col("level") - 1)
    low = F.lit(2 * (1 - eps) * n) / F.pow(F.lit(2.0), F.col("level"))
    return both.groupBy("level").agg(F.count(F.lit(1)).alias("vertices"), F.count(F.when(F.col("coreness") >= high, 1)).alias("too_dense"), F.count(F.when((F.col("rate") < 1) & (F.col("coreness") < low), 1)).alias("too_sparse"))


def machine_load(df: DataFrame) -> DataFrame:
    """Rows per partition: the least, the mean and the largest load of a task."""
    per = df.groupBy(F.spark_partition_id().alias("p")).agg(F.count(F.lit(1)).alias("rows"))
    return per.agg(F.count(F.lit(1)).alias("tasks"), F.min("rows").alias("least"), F.avg("rows").alias("mean"), F.max("rows").alias("most"))


def mean_of_runs(rows: DataFrame, *keys: str) -> DataFrame:
    values = [c for c, t in rows.dtypes if c not in keys and c != "seed" and t in ("double", "bigint", "int")]
    return rows.groupBy(*keys).agg(*[F.avg(c).alias(c) for c in values])
