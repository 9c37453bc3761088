"""What labels are used for: hierarchy, approximate cores, label checks, orientation, densest subgraphs, baselines."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import edge_uniform
from ..runtime import Rounds, shared_dir, written
from ..sources import degrees
from .peel import LOCAL_EDGES, _wave_order, exact_coreness, exclusive_local, strip_below


def edge_levels(edges: DataFrame, labels: DataFrame, value: str = "coreness") -> DataFrame:
    """(src, dst, level): an edge lies in all cores up to the smaller label of its ends."""
    a, b = labels.select(F.col("id").alias("src"), F.col(value).alias("x")), labels.select(F.col("id").alias("dst"), F.col(value).alias("y"))
    return edges.join(a, "src").join(b, "dst").select("src", "dst", F.least("x", "y").alias("level"))


def core_hierarchy(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """(k, vertices, edges, density) of every core, k over the occurring corenesses."""
    v = labels.groupBy(F.col("coreness").alias("k")).agg(F.count(F.lit(1)).alias("v"))
    e = edge_levels(edges, labels).groupBy(F.col("level").alias("k")).agg(F.count(F.lit(1)).alias("e"))
    both = v.join(e, "k", "full").fillna(0, ["v", "e"])
    # One row for each distinct coreness: a short table, summed from the densest core down.
    down = Window.orderBy(F.desc("k")).rowsBetween(Window.unboundedPreceding, 0)
    out = both.select("k", F.sum("v").over(down).alias("vertices"), F.sum("e").over(down).alias("edges"))
    return out.withColumn("density", F.col("edges") / F.col("vertices"))


def approx_k_core(edges: DataFrame, labels: DataFrame, k: float, slack: float) -> tuple[DataFrame, DataFrame]:
    """(vertices, edges): vertices with label >= slack * k, closed by peeling to degree >= slack * k among themselves."""
    import math

    some = labels.where(F.col("label") >= slack * k).select("id")
    inside = edges.join(some.select(F.col("id").alias("src")), "src", "left_semi").join(some.select(F.col("id").alias("dst")), "dst", "left_semi")
    closed, _ = strip_below(inside, math.ceil(slack * k))
    return degrees(closed).select("id"), closed


def label_bounds(labels: DataFrame, exact: DataFrame, eps: float, side: str = "lower") -> DataFrame:
    """Rows that break the promise: label in [(1 - 2 eps) C, C] (lower), or in [C, C / (1 - 2 eps)] (upper)."""
    both = labels.join(exact, "id")
    c, x, tiny = F.col("coreness"), F.col("label"), 1e-9
    ok = (x <= c + tiny) & (x >= (1 - 2 * eps) * c - tiny) if side == "lower" else (x >= c - tiny) & (x * (1 - 2 * eps) <= c + tiny)
    return both.where(~ok).select("id", "label", "coreness")


def orient_edges(edges: DataFrame, order: DataFrame) -> DataFrame:
    """(tail, head): each edge points to its end peeled first (then the smaller id), so in-degree <= coreness."""
    a = order.select(F.col("id").alias("src"), F.col("step").alias("x"))
    b = order.select(F.col("id").alias("dst"), F.col("step").alias("y"))
    both = edges.join(a, "src").join(b, "dst")
    first = (F.col("x") < F.col("y")) | ((F.col("x") == F.col("y")) & (F.col("src") < F.col("dst")))
    return both.select(F.when(first, F.col("dst")).otherwise(F.col("src")).alias("tail"), F.when(first, F.col("src")).otherwise(F.col("dst")).alias("head"))


def peel_order(edges: DataFrame, method: str = "auto") -> DataFrame:
    """(id, coreness, step): the removal order of a peel; vertices of one step fall together. 'local' peels in one task,
    'waves' across the cluster, 'auto' locally where a count allows it."""
    if method == "auto":
        edges = written(edges, "edges")
        method = "local" if edges.count() <= LOCAL_EDGES else "waves"
    if method == "waves":
        return _wave_order(edges, Rounds())
    flags = edges.withColumns({"su": F.lit(False), "sv": F.lit(False)})
    return exclusive_local(flags).select("id", F.col("raw").alias("coreness"), "step")


def densest_from_cores(hierarchy: DataFrame) -> DataFrame:
    """The core of the highest edge density (smallest k on ties): at least half as dense as the densest subgraph."""
    return hierarchy.orderBy(F.desc("density"), "k").limit(1)


# ---------------------------------------------------------------- baselines


def threshold_waves(edges: DataFrame, start: int = 4, growth: int = 2, rounds: Rounds | None = None) -> DataFrame:
    """(id, estimate): strip everything below the threshold, estimate it by the threshold, multiply, go on."""
    shared_dir(edges.sparkSession)
    rounds = rounds or Rounds()
    threshold, left, out = start, edges, None
    while not left.isEmpty():
        before = degrees(left).select("id")
        left, _ = strip_below(left, threshold, rounds=rounds)
        part = written(before.join(degrees(left).select("id"), "id", "left_anti").withColumn("estimate", F.lit(threshold).cast("long")), "threshold")
        out = part if out is None else out.unionByName(part)
        threshold *= growth
    return out if out is not None else degrees(edges).select("id", F.lit(start).cast("long").alias("estimate"))


def uniform_sample_coreness(edges: DataFrame, rate: float, seed: int = 0, kind: str = "xxhash64", method: str = "local") -> DataFrame:
    """(id, raw, label): one sample for all densities, label raw / rate; vertices that the sample misses get 0."""
    sample = written(edges.where(edge_uniform(F.col("src"), F.col("dst"), seed, kind) <= rate), "uniform")
    labels = exact_coreness(sample, method)
    return degrees(edges).select("id").join(labels, "id", "left").select("id", F.coalesce("coreness", F.lit(0)).cast("long").alias("raw"), (F.coalesce("coreness", F.lit(0)) / F.lit(rate)).alias("label"))


def densest_by_peeling(edges: DataFrame, eps: float = 0.1) -> tuple[float, DataFrame, int]:
    """(density, vertices, rounds): strip all vertices of degree below 2 (1 + eps) times the density, keep the best."""
    shared_dir(edges.sparkSession)
    left, best, found, rounds = edges, -1.0, None, 0
    while True:
        d = degrees(left).checkpoint()
        n, twice = d.agg(F.count(F.lit(1)), F.sum("degree")).first()
        if not n:
            return max(best, 0.0), found if found is not None else d.select("id"), rounds
        density = twice / 2 / n
        if density > best:
            best, found = density, d.select("id")
        weak = d.where(F.col("degree") <= 2 * (1 + eps) * density).select("id")
        left = left.join(weak, left["src"] == weak["id"], "left_anti").join(weak, left["dst"] == weak["id"], "left_anti").checkpoint()
        rounds += 1
