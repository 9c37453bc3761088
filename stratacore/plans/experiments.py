"""The experiment workloads: space and error against threshold and growth, scaling, baselines, claims, ablations."""

from __future__ import annotations

import math
import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import TWO52, edge_u52, edge_uniform
from ..operators import cores
from ..operators.peel import PACKED_EDGES, exact_coreness, numbered, packed_coreness
from ..operators.sketch import sketch_coreness
from ..params import SketchParams
from ..runtime import Rounds, drop_written, written
from ..sources import clique_ladder, degrees, graph
from . import grid
from .measures import POINTS, band_check, error_percentiles, relative_error

#: The four graphs that stand in for the published ones, and the published values and numbers of runs.
GRAPHS = ("word_adjacency", "doc_word", "cust_supp", "part_supp")
ACCEPTS, GROWTHS, SEEDS = (2, 3, 4, 5), (1.2, 1.4, 1.6, 2.0), (0, 1, 2)
PRACTICAL = SketchParams(accept=3, p0="scaled", cap="scaled", peeler="auto")


def sweep(spark: SparkSession, sf_dir: str, graphs: list[str], params: list[SketchParams], seeds=SEEDS, errors: bool = True) -> DataFrame:
    """One row for each graph, parameter set and seed, each sketch by the cluster: for graphs above one task's size.
    errors=False leaves the error percentiles null and needs no exact labels."""
    out = []
    for name in graphs:
        edges = written(graph(spark, sf_dir, name), "edges")
        m, n = edges.count(), degrees(edges).count()
        exact = written(exact_coreness(edges, "auto"), "exact") if errors else None
        for p in params:
            for seed in seeds:
                began = time.time()
                s = sketch_coreness(edges, replace(p, seed=seed), n)
                took = time.time() - began
                e = error_percentiles(s.labels, exact).first() if errors else [None] * 6
                out.append((name, seed, float(p.threshold(n)), p.growth, p.eps, n, m, len(s.space), s.space_max(), s.space_sum(), s.space_max() / m, s.space_sum() / m, s.space_max() / n, *(e[k] for k in range(1, 6)), took))
    return spark.createDataFrame(out, f"graph string, seed int, {grid.REPORT}")


def vary_accept(spark, sf_dir, graphs=GRAPHS, values=ACCEPTS, seeds=SEEDS, errors: bool = True) -> DataFrame:
    return grid.report(spark, sf_dir, graphs, [replace(PRACTICAL, accept=t) for t in values], seeds, errors)


def vary_growth(spark, sf_dir, graphs=GRAPHS, values=GROWTHS, seeds=SEEDS, eps=(0.25,), errors: bool = True) -> DataFrame:
    return grid.report(spark, sf_dir, graphs, [replace(PRACTICAL, growth=m, eps=e) for m in values for e in eps], seeds, errors)


def scaling(spark, sf_dir: str, graphs=("doc_word", "cust_supp", "copart"), parts=(0.125, 0.25, 0.5, 1.0)) -> DataFrame:
    """Seconds against edges at accept 4, growth 2, over growing parts of each graph's edges; slope: of the logarithms,
    over the rows of the graph (below 1: sublinear). Seconds hold what a level costs at least on this cluster."""
    out = []
    for name in graphs:
        whole, rows = written(graph(spark, sf_dir, name), "edges"), []
        for part in parts:
            edges = written(whole.where(edge_uniform(F.col("src"), F.col("dst"), "part") <= part), "part")
            began = time.time()
            sketch_coreness(edges, replace(PRACTICAL, accept=4))
            rows.append((edges.count(), time.time() - began))
        out += [(name, m, s, slope(rows)) for m, s in rows]
    return spark.createDataFrame(out, "graph string, m long, seconds double, slope double")


def slope(rows: list[tuple[float, float]]) -> float:
    """Least-squares slope of log(seconds) on log(edges): below 1 means sublinear."""
    xs, ys = [math.log(m) for m, _ in rows], [math.log(max(s, 1e-9)) for _, s in rows]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys, strict=True)) / max(1e-12, sum((x - mx) ** 2 for x in xs))


def baseline_time(spark, sf_dir, graphs=GRAPHS) -> DataFrame:
    """Rounds, Spark jobs and seconds of the sketch and of the threshold waves."""
    out = []
    for name in graphs:
        edges = written(graph(spark, sf_dir, name), "edges")
        began = time.time()
        s = sketch_coreness(edges, replace(PRACTICAL, accept=4))
        out.append((name, "sketch", s.rounds.levels, s.rounds.jobs, 0, time.time() - began))
        began, r = time.time(), Rounds()
        cores.threshold_waves(edges, rounds=r)
        out.append((name, "threshold_waves", 0, r.jobs, r.waves, time.time() - began))
    return spark.createDataFrame(out, "graph string, method string, levels int, jobs int, waves int, seconds double")


#: Log constants scaled down so far that several levels below rate 1 settle vertices of a small ladder of cliques.
SMALL = SketchParams(eps=0.25, c_rate=0.04, c_accept=0.08, c_cap=0.16, hash="md5")
LADDER = 60


def claims(spark, most: int = LADDER, p: SketchParams = SMALL, seeds=SEEDS) -> DataFrame:
    """Level bands on a ladder of cliques; one row per seed and level."""
    edges = written(clique_ladder(spark, most), "edges")
    exact, n, out = written(exact_coreness(edges, "local"), "exact"), degrees(edges).count(), None
    for seed in seeds:
        rows = band_check(sketch_coreness(edges, replace(p, seed=seed, idle=True), n).labels, exact, n, p.eps).selectExpr(f"{seed} as seed", "*")
        out = rows if out is None else out.unionByName(rows)
    return out


def success_rate(spark, sf_dir, p: SketchParams = SMALL, seeds=tuple(range(10)), graphs=("copart", "user_hour")) -> DataFrame:
    """(graph, runs, levels_used, bands, sizes, labels): the share of seeds that keep each promise; c_rate grows fourfold
    from row to row of a graph, so that the shares can be seen to rise with the constants."""
    ladder = written(clique_ladder(spark, LADDER).select(F.lit("clique_ladder").alias("graph"), "src", "dst"), "edges")
    out = None
    for times in (1, 4, 16):
        q = replace(p, c_rate=times * p.c_rate, c_accept=times * p.c_accept, c_cap=times * p.c_cap)
        for e in [ladder, *grid.graph_edges(spark, sf_dir, graphs)]:
            share = lambda c: F.avg(F.col(c).cast("double")).alias(c)
            rows = grid.success(e, q, seeds).groupBy("graph").agg(F.count(F.lit(1)).alias("runs"), F.max("levels_used").alias("levels_used"), share("bands"), share("sizes"), share("labels"))
            rows = rows.select("graph", F.lit(q.c_rate).alias("c_rate"), "runs", "levels_used", "bands", "sizes", "labels")
            out = rows if out is None else out.unionByName(rows)
    return out


def ablate_uniform(spark, sf_dir, names=("word_adjacency", "copart"), seed: int = 0) -> DataFrame:
    """Errors of the adaptive sketch and of uniform samples: one of the same total size, one of the size of the largest
    level (what one machine must hold); by coreness below 5 and from 5 on."""
    out, p = None, replace(PRACTICAL, seed=seed)
    for name in names:
        edges = written(graph(spark, sf_dir, name).select(F.lit(name).alias("graph"), "src", "dst"), "edges")
        m = edges.count()
        rows = grid.ablation(edges, p) if m <= grid.EXACT_EDGES else _ablate_large(edges, m, name, p)
        out = rows if out is None else out.unionByName(rows)
    return out


def _ablate_large(edges: DataFrame, m: int, name: str, p: SketchParams) -> DataFrame:
    """The same for a graph above one task's size. Vertices are numbered once, with the hashes of the ids as they were."""
    numbers, ids = numbered(edges)
    hashed = numbers.select(F.col("a").alias("src"), F.col("b").alias("dst"), edge_u52(F.col("src"), F.col("dst"), p.seed, p.hash).alias("u52"))
    hashed, n = written(hashed, "numbered"), ids.count()
    drop_written(edges)
    pairs = hashed.select("src", "dst")
    if m <= PACKED_EDGES:
        exact = packed_coreness(hashed.select(F.col("src").alias("a"), F.col("dst").alias("b")), n)
    else:
        exact = written(exact_coreness(pairs, "refine"), "exact")
    s = sketch_coreness(hashed, p, n)
    methods = [("adaptive", 0.0, s.labels)]
    for method, size in (("uniform_total", s.space_sum()), ("uniform_largest", s.space_max())):
        rate = min(1.0, size / m)
        sample = exact_coreness(hashed.where(F.col("u52") <= int(rate * TWO52)).select("src", "dst"), "auto")
        methods.append((method, rate, sample.select("id", (F.col("coreness") / F.lit(rate)).alias("label"))))
    errors, points = exact.where("coreness >= 1"), F.array(*map(F.lit, POINTS))
    for k, (_, _, labels) in enumerate(methods):
        errors = errors.join(labels.select("id", F.col("label").alias(f"label{k}")), "id", "left")
    band = F.when(F.col("coreness") < 5, "below 5").otherwise("5 and more").alias("band")
    at = [F.percentile(relative_error(F.coalesce(f"label{k}", F.lit(0.0)), F.col("coreness")), points).alias(f"at{k}") for k in range(len(methods))]
    found = errors.groupBy(band).agg(F.count(F.lit(1)).alias("vertices"), *at)
    bands = edges.sparkSession.createDataFrame([(b,) for b, _, _ in grid.BANDS], "band string")
    each = F.explode(F.array(*[F.struct(F.lit(method).alias("method"), F.lit(rate).alias("rate"), F.col(f"at{k}").alias("at")) for k, (method, rate, _) in enumerate(methods)]))
    rows = bands.join(found, "band", "left").select(each.alias("r"), "band", F.coalesce("vertices", F.lit(0)).alias("vertices"))
    return rows.select(F.lit(name).alias("graph"), "r.method", "r.rate", "band", "vertices", *[F.round(F.col("r.at")[k], 6).alias(f"p{int(100 * q)}") for k, q in enumerate(POINTS)])
