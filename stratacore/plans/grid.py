"""Whole parameter grids at once: every run in one task, the runs side by side.

A graph that one task can hold (SPACE_EDGES, EXACT_EDGES) needs no cluster for one sketch, but a grid of graphs, thresholds, growth
factors and seeds is many sketches. Each (graph, seed) is a group whose task runs all parameter sets over its edges in
arrays, with the same hashes, schedule, peel and label formula as `sketch_coreness`, so the numbers are the same.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace
from functools import cached_property, reduce
from multiprocessing.pool import ThreadPool

import numpy as np
import pyarrow as pa
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import TWO52, edge_u52
from ..operators.peel import PACKED_EDGES, local_labels, numbered
from ..operators.sketch import sketch_coreness
from ..params import SketchParams, label_of, plan_space, rate_schedule
from ..runtime import drop_written, shuffles_dropped, written
from ..sources import graph
from .banded import banded_report

POINTS = (50, 60, 70, 80, 90)


#: Edges of a grid's graph in one task: 32 bytes each while they are sorted, 56 where the exact peel is asked for.
SPACE_EDGES, EXACT_EDGES = 40_000_000, 20_000_000
#: Edges above which `report` brings them to its runs in the order of their hashes (`banded`), which hold samples alone.
BANDED_EDGES = 2_000_000


class Graph:
    """Edges as vertex numbers in ascending order of their hashes, so that a sample is a prefix; the exact coreness is
    peeled when it is asked for."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, u52: np.ndarray):
        order = np.argsort(u52)
        self.u52 = u52[order]
        number = np.zeros(max(int(src.max()), int(dst.max())) + 1, np.int32)
        number[src], number[dst] = 1, 1
        self.n = int(number.sum())
        np.cumsum(number, out=number)
        self.src, self.dst = number[src[order]] - 1, number[dst[order]] - 1

    @cached_property
    def exact(self) -> np.ndarray:
        return local_labels(self.src, self.dst, self.n, np.zeros(self.n, bool))[0]


class Run:
    """One sketch: labels and levels by vertex number; (level, rate, edges, edges after a pre-peel) of each level."""

    def __init__(self, g: Graph, p: SketchParams, prepeel: int = 0):
        began = time.time()
        self.label, self.level, self.space = np.zeros(g.n), np.full(g.n, -1), []
        settled = np.zeros(g.n, bool)
        for lv in rate_schedule(g.n, p):
            src, dst = g.src, g.dst
            if lv.rate < 1:
                drawn = int(np.searchsorted(g.u52, int(lv.rate * TWO52), "right"))
                src, dst = src[:drawn], dst[:drawn]
            inside = ~(settled[src] & settled[dst])
            src, dst = src[inside], dst[inside]
            raw, _ = local_labels(src, dst, g.n, settled)
            left = len(src)
            if prepeel:
                weak = (raw >= 0) & (raw < prepeel)
                left = int((~weak[src] & ~weak[dst]).sum())
            took = np.flatnonzero(~settled & ((raw >= lv.accept) | (lv.rate >= 1)))
            values = np.array([label_of(x, lv, p) for x in range(int(raw.max(initial=0)) + 1)])
            self.label[took], self.level[took], settled[took] = values[raw[took]], lv.level, True
            self.space.append((lv.level, lv.rate, len(src), left))
        self.seconds = time.time() - began

    @property
    def sizes(self) -> list[int]:
        return [x[2] for x in self.space]


def per_run(edges: DataFrame, seeds: tuple[int, ...], kind: str, rows: Callable[[Graph, int], list[tuple]], schema: str) -> DataFrame:
    """rows(graph, seed) of every graph and seed, from (graph, src, dst); schema: what follows graph and seed."""
    runs = F.explode(F.array(*[F.struct(F.lit(s).alias("seed"), edge_u52(F.col("src"), F.col("dst"), s, kind).alias("u52")) for s in seeds]))
    types = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "boolean": pa.bool_()}
    out = pa.schema([(name, types[kind]) for name, kind in (c.split() for c in f"graph string, seed int, {schema}".split(","))])

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        g = Graph(*(np.concatenate([c.to_numpy() for c in table[x].chunks]) for x in ("a", "b", "u52")))
        name, seed = key[0].as_py(), key[1].as_py()
        return pa.Table.from_pylist([dict(zip(out.names, (name, seed, *r), strict=True)) for r in rows(g, seed)], out)

    # A seed's hashes are of the ids as they are; vertices travel as numbers of four bytes.
    hashed = numbered(edges)[0].select("graph", "a", "b", runs.alias("r"))
    return hashed.select("graph", "r.seed", "a", "b", "r.u52").groupBy("graph", "seed").applyInArrow(run, f"graph string, seed int, {schema}")


def graph_edges(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> list[DataFrame]:
    """(graph, src, dst) of each graph, for `per_run`; raises where one is too large for one task."""
    small, large = _by_size(spark, sf_dir, names, EXACT_EDGES)
    if large:
        raise ValueError(f"{large} have more than {EXACT_EDGES} edges: take the cluster's peeler")
    return small


def _by_size(spark: SparkSession, sf_dir: str, names: tuple[str, ...], most: int) -> tuple[list[DataFrame], list[str]]:
    """(graph, src, dst) of the graphs that one task holds, and the names of the others."""
    small, large = [], []
    for name in names:
        e = written(graph(spark, sf_dir, name).select(F.lit(name).alias("graph"), "src", "dst"), "edges")
        if e.count() <= most:
            small.append(e)
        else:
            large.append(name)
            drop_written(e)
    return small, large


REPORT = "accept double, growth double, eps double, n long, m long, levels int, max_edges long, sum_edges long, max_share double, sum_share double, max_per_n double, p50 double, p60 double, p70 double, p80 double, p90 double, seconds double"


def report(spark: SparkSession, sf_dir: str, names: tuple[str, ...], grid: list[SketchParams], seeds: tuple[int, ...], errors: bool = True) -> DataFrame:
    """One row for each graph, seed and parameter set: space, and error percentiles over coreness >= 5 (null without
    `errors`). Edges of graphs above one task's size come in bands; what exceeds those (PACKED_EDGES, CODED_VERTICES) is
    swept sketch by sketch by the cluster."""

    def rows(g: Graph, seed: int) -> list[tuple]:
        out, m = [], len(g.src)
        high = g.exact >= 5 if errors else np.zeros(g.n, bool)
        for p in grid:
            r = Run(g, replace(p, seed=seed))
            err = np.abs(r.label[high] - g.exact[high]) / g.exact[high] if errors else None
            points = [float(x) for x in np.percentile(err, POINTS)] if high.any() else [None] * len(POINTS)
            out.append((float(p.threshold(g.n)), p.growth, p.eps, g.n, m, len(r.space), max(r.sizes), sum(r.sizes), max(r.sizes) / m, sum(r.sizes) / m, max(r.sizes) / g.n, *points, r.seconds))
        return out

    from .experiments import sweep

    most = min(BANDED_EDGES, EXACT_EDGES if errors else SPACE_EDGES)

    def one(name: str) -> DataFrame | None:
        edges = written(graph(spark, sf_dir, name), "edges")
        m = edges.count()
        if m <= most:
            return per_run(edges.select(F.lit(name).alias("graph"), "src", "dst"), seeds, grid[0].hash, rows, REPORT)
        found = banded_report(edges, m, name, grid, seeds, errors, f"graph string, seed int, {REPORT}", POINTS) if m <= PACKED_EDGES else None
        drop_written(edges)
        return found

    # One graph's single tasks (its peel, its runs) leave cores to the others.
    with shuffles_dropped(spark), ThreadPool(len(names)) as pool:
        parts = pool.map(inheritable_thread_target(spark)(one), names)
    large = [name for name, part in zip(names, parts, strict=True) if part is None]
    parts = [part for part in parts if part is not None]
    return reduce(DataFrame.unionByName, [*parts, *([sweep(spark, sf_dir, large, grid, seeds, errors)] if large else [])])


BANDS = (("below 5", 1, 4), ("5 and more", 5, None))
ABLATION = "method string, rate double, band string, vertices long, p50 double, p60 double, p70 double, p80 double, p90 double"


def ablation(edges: DataFrame, p: SketchParams) -> DataFrame:
    """`experiments.ablate_uniform` for a graph (graph, src, dst) of up to EXACT_EDGES edges: all methods in one task."""

    def rows(g: Graph, seed: int) -> list[tuple]:
        r, m = Run(g, replace(p, seed=seed)), len(g.src)
        methods = [("adaptive", 0.0, r.label)]
        for method, size in (("uniform_total", sum(r.sizes)), ("uniform_largest", max(r.sizes))):
            rate = min(1.0, size / m)
            drawn = int(np.searchsorted(g.u52, int(rate * TWO52), "right"))
            methods.append((method, rate, local_labels(g.src[:drawn], g.dst[:drawn], g.n, np.zeros(g.n, bool))[0] / rate))
        out = []
        for method, rate, label in methods:
            for band, least, most in BANDS:
                some = (g.exact >= least) & (g.exact <= (most or g.n))
                err = np.abs(label[some] - g.exact[some]) / g.exact[some]
                points = [float(x) for x in np.percentile(err, POINTS)] if some.any() else [None] * len(POINTS)
                out.append((method, rate, band, int(some.sum()), *points))
        return out

    return per_run(edges, (p.seed,), p.hash, rows, ABLATION).drop("seed").withColumns({f"p{k}": F.round(f"p{k}", 6) for k in POINTS})


def prepeel_saving(spark: SparkSession, sf_dir: str, names: tuple[str, ...], p: SketchParams, least: int = 3) -> DataFrame:
    """(graph, seed, level, rate, edges, collected): a level's sample, and what the peeling task gets after the waves."""
    rows = lambda g, seed: Run(g, replace(p, seed=seed), least).space
    schema = "level int, rate double, edges long, collected long"
    small, large = _by_size(spark, sf_dir, names, SPACE_EDGES)
    parts = [per_run(e, (p.seed,), p.hash, rows, schema) for e in small]
    for name in large:
        space = sketch_coreness(graph(spark, sf_dir, name), replace(p, prepeel=least, rounds="two")).space
        parts.append(spark.createDataFrame([(name, p.seed, *x) for x in space], f"graph string, seed int, {schema}"))
    return reduce(DataFrame.unionByName, parts)


def band_breaks(level: np.ndarray, exact: np.ndarray, rates: list[float], n: int, eps: float) -> list[tuple[int, int, int, int]]:
    """Per level: settled vertices, and how many lie above and below the coreness band of that level."""
    out = []
    for k in sorted(set(level.tolist())):
        c = exact[level == k]
        high, low = 2 * (1 + eps) * n / 2.0 ** (k - 1), 2 * (1 - eps) * n / 2.0**k
        out.append((int(k), len(c), int((c >= high).sum()), int((c < low).sum()) if rates[k] < 1 else 0))
    return out


def success(edges: DataFrame, p: SketchParams, seeds: tuple[int, ...]) -> DataFrame:
    """(graph, seed, levels_used, bands, sizes, labels): whether a run keeps every level's band, the bound on every
    level's sample, and the bound 1 - 2 eps on every label; edges: (graph, src, dst)."""

    def rows(g: Graph, seed: int) -> list[tuple]:
        r = Run(g, replace(p, seed=seed))
        breaks = band_breaks(r.level, g.exact, [x[1] for x in r.space], g.n, p.eps)
        bound = plan_space(g.n, p)["bound_max"]
        fine = (r.label <= g.exact + 1e-9) & (r.label >= (1 - 2 * p.eps) * g.exact - 1e-9)
        return [(len(breaks), not any(a or b for _, _, a, b in breaks), max(r.sizes) <= bound, bool(fine.all()))]

    return per_run(edges, seeds, p.hash, rows, "levels_used int, bands boolean, sizes boolean, labels boolean")
