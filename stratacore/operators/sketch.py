"""The adaptive sketch: samples of growing rate, each peeled with the settled vertices kept, dense vertices first."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions import TWO52, edge_u52, first_level
from ..params import Level, SketchParams, deflation, label_of, rate_schedule, without_idle
from ..runtime import Rounds, drop_written, written
from ..sources import degrees
from .peel import _flagged, coreness_bound, exclusive_local, exclusive_refined, local_labels, prepeel_labels


@dataclass
class Sketch:
    """labels (id, label, level, raw, rate); sample (level, src, dst); space rows (level, rate, edges, peeled edges)."""

    labels: DataFrame
    sample: DataFrame
    space: list[tuple[int, float, int, int]]
    rounds: Rounds

    def space_max(self) -> int:
        return max((x[2] for x in self.space), default=0)

    def space_sum(self) -> int:
        return sum(x[2] for x in self.space)


def annotate(edges: DataFrame, p: SketchParams, rates: list[float]) -> DataFrame:
    """edges with their hash (their column u52, if they bring it) and the first level whose nested sample holds them."""
    u = F.col("u52") if "u52" in edges.columns else edge_u52(F.col("src"), F.col("dst"), p.seed, p.hash)
    return edges.select("src", "dst", u.alias("u52")).withColumn("first_level", first_level(F.col("u52"), rates))


def level_sample(annotated: DataFrame, level: int, rate: float, p: SketchParams) -> DataFrame:
    """Edges of a level's sample. Nested: one hash per edge for all levels, a pruned scan of the clustered table."""
    if p.sampler == "nested" or rate >= 1:
        return annotated.where(F.col("first_level") <= level)
    u = edge_u52(F.col("src"), F.col("dst"), f"{p.seed}/{level}", p.hash)
    return annotated.where(u <= F.lit(int(rate * TWO52)))


def peeled(sample: DataFrame, edges: int, level: Level, p: SketchParams, rounds: Rounds, floor: int = 0) -> DataFrame:
    """(id, raw) of the unsettled vertices of a level's flagged sample, by the peeler that p and its size ask for; it may
    leave out vertices below `floor`."""
    local = p.peeler == "local" or (p.peeler == "auto" and edges <= p.max_local_edges)
    if local:
        return exclusive_local(sample, p.max_local_edges if p.peeler == "auto" else 1 << 62).select("id", "raw")
    # Labels are clipped at the cap anyway; what is clipped must still reach the threshold.
    most = None if math.isinf(level.cap) else math.ceil(max(level.cap, level.accept))
    return exclusive_refined(sample, most, rounds, floor, edges)


def accepted(raw: DataFrame, level: Level, p: SketchParams) -> DataFrame:
    """(id, label, level, raw, rate) of the vertices that a level settles; params.label_of states the formula."""
    took = raw.where(F.col("raw") >= level.accept) if level.rate < 1 else raw
    whole = math.isinf(level.cap)
    clipped = F.col("raw").cast("double") if whole else F.least(F.col("raw").cast("double"), F.lit(float(level.cap)))
    kept = F.col("raw") if whole else F.least("raw", F.lit(math.ceil(level.cap)))
    return took.select("id", (F.lit(deflation(level, p)) * clipped / F.lit(level.rate)).alias("label"), F.lit(level.level).alias("level"), kept.cast("long").alias("raw"), F.lit(level.rate).alias("rate"))


def prepeeled(h: DataFrame, settled: DataFrame | None, n_settled: int, level: Level, p: SketchParams, rounds: Rounds, floor: int = 0) -> tuple[DataFrame, int]:
    """((id, raw), edges that the peeler got): the waves that need no peeler first, where p asks for them."""
    if not p.prepeel:
        size = h.count()
        return peeled(h, size, level, p, rounds, floor), size
    rest, low = prepeel_labels(h.select("src", "dst"), p.prepeel, None if settled is None else settled.select("id"))
    rest = _flagged(rest, settled, n_settled)
    size = rest.count()
    return peeled(rest, size, level, p, rounds, floor).unionByName(low.select("id", F.col("label").alias("raw"))), size


def _carried(last: DataFrame, new: DataFrame, n_new: int) -> DataFrame:
    """The last level's sample without the edges that its settled vertices made needless, its flags brought up to date."""
    more = _flagged(last.select("src", "dst", F.col("su").alias("was_u"), F.col("sv").alias("was_v")), new, n_new)
    more = more.select("src", "dst", (F.col("su") | F.col("was_u")).alias("su"), (F.col("sv") | F.col("was_v")).alias("sv"))
    return more.where(~(F.col("su") & F.col("sv")))


def first_levels(annotated: DataFrame, levels: list[Level], p: SketchParams) -> tuple[DataFrame, list[tuple[int, int]]]:
    """((id, label, level, raw, rate) of what the levels settle, (edges of its sample, vertices settled) of each level),
    from edges whose first level is one of them: nested samples, sketched in one task."""
    kind = annotated.schema["src"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        ids, src, dst = None, np.zeros(0, np.int32), np.zeros(0, np.int32)
        if got:
            t = pa.Table.from_batches(got)
            del got
            both = pa.chunked_array([*t["src"].chunks, *t["dst"].chunks]).combine_chunks().dictionary_encode()
            both = both.combine_chunks() if isinstance(both, pa.ChunkedArray) else both
            ids, code, first = both.dictionary, both.indices.to_numpy(), t["first_level"].to_numpy()
            order = np.argsort(first, kind="stable")
            src, dst, first = code[: len(first)][order], code[len(first) :][order], first[order]
            del t, both, code, order
            settled = np.zeros(len(ids), bool)
        for lv in levels:
            drawn = int(np.searchsorted(first, lv.level, "right")) if len(src) else 0
            a, b = src[:drawn], dst[:drawn]
            inside = ~(settled[a] & settled[b]) if drawn else np.zeros(0, bool)
            a, b = a[inside], b[inside]
            # The size of the level's sample goes out as a row without an id.
            yield pa.RecordBatch.from_arrays([pa.nulls(1, got_type), pa.array([0.0]), pa.array([lv.level], pa.int32()), pa.array([len(a)]), pa.array([lv.rate])], names)
            if not len(a):
                continue
            here, code = np.unique(np.concatenate([a, b]), return_inverse=True)
            raw, _ = local_labels(code[: len(a)], code[len(a) :], len(here), settled[here])
            took = np.flatnonzero((raw >= 0) & ((raw >= lv.accept) | (lv.rate >= 1)))
            if not len(took):
                continue
            vertices, raw = here[took], raw[took]
            settled[vertices] = True
            label = np.array([label_of(x, lv, p) for x in range(int(raw.max()) + 1)])[raw]
            kept = raw if math.isinf(lv.cap) else np.minimum(raw, math.ceil(lv.cap))
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(vertices)), pa.array(label), pa.array(np.full(len(took), lv.level, np.int32)), pa.array(kept), pa.array(np.full(len(took), lv.rate))], names)

    names, got_type = ["id", "label", "level", "raw", "rate"], pa.string() if kind == "string" else pa.int32() if kind == "int" else pa.int64()
    rows = annotated.where(F.col("first_level") <= levels[-1].level).select("src", "dst", "first_level").repartition(1)
    out = written(rows.mapInArrow(run, f"id {kind}, label double, level int, raw long, rate double"), "first-levels")
    sums = out.groupBy("level").agg(F.max(F.when(F.col("id").isNull(), F.col("raw"))).alias("edges"), F.count("id").alias("vertices"))
    by = {r.level: (r.edges, r.vertices) for r in sums.collect()}  # one row for each level
    return out.where("id is not null"), [by[lv.level] for lv in levels]


def sketch_coreness(edges: DataFrame, p: SketchParams, n: int | None = None) -> Sketch:
    """Approximate coreness of every vertex of canonical edges; n: how many have edges, where that is known.

    rounds='two': each level writes its sample (the parallel round), then peels it. With nested samples a level carries
    on the last one's table, meets only the newly settled vertices in it, and looks all settled ones up for its own new
    edges alone. rounds='fused' (one-task peel, no pre-peel): a level is one job that samples, peels and writes what it
    settles; its sample is counted on the way by an observation. rounds='auto' (nested samples, no pre-peel): the first levels,
    as many as one task holds the sample of, are one job; the others are rounds of two. Once all vertices are settled
    the samples of what levels remain are empty and are not run. Labels depend neither on it nor on the peeler.
    """
    spark, rounds = edges.sparkSession, Rounds()
    with rounds.counted(spark):
        stored = None
        if n is None and not getattr(edges, "_stored_at", None):
            edges = stored = written(edges, "edges")  # else what makes them runs for the count and again for the table
        n = n if n is not None else degrees(edges).count()
        levels = rate_schedule(n, p)
        if p.accept is None and not p.idle and len(levels) > 1:  # log constants ask for more than most graphs hold
            levels = without_idle(levels, coreness_bound(edges))
        annotated = written(annotate(edges, p, [x.rate for x in levels]), "annotated", "first_level")
        drop_written(*([stored] if stored is not None else []))
        kind = edges.schema["src"].dataType.simpleString()
        one_task = p.peeler == "local" or (p.peeler == "auto" and annotated.count() <= p.max_local_edges)
        fused = p.rounds != "two" and one_task and not p.prepeel
        settled, new, n_settled, n_new, last, samples, space = None, None, 0, 0, None, [], []
        if p.rounds == "auto" and p.sampler == "nested" and p.peeler != "distributed" and not p.prepeel:
            held = {r.first_level: r["count"] for r in annotated.groupBy("first_level").count().collect()}  # one row for each level
            sums = np.cumsum([held.get(lv.level, 0) for lv in levels])
            most = math.inf if p.peeler == "local" else p.max_local_edges
            first = [lv for lv, rows in zip(levels, sums, strict=True) if rows <= most]
            if first:
                settled, sizes = first_levels(annotated, first, p)
                for lv, (size, n_new) in zip(first, sizes, strict=True):
                    before = settled.where(F.col("level") < lv.level) if n_settled else None
                    h = _flagged(level_sample(annotated, lv.level, lv.rate, p).select("src", "dst"), before, n_settled).where(~(F.col("su") & F.col("sv")))
                    samples.append(h.select(F.lit(lv.level).alias("level"), "src", "dst"))
                    space.append((lv.level, lv.rate, size, size))
                    rounds.levels, n_settled = rounds.levels + 1, n_settled + n_new
                levels, fused = levels[len(first) :], False
        for lv in levels:
            if n_settled == n and samples:
                rounds.levels += 1
                space.append((lv.level, lv.rate, 0, 0))
                continue
            if fused or last is None or p.sampler != "nested":
                h = _flagged(level_sample(annotated, lv.level, lv.rate, p).select("src", "dst"), settled, n_settled).where(~(F.col("su") & F.col("sv")))
            else:
                fresh = _flagged(annotated.where(F.col("first_level") == lv.level).select("src", "dst"), settled, n_settled).where(~(F.col("su") & F.col("sv")))
                h = _carried(last, new, n_new).unionByName(fresh)
            seen, took = Observation(), Observation()
            if fused:
                raw = exclusive_local(h.observe(seen, F.count(F.lit(1)).alias("edges")), 1 << 62).select("id", "raw")
            else:
                h = last = written(h, f"sample-{lv.level}")
                size = h.count()  # from the footers of the table just written
                # Nothing below the threshold is settled, so a refinement need not tell those vertices apart.
                raw, least = prepeeled(h, settled, n_settled, lv, p, rounds, math.ceil(lv.accept) if lv.rate < 1 else 0)
            new = written(accepted(raw, lv, p).observe(took, F.count(F.lit(1)).alias("vertices")), f"settled-{lv.level}")
            if fused:
                size = least = seen.get["edges"]
            n_new = took.get["vertices"]
            rounds.levels, n_settled = rounds.levels + 1, n_settled + n_new
            settled = new if settled is None else settled.unionByName(new)
            samples.append(h.select(F.lit(lv.level).alias("level"), "src", "dst"))
            space.append((lv.level, lv.rate, size, least))
    sample = samples[0]
    for s in samples[1:]:
        sample = sample.unionByName(s)
    if settled is None:
        settled = spark.createDataFrame([], f"id {kind}, label double, level int, raw long, rate double")
    return Sketch(settled, sample, space, rounds)


def with_isolated(labels: DataFrame, vertices: DataFrame) -> DataFrame:
    """labels extended by the vertices (id) without any edge: label 0."""
    alone = vertices.select("id").distinct().join(labels.select("id"), "id", "left_anti")
    return labels.unionByName(alone.select("id", F.lit(0.0).alias("label"), F.lit(-1).alias("level"), F.lit(0).cast("long").alias("raw"), F.lit(1.0).alias("rate")))
