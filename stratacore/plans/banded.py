"""Parameter grids over graphs that are large for one task: edges come to a run in the order of their hashes.

Many tasks number the edges of a graph once and sort them, for each seed, by the first of the grid's rates that draws them
(their band). One task for each seed then reads them band by band and holds, for each parameter set, the sample of its
level alone: edges between settled vertices are dropped as they come. Hashes, schedule, labels and sizes are those of `grid.Run`.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import TWO52, edge_u52
from ..operators.peel import ROW_EDGES, code, pack_lists, packed_degrees, peel_packed, peeled_lists, unpack_labels, vertex_codes
from ..params import Level, SketchParams, label_of, rate_schedule
from ..runtime import drop_written, written

#: Edges that a run sorts by band at once; bands of more come row by row.
GROUP_EDGES = 2_000_000


class BandRun:
    """One sketch whose edges come in the order of their hashes."""

    def __init__(self, n: int, p: SketchParams):
        self.p, self.n, self.seconds = p, n, 0.0
        self.settled, self.label = np.zeros(n, bool), np.zeros(n)
        self.sizes: list[int] = []
        self.held: list[tuple[np.ndarray, np.ndarray]] = []
        self.any_settled = False

    def meet(self, a: np.ndarray, b: np.ndarray) -> None:
        began = time.time()
        if self.any_settled:
            keep = ~(self.settled[a] & self.settled[b])
            a, b = a[keep], b[keep]
        if len(a):
            self.held.append((a, b))
        self.seconds += time.time() - began

    def level(self, lv: Level) -> None:
        """Peel the sample held and settle what the level accepts."""
        began = time.time()
        a, b = (np.concatenate([x[k] for x in self.held]) if self.held else np.zeros(0, np.int32) for k in (0, 1))
        self.held = []
        self.sizes.append(len(a))
        whole = lv.rate >= 1
        top = None if math.isinf(lv.cap) else math.ceil(max(lv.cap, lv.accept))
        who, raw = pinned_cores(a, b, self.settled, 0 if whole else math.ceil(lv.accept), top)
        if len(who):
            values = np.array([label_of(x, lv, self.p) for x in range(int(raw.max()) + 1)])
            self.label[who], self.settled[who], self.any_settled = values[raw], True, True
        self.seconds += time.time() - began
        if not whole:
            self.meet(a, b)


def pinned_cores(a: np.ndarray, b: np.ndarray, settled: np.ndarray, least: int, top: int | None) -> tuple[np.ndarray, np.ndarray]:
    """(vertices, raw labels, clipped at top) of the unsettled vertices of some edges whose raw label is at least `least`;
    settled ones are never removed, so they only add to the degrees of their neighbours."""
    here = None
    if 8 * len(a) < len(settled):
        here, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        a, b, settled = at[: len(a)], at[len(a) :], settled[here]
    n, sa, sb = len(settled), settled[a], settled[b]
    degree = np.bincount(a[~sa], minlength=n) + np.bincount(b[~sb], minlength=n)
    inner = ~(sa | sb)
    a, b = a[inner], b[inner]
    del inner, sa, sb
    while len(a):  # whole fronts while they are large; the rest falls by neighbour lists
        weak = degree < least
        gone = weak[a] | weak[b]
        fell = int(gone.sum())
        if fell:
            degree -= np.bincount(a[gone], minlength=n) + np.bincount(b[gone], minlength=n)
            a, b = a[~gone], b[~gone]
        if 20 * fell < len(a):
            break
    some = degree >= max(least, 1)
    some[a], some[b] = True, True
    who = np.flatnonzero(some & ~settled)
    number = np.zeros(n, np.int64)
    number[who] = np.arange(len(who))
    x, y = number[a], number[b]
    del a, b, number
    arcs = np.concatenate([x << 32 | y, y << 32 | x])
    del x, y
    arcs.sort()
    start = np.concatenate([[0], np.cumsum(np.bincount(arcs >> 32, minlength=len(who)))])
    nbr = (arcs & 0xFFFFFFFF).astype(np.int32)
    del arcs
    raw, _ = peeled_lists(start, nbr, np.zeros(len(who), bool), degree[who], least, top)
    found = raw >= least
    who, raw = who[found], raw[found]
    return (who if here is None else here[who]), raw


def bands(n: int, grid: list[SketchParams]) -> tuple[np.ndarray, list[list[tuple[int, Level]]]]:
    """(the largest hash of each rate below 1, ascending; for each parameter set its levels with the place of their rate)."""
    schedules = [rate_schedule(n, p) for p in grid]
    bound = np.unique(np.array([int(lv.rate * TWO52) for s in schedules for lv in s if lv.rate < 1], np.int64))
    place = lambda lv: len(bound) if lv.rate >= 1 else int(np.searchsorted(bound, int(lv.rate * TWO52)))
    return bound, [[(place(lv), lv) for lv in s] for s in schedules]


def band_groups(bound: np.ndarray, m: int) -> list[tuple[int, int]]:
    """Bands first..last of each group: as many as hold GROUP_EDGES of m edges with even hashes, one at least."""
    ends, out, first, before = [*bound.tolist(), TWO52], [], 0, 0
    for k, end in enumerate(ends):
        if k > first and (end - before) / TWO52 * m > GROUP_EDGES:
            out.append((first, k - 1))
            first, before = k, ends[k - 1]
    return [*out, (first, len(ends) - 1)]


def banded_report(edges: DataFrame, m: int, name: str, grid: list[SketchParams], seeds: tuple[int, ...], errors: bool, schema: str, points: tuple[int, ...]) -> DataFrame | None:
    """The rows of `grid.report` for the written edges of a graph; None where its vertices get no codes."""
    ids, codes = vertex_codes(edges)
    drop_written(ids)
    if codes is None:
        return None
    n = len(codes)
    bound, levels = bands(n, grid)
    groups = band_groups(bound, m)
    firsts = np.array([first for first, _ in groups])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0

        def packed_rows() -> Iterator[pa.RecordBatch]:
            a, b, *hashes = (np.concatenate([x[k] for x in held]) for k in range(2 + len(seeds)))
            a, b = (np.searchsorted(codes, x).astype(np.int32) for x in (a, b))
            empty = [pa.nulls(1, pa.binary())] * 3
            if errors:
                lists = [pa.array([x.tobytes()], pa.binary()) for x in pack_lists(a, b)]
                yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int32()), pa.nulls(1, pa.int32()), *empty, *lists], names)
            for unit, u in enumerate(hashes):
                band = np.searchsorted(bound, u).astype(np.uint16)
                order = np.argsort(band, kind="stable")
                band, x, y = band[order], a[order], b[order]
                cuts = [*np.searchsorted(band, firsts).tolist(), len(band)]
                for k in range(len(groups)):
                    s = slice(cuts[k], cuts[k + 1])
                    if cuts[k] < cuts[k + 1]:
                        own = [pa.array([z[s].tobytes()], pa.binary()) for z in (x, y, band)]
                        yield pa.RecordBatch.from_arrays([pa.array([unit], pa.int32()), pa.array([k], pa.int32()), *own, *empty], names)

        for batch in batches:
            held.append([c.to_numpy() for c in batch.columns])
            rows += batch.num_rows
            if rows >= ROW_EDGES:
                yield from packed_rows()
                held, rows = [], 0
        if rows:
            yield from packed_rows()

    names = ["unit", "part", "a", "b", "band", "at", "count", "nbr"]
    hashed = edges.select(code("src").alias("a"), code("dst").alias("b"), *[edge_u52(F.col("src"), F.col("dst"), s, grid[0].hash).alias(f"u{k}") for k, s in enumerate(seeds)])
    packed = written(hashed.mapInArrow(pack, "unit int, part int, a binary, b binary, band binary, at binary, count binary, nbr binary"), "bands")
    sent = packed.where("unit is not null").select("unit", "part", "a", "b", "band")
    if errors:
        lists = packed.where("unit is null").select("at", "count", "nbr")
        exact = peel_packed(lists, packed_degrees(lists, n), n, None)
        units = F.explode(F.array(*[F.lit(k) for k in range(len(seeds))]))
        # The exact labels lead, by vertex number.
        whole = exact.coalesce(1).mapInArrow(lambda batches: unpack_labels(batches, n), "a binary").select(units.alias("unit"), F.lit(-1).alias("part"), "a", F.lit(None).cast("binary").alias("b"), F.lit(None).cast("binary").alias("band"))
        sent = sent.unionByName(whole)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs, todo, exact, held, now, seed = [BandRun(n, p) for p in grid], [list(x) for x in levels], None, [], None, None

        def advance(band: int) -> None:
            """Run the levels whose edges have all come: those of earlier bands."""
            for r, rest in zip(runs, todo, strict=True):
                while rest and rest[0][0] < band:
                    r.level(rest.pop(0)[1])

        def close() -> None:
            a, b, band = (np.concatenate([x[k] for x in held]) for k in range(3))
            held.clear()
            order = np.argsort(band, kind="stable")
            a, b, band = a[order], b[order], band[order]
            for k in range(groups[now][0], groups[now][1] + 1):
                s = slice(*np.searchsorted(band, [k, k + 1]))
                if s.start < s.stop:
                    advance(k)
                    for r in runs:
                        r.meet(a[s], b[s])

        for batch in batches:
            for unit, part, *row in zip(*batch.columns, strict=True):
                seed, part = seeds[unit.as_py()], part.as_py()
                if part < 0:
                    exact = np.frombuffer(row[0].as_buffer(), np.int32).copy()
                    continue
                if held and part != now:
                    close()
                now = part
                a, b, band = (np.frombuffer(x.as_buffer(), t) for x, t in zip(row, (np.int32, np.int32, np.uint16), strict=True))
                if groups[part][0] < groups[part][1]:
                    held.append((a.copy(), b.copy(), band.copy()))
                    continue
                advance(groups[part][0])
                for r in runs:
                    r.meet(a if r.any_settled else a.copy(), b if r.any_settled else b.copy())
        if seed is None:
            return
        if held:
            close()
        advance(len(bound) + 1)
        high = exact >= 5 if errors else np.zeros(n, bool)
        out = []
        for p, r in zip(grid, runs, strict=True):
            err = np.abs(r.label[high] - exact[high]) / exact[high] if errors else None
            at = [float(x) for x in np.percentile(err, points)] if high.any() else [None] * len(points)
            out.append((name, seed, float(p.threshold(n)), p.growth, p.eps, n, m, len(r.sizes), max(r.sizes), sum(r.sizes), max(r.sizes) / m, sum(r.sizes) / m, max(r.sizes) / n, *at, r.seconds))
        yield from pa.Table.from_pylist([dict(zip(fields.names, x, strict=True)) for x in out], fields).to_batches()

    types = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64()}
    fields = pa.schema([(c, types[t]) for c, t in (x.split() for x in schema.split(","))])
    rows = written(sent.repartitionById(len(seeds), F.col("unit")).sortWithinPartitions("part").mapInArrow(run, schema), "report")
    drop_written(packed)
    return rows
