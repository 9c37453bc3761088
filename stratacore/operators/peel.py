"""Peeling: exact and exclusive core labels, locally, in waves, or by refinement across the cluster.

Exclusive labels keep the settled vertices in the graph for ever: they are never removed and get no label. They are
the largest fixpoint of "h-index of the neighbours' values" with settled vertices pinned at infinity, which is what
the distributed form computes; capped at c, all values may be clipped at c.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..runtime import BROADCAST_ROWS, Rounds, bucketed, drop_written, fits_broadcast, shared_dir, written
from ..sources import arcs, degrees, dense_ids

PINNED = 1 << 40
#: Edges that one task may peel: about 100 bytes each at the peak of the array form, 1 GB in all.
LOCAL_EDGES = 10_000_000
#: The same 1 GB with vertices as numbers: 56 bytes an edge at the peak.
NUMBERED_EDGES = 20_000_000
#: With neighbour lists packed beforehand by many tasks: 8 bytes an edge and some arrays of the vertices.
PACKED_EDGES = 100_000_000
#: Vertices whose codes come to the driver and go to the tasks, 8 bytes each.
CODED_VERTICES = 8_000_000
#: Edges of a packed row, whose lists are 8 bytes an edge.
ROW_EDGES = 500_000
#: Neighbours that a peel looks up at once.
SPAN = 8_000_000
#: Arcs of a bucket below which a refinement takes fewer buckets than a shuffle has partitions.
BUCKET_ARCS = 50_000


# ---------------------------------------------------------------- one task


def local_labels(src: np.ndarray, dst: np.ndarray, n: int, settled: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Labels and removal order of vertices 0..n-1; settled ones get -1. Peels whole fronts with array operations."""
    ends = np.concatenate([src, dst])
    order = np.argsort(ends, kind="stable")
    nbr = np.concatenate([dst, src])[order]
    start = np.concatenate([[0], np.cumsum(np.bincount(ends, minlength=n))])
    del ends, order
    return peeled_lists(start, nbr, settled)


def peeled_lists(start: np.ndarray, nbr: np.ndarray, settled: np.ndarray, degree: np.ndarray | None = None, floor: int = 0, top: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """`local_labels` of neighbour lists: those of vertex v are nbr[start[v] : start[v + 1]]. degree: with neighbours that
    no list has and that are never removed. Labels below floor are not told apart (floor - 1), labels from top on are top."""
    n = len(settled)
    degree = np.diff(start) if degree is None else degree
    label, turn = np.full(n, -1, np.int64), np.full(n, -1, np.int64)
    alive = ~settled
    level, step = max(0, floor - 1), 0
    rest = np.flatnonzero(alive)
    while len(rest):
        level = max(level, int(degree[rest].min()))
        if top is not None and level >= top:
            label[rest], turn[rest] = top, step
            break
        front = rest[degree[rest] <= level]
        while len(front):
            label[front], turn[front], alive[front] = level, step, False
            step += 1
            spans = np.cumsum(start[front + 1] - start[front])
            if spans[-1] > max(n // 4, 1):  # counted over all vertices, some lists at a time
                times = np.zeros(n, np.int64)
                for part in np.split(front, np.searchsorted(spans, np.arange(SPAN, spans[-1], SPAN))):
                    hit = nbr[degree_spans(start, part)]
                    times += np.bincount(hit[alive[hit]], minlength=n)
                touched = np.flatnonzero(times)
                times = times[touched]
            else:
                hit = nbr[degree_spans(start, front)]
                touched, times = np.unique(hit[alive[hit]], return_counts=True)
            if not len(touched):
                break
            degree[touched] -= times
            front = touched[degree[touched] <= level]
        rest = rest[alive[rest]]
    return label, turn


def degree_spans(start: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Positions of all neighbours of some rows."""
    n = start[rows + 1] - start[rows]
    ends = np.cumsum(n)
    return np.repeat(start[rows] - ends + n, n) + np.arange(ends[-1] if len(ends) else 0)


def exclusive_local(edges: DataFrame, most_edges: int = LOCAL_EDGES) -> DataFrame:
    """(id, raw, step) of the unsettled vertices of (src, dst, su, sv), peeled in one task (the single-machine round)."""
    kind = edges.schema["src"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = list(batches)
        if not sum(b.num_rows for b in got):
            return
        t = pa.Table.from_batches(got).combine_chunks()
        if t.num_rows > most_edges:
            raise MemoryError(f"{t.num_rows} edges exceed max_local_edges={most_edges}; use the distributed peeler")
        both = pa.chunked_array([*t["src"].chunks, *t["dst"].chunks]).combine_chunks().dictionary_encode()
        both = both.combine_chunks() if isinstance(both, pa.ChunkedArray) else both
        code, m, n = both.indices.to_numpy(), t.num_rows, len(both.dictionary)
        settled = np.zeros(n, bool)
        settled[code[:m][t["su"].to_numpy()]] = True
        settled[code[m:][t["sv"].to_numpy()]] = True
        label, turn = local_labels(code[:m], code[m:], n, settled)
        keep = np.flatnonzero(~settled)
        yield pa.RecordBatch.from_arrays([both.dictionary.take(pa.array(keep)), pa.array(label[keep]), pa.array(turn[keep])], ["id", "raw", "step"])

    return edges.select("src", "dst", "su", "sv").repartition(1).mapInArrow(run, f"id {kind}, raw long, step long")


# ---------------------------------------------------------------- across the cluster


def exclusive_refined(edges: DataFrame, cap: int | None = None, rounds: Rounds | None = None, floor: int = 0, size: int | None = None) -> DataFrame:
    """(id, raw) of the unsettled vertices of (src, dst, su, sv), by sweeps of clipped h-indices until none changes.

    Arcs are laid out once. While the vertices may be broadcast, by receiver: a sweep sends the values to the arcs and
    shuffles nothing (a hub has fewer arcs than there are vertices). With more of them by sender: a sweep shuffles the
    values to the arcs and then only (vertex, value) rows, which are combined per distinct value before that shuffle, so
    a hub receives at most one row per value and map task. A sweep's values are a table, whose changes are counted as it
    is written; the one before the last is deleted. The number of sweeps is that of the graph (half the length of its
    longest chain at worst); nothing stops them early.

    floor: vertices below it are left out, and count for nothing as soon as they fall below (no core from there on needs
    them). size: the number of edges, where the caller knows it.
    """
    rounds, spark = rounds or Rounds(), edges.sparkSession
    with rounds.counted(spark):
        top = F.lit(cap if cap is not None else PINNED)
        side = F.explode(F.array(F.struct(F.col("src").alias("to"), F.col("dst").alias("of"), F.col("su").alias("fixed")), F.struct(F.col("dst").alias("to"), F.col("src").alias("of"), F.col("sv").alias("fixed"))))
        buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
        buckets = buckets if size is None else min(buckets, 1 + 2 * size // BUCKET_ARCS)
        both = bucketed(edges.select(side.alias("a")).select("a.*"), "arcs", "to", buckets)
        counted = Observation()
        first = both.groupBy(F.col("to").alias("id")).agg(F.max("fixed").alias("fixed"), F.count(F.lit(1)).alias("degree"))
        first = written(first.observe(counted, F.count(F.lit(1)).alias("all"), F.count_if(~F.col("fixed") & (F.col("degree") >= floor)).alias("moving")), "degrees")
        pinned = first.where("fixed").select("id", F.lit(PINNED).alias("value"))
        values = first.where(~F.col("fixed") & (F.col("degree") >= floor)).select("id", F.least("degree", top).alias("value"))
        few, moving = counted.get["all"] <= BROADCAST_ROWS, both.where("not fixed").select("to", "of")
        sent_to = F.broadcast if few else lambda df: df
        if not few:
            moving = bucketed(moving, "arcs", "of", buckets)
            drop_written(both)
        n, last = counted.get["moving"], None
        while n:
            known = sent_to(values.unionByName(pinned))
            sent = moving.join(known, moving["of"] == known["id"]).groupBy("to", F.least("value", top).alias("value")).agg(F.count(F.lit(1)).alias("k"))
            fall = Window.partitionBy("to").orderBy(F.desc("value")).rowsBetween(Window.unboundedPreceding, 0)
            best = sent.withColumn("at_least", F.sum("k").over(fall)).groupBy("to").agg(F.max(F.least("value", "at_least")).alias("next"))
            old = known if few else values
            new = best.join(old, best["to"] == old["id"]).where(F.col("next") >= floor).select("id", F.least("value", "next").alias("value"), F.col("value").alias("old"))
            seen = Observation()
            new = written(new.observe(seen, F.count(F.lit(1)).alias("rows"), F.count_if(F.col("value") < F.col("old")).alias("fell")), "values")
            drop_written(*([last] if last is not None else []))
            last, values, rounds.sweeps = new, new.select("id", "value"), rounds.sweeps + 1
            if seen.get["rows"] == n and not seen.get["fell"]:
                break
            n = seen.get["rows"]
        drop_written(both if few else moving)
    return values.select("id", F.col("value").alias("raw"))


def _flagged(edges: DataFrame, settled: DataFrame | None, rows: int | None = None) -> DataFrame:
    """edges with su, sv: whether an end is in the settled (id) table. Broadcast only behind a row check.

    rows: the number of settled ids where the caller knows it (and knows that they are distinct)."""
    if settled is None:
        return edges.withColumns({"su": F.lit(False), "sv": F.lit(False)})
    ids = settled.select("id") if rows is not None else settled.select("id").distinct()
    small = rows <= BROADCAST_ROWS if rows is not None else fits_broadcast(ids)
    ids = F.broadcast(ids) if small else ids
    one = edges.join(ids.select(F.col("id").alias("src"), F.lit(True).alias("_u")), "src", "left")
    both = one.join(ids.select(F.col("id").alias("dst"), F.lit(True).alias("_v")), "dst", "left")
    return both.select(*edges.columns, F.coalesce("_u", F.lit(False)).alias("su"), F.coalesce("_v", F.lit(False)).alias("sv"))


def exclusive_labels(edges: DataFrame, settled: DataFrame | None = None, cap: int | None = None, method: str = "distributed", rounds: Rounds | None = None) -> DataFrame:
    """(id, label) of the vertices outside `settled`; with cap, min(label, cap). Edges inside `settled` do not count.
    method: 'local' (one task), 'distributed', or 'auto': local where a count shows that one task may hold the edges."""
    flagged = _flagged(edges, settled).where(~(F.col("su") & F.col("sv")))
    if method == "auto":
        flagged = written(flagged, "flagged")  # counted from its footers
        method = "local" if flagged.count() <= LOCAL_EDGES else "distributed"
    if method == "local":
        out = exclusive_local(flagged)
        raw = F.col("raw") if cap is None else F.least("raw", F.lit(cap))
        return out.select("id", raw.alias("label"))
    return exclusive_refined(flagged, cap, rounds).select("id", F.col("raw").alias("label"))


def exact_coreness(edges: DataFrame, method: str = "refine", rounds: Rounds | None = None) -> DataFrame:
    """(id, coreness) by 'waves' (strip degree <= k for k = 0, 1, ..), 'refine' (h-index sweeps), 'local' (one task), or
    'auto': local where a count shows that one task may hold the edges (from LOCAL_EDGES to NUMBERED_EDGES with vertices
    as numbers of four bytes, to PACKED_EDGES as packed lists of such numbers), else refine."""
    if method == "waves":
        return _waves(edges, rounds or Rounds())
    if method == "auto":
        edges = written(edges, "edges")  # counted from its footers, and not computed again by the peel
        m = edges.count()
        if LOCAL_EDGES < m <= NUMBERED_EDGES:
            return _numbered_coreness(edges)
        if NUMBERED_EDGES < m <= PACKED_EDGES:
            ids, codes = vertex_codes(edges)
            if codes is not None:
                labels = packed_coreness(edges.select(code("src").alias("a"), code("dst").alias("b")), len(codes), codes)
                return ids.join(labels.withColumnRenamed("id", "n"), F.col("code") == F.col("n")).select(F.col("key").alias("id"), "coreness")
            edges, ids = numbered(edges)
            labels = packed_coreness(edges.select("a", "b"), ids.count())
            return ids.join(labels.withColumnRenamed("id", "n"), F.col("id") == F.col("n")).select(F.col("key").alias("id"), "coreness")
        method = "local" if m <= LOCAL_EDGES else "refine"
    out = exclusive_labels(edges, None, None, "local" if method == "local" else "distributed", rounds)
    return out.select("id", F.col("label").alias("coreness"))


def coreness_bound(edges: DataFrame) -> int:
    """The largest h such that h vertices have degree >= h: no core is denser. One row for each distinct degree is
    ranked, fewer than the root of twice the edges."""
    fall = Window.orderBy(F.desc("degree")).rowsBetween(Window.unboundedPreceding, 0)
    sizes = degrees(edges).groupBy("degree").agg(F.count(F.lit(1)).alias("k")).withColumn("at_least", F.sum("k").over(fall))
    return sizes.agg(F.max(F.least("degree", "at_least"))).first()[0] or 0


def _numbered_coreness(edges: DataFrame) -> DataFrame:
    """(id, coreness), peeled in one task that holds vertex numbers instead of ids."""
    edges, ids = numbered(edges)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
        if not sum(len(a) for a, _ in got):
            return
        src, dst = (np.concatenate([x[k] for x in got]) for k in (0, 1))
        del got
        n = max(int(src.max()), int(dst.max())) + 1
        label, _ = local_labels(src, dst, n, np.zeros(n, bool))
        for at in range(0, n, 1 << 16):
            part = label[at : at + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(at, at + len(part), dtype=np.int64)), pa.array(part)], ["n", "coreness"])

    labels = edges.select("a", "b").repartition(1).mapInArrow(run, "n long, coreness long")
    return ids.join(labels, ids["id"] == labels["n"]).select(F.col("key").alias("id"), "coreness")


def code(end: str) -> Column:
    """An id as a long: strings by their hash, of which `vertex_codes` finds out whether it tells them apart."""
    return F.when(F.typeof(end) == "string", F.xxhash64(end)).otherwise(F.expr(f"try_cast({end} as bigint)"))


def vertex_codes(edges: DataFrame) -> tuple[DataFrame, np.ndarray | None]:
    """((code, key) of the vertices, their codes in ascending order): a vertex's number is the place of its code, which
    any task finds without a join. No codes where there are more than CODED_VERTICES or two ids have the same one."""
    ids = edges.select(F.explode(F.array("src", "dst")).alias("key")).distinct()
    ids = written(ids.select(code("key").alias("code"), "key"), "codes")
    if ids.count() > CODED_VERTICES:
        return ids, None
    codes = np.sort(ids.select("code").toArrow()["code"].to_numpy())
    return ids, None if (codes[1:] == codes[:-1]).any() else codes


def packed_coreness(edges: DataFrame, n: int, codes: np.ndarray | None = None) -> DataFrame:
    """(id, coreness) of edges (a, b) between the numbers 0..n-1, peeled in one task that holds nothing but neighbour lists.
    codes: a, b and id are codes of `vertex_codes` instead.

    Many tasks sort and pack the lists of ROW_EDGES edges each (a row: vertices, their counts, the neighbours); one adds
    the counts up, whose sums come to the driver (4 bytes a vertex) and tell the last task where each row's parts go.
    """

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0

        def row() -> pa.RecordBatch:
            a, b = (np.concatenate([x[k] for x in held]) for k in (0, 1))
            a, b = (x if codes is None else np.searchsorted(codes, x) for x in (a, b))
            return pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in pack_lists(a, b)], ["at", "count", "nbr"])

        for b in batches:
            held.append((b.column(0).to_numpy(), b.column(1).to_numpy()))
            rows += b.num_rows
            if rows >= ROW_EDGES:
                yield row()
                held, rows = [], 0
        if rows:
            yield row()

    packed = written(edges.select("a", "b").mapInArrow(pack, "at binary, count binary, nbr binary"), "packed")
    labels = peel_packed(packed, packed_degrees(packed, n), n, codes)
    drop_written(packed)
    return labels


def pack_lists(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(vertices, how many neighbours each has, the neighbours) of the arcs of some edges."""
    a, b = a.astype(np.uint64), b.astype(np.uint64)
    arcs = np.sort(np.concatenate([a << np.uint64(32) | b, b << np.uint64(32) | a]))
    at, count = np.unique((arcs >> np.uint64(32)).astype(np.int32), return_counts=True)
    return at, count.astype(np.int32), (arcs & np.uint64(0xFFFFFFFF)).astype(np.int32)


def packed_degrees(packed: DataFrame, n: int) -> np.ndarray:
    """The degrees of the numbers 0..n-1, from the counts of packed rows."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        degree = np.zeros(n, np.int32)
        for b in batches:
            for at, count in zip(b.column(0), b.column(1), strict=True):
                degree[np.frombuffer(at.as_buffer(), np.int32)] += np.frombuffer(count.as_buffer(), np.int32)
        yield pa.RecordBatch.from_arrays([pa.array([degree.tobytes()], pa.binary())], ["degree"])

    # Few rows, each of megabytes: they are sent row by row.
    return np.frombuffer(packed.select("at", "count").coalesce(1).mapInArrow(add, "degree binary").first()[0], np.int32)


def peel_packed(packed: DataFrame, degree: np.ndarray, n: int, codes: np.ndarray | None) -> DataFrame:
    """(id, coreness) of packed rows (at, count, nbr), peeled in one task; id: a number, or its code where codes are given."""

    def peel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        start = np.concatenate([[0], np.cumsum(degree, dtype=np.int64)])
        nbr, free = np.empty(start[-1], np.int32), start[:-1].copy()
        for b in batches:
            for row in zip(*b.columns, strict=True):
                at, count, part = (np.frombuffer(x.as_buffer(), np.int32) for x in row)
                ends = np.cumsum(count, dtype=np.int64)
                nbr[np.repeat(free[at] - ends + count, count) + np.arange(len(part))] = part
                free[at] += count
        label, _ = peeled_lists(start, nbr, np.zeros(n, bool))
        for at in range(0, n, 1 << 16):
            part = label[at : at + (1 << 16)]
            who = np.arange(at, at + len(part), dtype=np.int64) if codes is None else codes[at : at + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(who), pa.array(part)], ["id", "coreness"])

    return written(packed.coalesce(1).mapInArrow(peel, "id long, coreness long"), "coreness")


def unpack_labels(batches: Iterator[pa.RecordBatch], n: int) -> Iterator[pa.RecordBatch]:
    """All (id, coreness) as one row: four bytes for each of the numbers 0..n-1."""
    label = np.zeros(n, np.int32)
    for b in batches:
        label[b.column(0).to_numpy()] = b.column(1).to_numpy()
    yield pa.RecordBatch.from_arrays([pa.array([label.tobytes()], pa.binary())], ["a"])


def numbered(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(edges with a, b: the consecutive numbers (int) of their ends; (id, key) of the numbers)."""
    ids = dense_ids(edges.select(F.explode(F.array("src", "dst")).alias("key")))
    number = F.col("id").cast("int")
    ends = [ids.select(F.col("key").alias(end), number.alias(name)) for end, name in (("src", "a"), ("dst", "b"))]
    ends = [F.broadcast(x) for x in ends] if fits_broadcast(ids) else ends
    return edges.join(ends[0], "src").join(ends[1], "dst"), ids


def strip_below(edges: DataFrame, least: int, settled: DataFrame | None = None, rounds: Rounds | None = None) -> tuple[DataFrame, DataFrame]:
    """Remove vertices of degree < least again and again (settled ones stay); returns (edges left, (id, wave) removed)."""
    shared_dir(edges.sparkSession)
    gone, wave, rounds = None, 0, rounds or Rounds()
    with rounds.counted(edges.sparkSession):
        while True:
            weak = degrees(edges).where(F.col("degree") < least).select("id")
            if settled is not None:
                weak = weak.join(settled.select("id"), "id", "left_anti")
            weak = written(weak.select("id", F.lit(wave).alias("wave")), "weak")
            rounds.waves += 1
            if weak.isEmpty():
                return edges, gone if gone is not None else weak
            gone, wave = weak if gone is None else gone.unionByName(weak), wave + 1
            edges = written(edges.join(weak, edges["src"] == weak["id"], "left_anti").join(weak, edges["dst"] == weak["id"], "left_anti"), "left-edges")


def _waves(edges: DataFrame, rounds: Rounds) -> DataFrame:
    """Coreness k - 1 for what falls when the least degree becomes k; cores that nothing leaves are jumped over."""
    return _wave_order(edges, rounds).select("id", "coreness")


def _wave_order(edges: DataFrame, rounds: Rounds) -> DataFrame:
    """(id, coreness, step): removal by waves; vertices that lose their last edge in a cascade fall with its last wave."""
    out, left, step = None, written(edges, "edges"), 0
    while not left.isEmpty():
        least = degrees(left).agg(F.min("degree")).first()[0]
        before = left
        left, gone = strip_below(left, least + 1, rounds=rounds)
        lost = degrees(before).select("id").join(gone.select("id"), "id", "left_anti").join(degrees(left).select("id"), "id", "left_anti")
        last = gone.agg(F.max("wave")).first()[0]
        part = gone.unionByName(lost.withColumn("wave", F.lit(last + 1)))
        part = written(part.select("id", F.lit(least).cast("long").alias("coreness"), (F.lit(step).cast("long") + F.col("wave")).alias("step")), "wave")
        out, step = part if out is None else out.unionByName(part), step + last + 2
    return out if out is not None else degrees(edges).select("id", F.lit(0).cast("long").alias("coreness"), F.lit(0).cast("long").alias("step"))


def k_core(edges: DataFrame, k: int) -> DataFrame:
    """Edges of the maximal subgraph in which every vertex has degree >= k."""
    return strip_below(edges, k)[0]


def prepeel_labels(edges: DataFrame, least: int = 3, settled: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(edges left, (id, label)): waves for degree <= 0, 1, .. least - 1 that record the label of what falls."""
    out, left = None, edges
    for k in range(1, least + 1):
        before = left
        left, gone = strip_below(left, k, settled)
        lost = degrees(before).select("id").join(degrees(left).select("id"), "id", "left_anti")
        if settled is not None:
            lost = lost.join(settled.select("id"), "id", "left_anti")
        part = written(gone.select("id").unionByName(lost).distinct().withColumn("label", F.lit(k - 1).cast("long")), "prepeel")
        out = part if out is None else out.unionByName(part)
    return left, out


def h_sweep(edges: DataFrame) -> DataFrame:
    """(id, h): one sweep of the refinement, the h-index of each vertex's neighbour degrees."""
    d = degrees(edges)
    seen = arcs(edges).join(d, F.col("dst") == d["id"]).groupBy("src", "degree").agg(F.count(F.lit(1)).alias("k"))
    fall = Window.partitionBy("src").orderBy(F.desc("degree")).rowsBetween(Window.unboundedPreceding, 0)
    return seen.withColumn("s", F.sum("k").over(fall)).groupBy(F.col("src").alias("id")).agg(F.max(F.least("degree", "s")).alias("h"))
