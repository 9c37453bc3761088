"""One-pass, insert-only maintenance of the sketch over a stream of edges, and windowed twins.

With nested hashes and inserts only, the state after any prefix equals the batch sketch of that prefix, whatever the
order: settled sets only grow, and an edge that became useless stays useless. So a micro-batch is taken in level by
level. A level is relabelled only if it got a new edge or an earlier level settled a new vertex; `relabel='local'`
updates it around the new edges where only the former holds. Kept edges are a list of tables, one a batch, compacted
now and then. The state is versioned Parquet: one folder per committed batch, and a pointer written last, so that a
replayed batch is recognised and a lost driver resumes from the last commit.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..functions import edge_u52, first_level
from ..operators.peel import _flagged, local_labels
from ..operators.sketch import accepted, prepeeled
from ..params import SketchParams, rate_schedule
from ..runtime import Rounds, drop_written, written
from ..sources import edges_from

#: Batches of kept edges after which they become one table again (and needless edges go).
COMPACT = 8
#: New edges of a level up to which local relabelling walks out from each; with more it peels arrays.
WALK_EDGES = 1000


@dataclass
class BatchCost:
    """What a batch did: new edges, levels relabelled (and how many of them locally), vertices given a label anew."""

    batch: int
    inserted: int
    levels: int
    local_levels: int
    relabelled: int


class StreamingSketch:
    """State: kept edges (src, dst, first_level) that some level still needs, the raw labels and the settled labels by level.

    `n_upper` must be set (the stream's number of vertices is not known in advance). relabel: 'full' peels a touched
    level anew, 'local' walks out from its new edges. `keep` snapshots of past batches can be asked for by `labels(at=)`.
    """

    def __init__(self, spark: SparkSession, p: SketchParams, relabel: str = "full", keep: int = 16):
        if p.n_upper is None:
            raise ValueError("a stream needs n_upper")
        if p.sampler != "nested":
            raise ValueError("a stream needs nested samples")
        if relabel not in ("full", "local"):
            raise ValueError("relabel is 'full' or 'local'")
        self.spark, self.p, self.relabel, self.keep = spark, p, relabel, keep
        self.levels = rate_schedule(p.n_upper, p)
        self.parts: list[DataFrame] = []
        self.raw: list[DataFrame | None] = [None] * len(self.levels)
        self.settled: list[DataFrame | None] = [None] * len(self.levels)
        self.n_settled = [0] * len(self.levels)
        self.last_batch = -1
        self.history: dict[int, list[DataFrame]] = {}
        self.costs: list[BatchCost] = []

    @property
    def edges(self) -> DataFrame | None:
        """The kept edges, or None before the first one."""
        return reduce(DataFrame.unionByName, self.parts) if self.parts else None

    # ------------------------------------------------------------ taking edges in

    def add(self, edges: DataFrame, batch_id: int | None = None) -> None:
        """Insert a batch; one that was committed already is skipped (replay after a restart)."""
        if batch_id is not None and batch_id <= self.last_batch:
            return
        batch, p = batch_id if batch_id is not None else self.last_batch + 1, self.p
        new = edges_from(edges).withColumn("u", edge_u52(F.col("src"), F.col("dst"), p.seed, p.hash))
        new = new.select("src", "dst", first_level(F.col("u"), [x.rate for x in self.levels]).alias("first_level"))
        if self.parts:
            new = new.join(self.edges.select("src", "dst"), ["src", "dst"], "left_anti")
        new = written(new, "stream-new")
        arrived = {r.first_level: r["count"] for r in new.groupBy("first_level").count().collect()}  # one row per level
        if arrived:
            self.parts.append(new)
            self._take(batch, new, arrived)
            if len(self.parts) > COMPACT:
                self._prune()
        else:
            self.costs.append(BatchCost(batch, 0, 0, 0, 0))
        self.last_batch = batch
        self.history[batch] = [s for s in self.settled if s is not None]
        for old in sorted(self.history)[: -self.keep]:
            del self.history[old]

    def _before(self, level: int) -> tuple[DataFrame | None, int]:
        some = [s.select("id") for s in self.settled[:level] if s is not None]
        return (reduce(DataFrame.unionByName, some) if some else None), sum(self.n_settled[:level])

    def sample(self, level: int, edges: DataFrame | None = None) -> DataFrame:
        """The level's sample: hash reached, and not both ends settled by earlier levels."""
        h = (self.edges if edges is None else edges).where(F.col("first_level") <= level).select("src", "dst")
        return _flagged(h, *self._before(level)).where(~(F.col("su") & F.col("sv")))

    def _take(self, batch: int, new: DataFrame, arrived: dict[int, int]) -> None:
        cost, grew = BatchCost(batch, sum(arrived.values()), 0, 0, 0), False
        for lv in self.levels:
            got = any(k <= lv.level for k in arrived)
            if not (grew or got):
                continue
            h = written(self.sample(lv.level), "stream-sample")
            seen, took = Observation(), Observation()
            if self.relabel == "local" and not grew and self.raw[lv.level] is not None and h.count() <= self.p.max_local_edges:
                few = sum(k for at, k in arrived.items() if at <= lv.level) <= WALK_EDGES
                raw, cost.local_levels = locally_relabelled(h, self.sample(lv.level, new) if few else None, self.raw[lv.level]), cost.local_levels + 1
                raw = written(raw.observe(seen, F.count_if("moved").alias("vertices")), "stream-raw").drop("moved")
            else:
                raw, _ = prepeeled(h, *self._before(lv.level), lv, self.p, Rounds())
                raw = written(raw.observe(seen, F.count(F.lit(1)).alias("vertices")), "stream-raw")
            cost.relabelled += seen.get["vertices"]
            drop_written(h)
            before = self.n_settled[lv.level]
            self.raw[lv.level], self.settled[lv.level] = raw, written(accepted(raw, lv, self.p).observe(took, F.count(F.lit(1)).alias("vertices")), f"stream-settled-{lv.level}")
            self.n_settled[lv.level] = took.get["vertices"]
            # Settled sets only grow, so an unchanged number is an unchanged set.
            grew, cost.levels = grew or self.n_settled[lv.level] != before, cost.levels + 1
        self.costs.append(cost)

    def _prune(self) -> None:
        """One table of the kept edges, without those whose ends were both settled before the level that first holds them."""
        when = [s.select("id", "level") for s in self.settled[:-1] if s is not None]
        edges = self.edges
        if when:
            w = reduce(DataFrame.unionByName, when)
            a, b = w.select(F.col("id").alias("src"), F.col("level").alias("x")), w.select(F.col("id").alias("dst"), F.col("level").alias("y"))
            both = edges.join(a, "src", "left").join(b, "dst", "left")
            dead = F.col("x").isNotNull() & F.col("y").isNotNull() & (F.greatest("x", "y") < F.col("first_level"))
            edges = both.where(~dead).select("src", "dst", "first_level")
        old, self.parts = self.parts, [written(edges, "stream-edges")]
        drop_written(*old)

    # ------------------------------------------------------------ reading the state

    def labels(self, at: int | None = None) -> DataFrame:
        """(id, label, level, raw, rate) now, or after the past batch `at`."""
        if at is not None and at not in self.history:
            raise KeyError(f"no snapshot of batch {at}; kept are {sorted(self.history)}")
        some = self.history[at] if at is not None else [s for s in self.settled if s is not None]
        return reduce(DataFrame.unionByName, some) if some else self._nothing("id long, label double, level int, raw long, rate double")

    def _nothing(self, schema: str) -> DataFrame:
        return self.spark.createDataFrame([], schema)

    def space(self) -> list[tuple[int, int]]:
        """(level, edges) of the samples that the state can produce."""
        return [(lv.level, self.sample(lv.level).count()) for lv in self.levels] if self.parts else []

    def save(self, path: str) -> None:
        """Commit the state under its batch id; the pointer is written last."""
        at = f"{path}/batch-{self.last_batch}"
        edges = self.edges if self.parts else self._nothing("src long, dst long, first_level int")
        raws = [r.withColumn("level", F.lit(k)) for k, r in enumerate(self.raw) if r is not None]
        raw = reduce(DataFrame.unionByName, raws) if raws else self._nothing("id long, raw long, level int")
        for name, table in (("edges", edges), ("labels", self.labels()), ("raw", raw)):
            table.write.mode("overwrite").parquet(f"{at}/{name}")
        self.spark.createDataFrame([(self.last_batch,)], "batch long").coalesce(1).write.mode("append").parquet(f"{path}/commits")

    @classmethod
    def load(cls, spark: SparkSession, path: str, p: SketchParams, at: int | None = None, **options) -> StreamingSketch:
        """The state after the last commit, or after the commit `at`."""
        out = cls(spark, p, **options)
        out._resume(path, at)
        return out

    def _resume(self, path: str, at: int | None = None) -> None:
        self.last_batch = at if at is not None else self.spark.read.parquet(f"{path}/commits").agg(F.max("batch")).first()[0]
        edges, labels, raw = (self.spark.read.parquet(f"{path}/batch-{self.last_batch}/{x}") for x in ("edges", "labels", "raw"))
        self.parts = [] if edges.isEmpty() else [edges]
        if self.parts:
            sizes = {r.level: r["count"] for r in labels.groupBy("level").count().collect()}  # one row per level
            self.settled = [labels.where(F.col("level") == lv.level) for lv in self.levels]
            self.raw = [raw.where(F.col("level") == lv.level).drop("level") for lv in self.levels]
            self.n_settled = [sizes.get(lv.level, 0) for lv in self.levels]
        self.history = {self.last_batch: [s for s in self.settled if s is not None]}

    def start(self, stream: DataFrame, checkpoint: str, state: str | None = None, trigger: dict | None = None):
        """Run on a streaming DataFrame (src, dst): every micro-batch is inserted, and committed when `state` is given.

        A state folder with commits is resumed from first, so a new object goes on where a lost one stopped; batches
        that Spark replays are recognised by their number."""
        if state and self.last_batch < 0 and _exists(self.spark, f"{state}/commits"):
            self._resume(state)

        def take(batch: DataFrame, batch_id: int) -> None:
            self.add(batch, batch_id)
            if state:
                self.save(state)

        return stream.writeStream.foreachBatch(take).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def _exists(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)


def locally_relabelled(h: DataFrame, new: DataFrame | None, raw: DataFrame) -> DataFrame:
    """(id, raw, moved) of a level's sample h (src, dst, su, sv) after its edges `new` came in, from the labels before.

    One edge can raise only vertices whose label equals the smaller one of its ends and that are reached from such an
    end over vertices of that label; those with enough neighbours among themselves and above rise by one. Settled
    vertices stand above all labels. Edge by edge, in one task, by walks that end where labels differ. new=None: there
    are so many that nearly all labels are reached again and again; the task peels its sample by arrays instead.
    """
    kind = h.schema["src"].dataType
    edge = lambda df, tag: df.select(F.lit(tag).alias("tag"), "src", "dst", "su", "sv", F.lit(0).cast("long").alias("raw"))
    old = edge(h if new is None else h.join(new.select("src", "dst"), ["src", "dst"], "left_anti"), 0)
    known = raw.select(F.lit(2).alias("tag"), F.col("id").alias("src"), F.col("id").alias("dst"), F.lit(False).alias("su"), F.lit(False).alias("sv"), "raw")
    rows = old.unionByName(known) if new is None else old.unionByName(edge(new, 1)).unionByName(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tag, src, dst, su, sv, value = (np.concatenate(x) for x in zip(*((c.to_numpy(zero_copy_only=False) for c in b.columns) for b in batches), strict=True))
        near: dict = {}
        label: dict = {}

        def join(u, v) -> None:
            near.setdefault(u, []).append(v)
            near.setdefault(v, []).append(u)

        above = 1 << 62
        edges_too = tag != 2
        for ids, fixed in ((src, su), (dst, sv)):
            label.update(dict.fromkeys(ids[edges_too & fixed.astype(bool)].tolist(), above))
        label.update(zip(src[tag == 2].tolist(), value[tag == 2].tolist(), strict=True))
        for u, v in zip(src[tag == 0].tolist(), dst[tag == 0].tolist(), strict=True):
            join(u, v)
        moved = set()
        for u, v in zip(src[tag == 1].tolist(), dst[tag == 1].tolist(), strict=True):
            for x in (u, v):
                if x not in label:
                    label[x] = 0
                    moved.add(x)
            join(u, v)
            k = min(label[u], label[v])
            todo = [x for x in (u, v) if label[x] == k]
            reach = set(todo)
            while todo:
                for y in near[todo.pop()]:
                    if label[y] == k and y not in reach:
                        reach.add(y)
                        todo.append(y)
            count = {x: sum(label[y] > k or y in reach for y in near[x]) for x in reach}
            weak = [x for x, n in count.items() if n <= k]
            while weak:
                x = weak.pop()
                if x not in reach:
                    continue
                reach.discard(x)
                for y in near[x]:
                    if y in reach:
                        count[y] -= 1
                        if count[y] <= k:
                            weak.append(y)
            for x in reach:
                label[x] = k + 1
            moved |= reach
        kept = [(x, n) for x, n in label.items() if n != above]
        yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in kept], b_type), pa.array([n for _, n in kept], pa.int64()), pa.array([x in moved for x, _ in kept], pa.bool_())], ["id", "raw", "moved"])

    def peel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got).combine_chunks()
        both = pa.chunked_array([*t["src"].chunks, *t["dst"].chunks]).combine_chunks().dictionary_encode()
        both = both.combine_chunks() if isinstance(both, pa.ChunkedArray) else both
        code, n, m = both.indices.to_numpy(), len(both.dictionary), t.num_rows
        before, settled = np.full(n, -1, np.int64), np.zeros(n, bool)
        old = t["tag"].to_numpy() == 2
        src, dst = code[:m], code[m:]
        before[src[old]] = t["raw"].to_numpy()[old]
        settled[src[t["su"].to_numpy()]] = True
        settled[dst[t["sv"].to_numpy()]] = True
        label, _ = local_labels(src[~old], dst[~old], n, settled)
        keep = np.flatnonzero(~settled)
        yield pa.RecordBatch.from_arrays([both.dictionary.take(pa.array(keep)), pa.array(label[keep]), pa.array(label[keep] != before[keep])], ["id", "raw", "moved"])

    b_type = pa.string() if kind.simpleString() == "string" else pa.int64()
    return rows.repartition(1).mapInArrow(peel if new is None else run, f"id {kind.simpleString()}, raw long, moved boolean")


# ---------------------------------------------------------------- sources, windows, joins


def read_edge_stream(spark: SparkSession, path: str, schema: str, kind: str = "parquet", late: str | None = None) -> DataFrame:
    """Edges from files, one file a micro-batch. Late edges are valid (order does not matter); late='1 hour' drops them."""
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).format(kind).load(path)
    return s.withWatermark("edge_ts", late) if late else s


def _ends(edges: DataFrame, *more: str) -> DataFrame:
    return edges.select(*more, F.explode(F.array(F.struct(F.col("src").alias("id"), F.col("dst").alias("of")), F.struct(F.col("dst").alias("id"), F.col("src").alias("of")))).alias("e")).select(*more, "e.id", "e.of")


def _slot(width: str, slide: str | None):
    return F.window("edge_ts", width, slide) if slide else F.window("edge_ts", width)


def window_degrees(edges: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    """(start, id, degree) per time window of a table (edge_ts, src, dst): distinct neighbours, exactly, in two steps."""
    pairs = edges.select(_slot(width, slide).alias("w"), F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()
    return _ends(pairs, "w").groupBy("w", "id").agg(F.count(F.lit(1)).alias("degree")).select(F.col("w.start").alias("start"), "id", "degree")


def window_edges(edges: DataFrame, width: str, late: str, slide: str | None = None) -> DataFrame:
    """(start, src, dst): the distinct edges of each window of a stream, kept as state until the watermark passes it.

    Window results that need one more grouping (degrees, cores) take these rows batch by batch, see `run_windows`."""
    s = edges.withWatermark("edge_ts", late).select("edge_ts", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
    return s.groupBy(_slot(width, slide).alias("w"), "src", "dst").agg(F.count(F.lit(1)).alias("times")).select(F.col("w.start").alias("start"), "src", "dst", "times")


def window_contacts(events: DataFrame, width: str, late: str, slide: str | None = None, blocks: int = 1) -> DataFrame:
    """(start, src, dst, times) of each window of a stream (edge_ts, id): src < dst were active in one minute, `times`
    counts the rows of src in minutes that hold dst. Windows begin and end with a minute.

    The state are the events, not their pairs: a window's events are kept by pairs of `blocks` of ids, and the pairs of a
    window are made and counted once, when the watermark passes it. Rows without id only move the watermark."""
    b = F.pmod(F.xxhash64("id"), F.lit(blocks))
    pair = F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda x: F.struct(F.least(b, x).alias("lo"), F.greatest(b, x).alias("hi")))
    s = events.withWatermark("edge_ts", late).select("edge_ts", "id", b.cast("int").alias("b"), F.explode(pair).alias("k"))
    rows = F.collect_list(F.struct(F.unix_micros("edge_ts").alias("at"), "id", "b")).alias("rows")
    kept = s.groupBy(_slot(width, slide).alias("w"), "k.lo", "k.hi").agg(rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                whole, lo, hi = batch["rows"][k].values, batch["lo"][k].as_py(), batch["hi"][k].as_py()
                whole = whole.filter(whole.field("id").is_valid())
                at, ids, block = (whole.field(x).to_numpy(zero_copy_only=False) for x in ("at", "id", "b"))
                for src, dst, times in _contacts(at, ids, block, lo, hi):
                    start = pa.repeat(batch["start"][k], len(src))
                    yield pa.RecordBatch.from_arrays([start, pa.array(src, pa.int64()), pa.array(dst, pa.int64()), pa.array(times, pa.int64())], ["start", "src", "dst", "times"])

    return kept.select(F.col("w.start").alias("start"), "lo", "hi", "rows").mapInArrow(run, "start timestamp, src long, dst long, times long")


#: Pairs that `window_contacts` makes at a time in one task, before they are counted.
CONTACT_PAIRS = 4_000_000


def _contacts(at: np.ndarray, ids: np.ndarray, block: np.ndarray, lo: int, hi: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(src, dst, times) of the pairs between the blocks lo and hi, from the events of both; by ranges of src."""
    if not len(ids):
        return
    names, first, number = np.unique(ids, return_index=True, return_inverse=True)
    block_of, n = block[first], len(names)
    minute = at // 60_000_000
    cell, rows = np.unique((minute - minute.min()) * n + number, return_counts=True)
    slot, who = np.divmod(cell, n)
    partners = np.searchsorted(slot, slot, "right") - np.arange(len(slot)) - 1  # later ones of the same minute
    order = np.argsort(who, kind="stable")
    made, begin = np.cumsum(partners[order]), 0
    ends = np.flatnonzero(np.append(np.diff(who[order]) != 0, True)) + 1  # a src's rows stay together
    while begin < len(order):
        limit = (made[begin - 1] if begin else 0) + CONTACT_PAIRS
        fits = ends[(ends > begin) & (made[ends - 1] <= limit)]
        stop = int(fits[-1]) if len(fits) else int(ends[np.searchsorted(ends, begin, "right")])
        part = order[begin:stop]
        begin, size = stop, partners[part]
        here = np.repeat(part, size)
        there = here + 1 + np.arange(len(here)) - np.repeat(np.cumsum(size) - size, size)
        src, dst = who[here], who[there]
        x, y = block_of[src], block_of[dst]
        inside = ((x == lo) & (y == hi)) | ((x == hi) & (y == lo))
        code, times = src[inside] * n + dst[inside], rows[here[inside]]
        if len(code):
            turn = np.argsort(code, kind="stable")
            code, times = code[turn], times[turn]
            new = np.flatnonzero(np.append(True, code[1:] != code[:-1]))
            src, dst = np.divmod(code[new], n)
            yield names[src], names[dst], np.add.reduceat(times, new)


def session_edges(edges: DataFrame, gap: str, late: str | None = None) -> DataFrame:
    """(start, end, src, dst, times): runs of contacts of a pair without a pause of `gap`; on tables and on streams."""
    s = edges.withWatermark("edge_ts", late) if late else edges
    pair = s.select("edge_ts", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
    return pair.groupBy(F.session_window("edge_ts", gap).alias("w"), "src", "dst").agg(F.count(F.lit(1)).alias("times")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "src", "dst", "times")


def session_contacts(events: DataFrame, gap: str, late: str, blocks: int = 1) -> DataFrame:
    """(start, src, dst, times) of a stream (edge_ts, id): runs of contacts of src < dst without a pause of `gap` (a minute
    at least); a contact is a row of src in a minute that holds dst, at its own time.

    The state are the events, not their pairs: a session of the events of a pair of `blocks` of ids holds the runs of all
    its pairs whole, and they are made once, when the watermark passes it. So it grows until these ids pause for `gap`."""
    span = events.sparkSession.sql(f"SELECT unix_micros(TIMESTAMP_SECONDS(0) + INTERVAL {gap})").first()[0]
    b = F.pmod(F.xxhash64("id"), F.lit(blocks))
    pair = F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda x: F.struct(F.least(b, x).alias("lo"), F.greatest(b, x).alias("hi")))
    s = events.withWatermark("edge_ts", late).select("edge_ts", "id", b.cast("int").alias("b"), F.explode(pair).alias("k"))
    rows = F.collect_list(F.struct(F.unix_micros("edge_ts").alias("at"), "id", "b")).alias("rows")
    kept = s.groupBy(F.session_window("edge_ts", gap).alias("w"), "k.lo", "k.hi").agg(rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                whole, lo, hi = batch["rows"][k].values, batch["lo"][k].as_py(), batch["hi"][k].as_py()
                whole = whole.filter(whole.field("id").is_valid())
                at, ids, block = (whole.field(x).to_numpy(zero_copy_only=False) for x in ("at", "id", "b"))
                for start, src, dst, times in _contact_runs(at, ids, block, lo, hi, span):
                    yield pa.RecordBatch.from_arrays([pa.array(start, pa.timestamp("us", "UTC")), pa.array(src, pa.int64()), pa.array(dst, pa.int64()), pa.array(times, pa.int64())], ["start", "src", "dst", "times"])

    return kept.select("lo", "hi", "rows").mapInArrow(run, "start timestamp, src long, dst long, times long")


def _contact_runs(at: np.ndarray, ids: np.ndarray, block: np.ndarray, lo: int, hi: int, gap: int) -> Iterator[tuple[np.ndarray, ...]]:
    """(start, src, dst, times) of the runs of pairs between the blocks lo and hi; by ranges of src, whose rows stay together."""
    if not len(ids):
        return
    names, first, number = np.unique(ids, return_index=True, return_inverse=True)
    block_of, n = block[first], len(names)
    minute = at // 60_000_000
    key = (minute - minute.min()) * n + number
    cell = np.unique(key)
    slot, who = np.divmod(cell, n)
    mine = np.searchsorted(cell, key)
    partners = np.searchsorted(slot, slot, "right")[mine] - mine - 1  # later ones of the same minute, for each event
    order = np.lexsort((at, number))
    made, begin = np.cumsum(partners[order]), 0
    ends = np.flatnonzero(np.append(np.diff(number[order]) != 0, True)) + 1
    while begin < len(order):
        limit = (made[begin - 1] if begin else 0) + CONTACT_PAIRS
        fits = ends[(ends > begin) & (made[ends - 1] <= limit)]
        stop = int(fits[-1]) if len(fits) else int(ends[np.searchsorted(ends, begin, "right")])
        part = order[begin:stop]
        begin, size = stop, partners[part]
        event = np.repeat(part, size)
        dst = who[mine[event] + 1 + np.arange(len(event)) - np.repeat(np.cumsum(size) - size, size)]
        src = number[event]
        x, y = block_of[src], block_of[dst]
        inside = ((x == lo) & (y == hi)) | ((x == hi) & (y == lo))
        code, time = src[inside] * n + dst[inside], at[event[inside]]
        if len(code):
            turn = np.argsort(code, kind="stable")  # times of a pair ascend already
            code, time = code[turn], time[turn]
            new = np.flatnonzero(np.append(True, (code[1:] != code[:-1]) | (time[1:] - time[:-1] >= gap)))
            src, dst = np.divmod(code[new], n)
            yield time[new], names[src], names[dst], np.diff(np.append(new, len(code)))


def run_windows(stream: DataFrame, path: str, checkpoint: str, mode: str = "append", trigger: dict | None = None):
    """Write a windowed stream to Parquet until the input is drained: windows as the watermark closes them ('append'), or
    the whole result anew with every batch ('complete')."""
    out = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True}))
    if mode == "append":
        return out.format("parquet").option("path", path).start()
    return out.foreachBatch(lambda rows, k: rows.write.mode("overwrite").parquet(path)).start()


def with_dimension(stream: DataFrame, table: DataFrame, key: str) -> DataFrame:
    """Stream-static join: each edge with the row of a dimension table that belongs to its source."""
    return stream.join(table, stream["src"] == table[key])


def matched_edges(left: DataFrame, right: DataFrame, on: str, within: str) -> DataFrame:
    """Stream-stream join to edges (src, dst): rows of both streams with the same key, at most `within` apart.

    left: (on, left_ts, src), right: (on, right_ts, dst). Watermarks of the same length bound the state of either side."""
    a = left.withWatermark("left_ts", within).select(F.col(on).alias("k1"), "left_ts", "src")
    b = right.withWatermark("right_ts", within).select(F.col(on).alias("k2"), "right_ts", "dst")
    near = F.expr(f"k1 = k2 AND right_ts BETWEEN left_ts - INTERVAL {within} AND left_ts + INTERVAL {within}")
    return a.join(b, near).select("src", "dst")


def match_batches(left: DataFrame, right: DataFrame, on: str, within: str, path: str, checkpoint: str, trigger: dict | None = None):
    """`matched_edges` with tables for state: its rows (src, dst) are appended to `path`; returns the running query.

    Both streams are taken by one query. A micro-batch writes its rows and joins them as a table with what came before
    from the other side, so no row is looked up by itself. As in a stream-stream join, rows older than the watermark (the
    smaller of both sides' largest times in earlier batches, less `within`) are dropped, and parts of the state whose
    newest row lies further back than a match reaches are deleted. A batch that is replayed is made anew: its rows and
    its pairs lie in folders of its number. State is kept by this object; a new run starts with a new checkpoint."""
    spark = left.sparkSession
    if left.schema[on].dataType != right.schema[on].dataType:
        raise ValueError(f"{on} has two types")
    span = spark.sql(f"SELECT CAST(unix_micros(TIMESTAMP_SECONDS(0) + INTERVAL {within}) AS BIGINT)").first()[0]
    none = lambda df, c: F.lit(None).cast(df.schema[c].dataType).alias(c)
    a = left.select(F.lit(0).alias("side"), F.col(on).alias("k"), F.unix_micros("left_ts").alias("at"), "src", none(right, "dst"))
    b = right.select(F.lit(1).alias("side"), F.col(on).alias("k"), F.unix_micros("right_ts").alias("at"), none(left, "src"), "dst")
    parts: dict[int, tuple[DataFrame, dict[int, int]]] = {}  # by batch: its rows, the newest time of each side
    newest: dict[int, dict[int, int]] = {}

    def watermark(before: int) -> int | None:
        seen = [max((t[side] for k, t in newest.items() if k < before and side in t), default=None) for side in (0, 1)]
        return None if None in seen else min(seen) - span

    def take(batch: DataFrame, number: int) -> None:
        late = watermark(number)
        times = {side: Observation() for side in (0, 1)}
        rows = batch.observe(times[0], F.max(F.when(F.col("side") == 0, F.col("at"))).alias("at")).observe(times[1], F.max(F.when(F.col("side") == 1, F.col("at"))).alias("at"))
        new = written(rows.where("k is not null and at is not null" + ("" if late is None else f" and at >= {late}")), "join-rows")
        newest[number] = {side: o.get["at"] for side, o in times.items() if o.get["at"] is not None}
        old = [t for k, (t, _) in parts.items() if k < number]
        pairs = _matches(new, new, span)
        if old:
            past = reduce(DataFrame.unionByName, old)
            pairs = pairs.unionByName(_matches(new, past, span)).unionByName(_matches(past, new, span))
        pairs.write.mode("overwrite").parquet(f"{path}/batch={number}")
        parts[number] = (new, newest[number])
        late = watermark(number + 1)
        for k in [k for k, (_, t) in parts.items() if late is not None and max(t.values(), default=late) < late - span]:
            drop_written(parts.pop(k)[0])

    return a.unionByName(b).writeStream.foreachBatch(take).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def _matches(left: DataFrame, right: DataFrame, span: int) -> DataFrame:
    """(src, dst) of the left rows of one table and the right rows of another, at most `span` microseconds apart."""
    a = left.where("side = 0").select("k", F.col("at").alias("x"), "src")
    b = right.where("side = 1").select("k", F.col("at").alias("y"), "dst")
    return a.join(b, "k").where(F.abs(F.col("x") - F.col("y")) <= span).select("src", "dst")


def contact_counts(stream: DataFrame) -> DataFrame:
    """Keyed state: (id, degree so far) for each vertex that a micro-batch touches; the state is its neighbours' set."""
    kind = stream.schema["src"].dataType.simpleString()

    def update(key, frames, state):
        seen = set(state.get[0]) if state.exists else set()
        for f in frames:
            seen.update(f["of"].tolist())
        state.update((sorted(seen),))
        import pandas as pd

        yield pd.DataFrame({"id": [key[0]], "degree": [len(seen)]})

    return _ends(stream).groupBy("id").applyInPandasWithState(update, f"id {kind}, degree long", f"seen array<{kind}>", "update", "NoTimeout")


# ---------------------------------------------------------------- several passes


def multi_pass(source: Callable[[], DataFrame], p: SketchParams, n: int) -> Iterator[tuple[int, DataFrame]]:
    """The sketch by one pass over `source()` (a function giving the edges anew) per level, keeping one sample at a time.

    Yields (level, labels): memory is the largest sample instead of their sum. Peeler, pre-peel and side are p's."""
    settled, n_settled = None, 0
    for lv in rate_schedule(n, p):
        edges = edges_from(source())
        if lv.rate < 1:
            edges = edges.where(edge_u52(F.col("src"), F.col("dst"), p.seed, p.hash) <= int(lv.rate * (1 << 52)))
        h = written(_flagged(edges, settled, n_settled).where(~(F.col("su") & F.col("sv"))), "pass-sample")
        raw, _ = prepeeled(h, settled, n_settled, lv, p, Rounds())
        took = written(accepted(raw, lv, p), "pass")
        drop_written(h)
        settled, n_settled = took if settled is None else settled.unionByName(took), n_settled + took.count()
        yield lv.level, took

