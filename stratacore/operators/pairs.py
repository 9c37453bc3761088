"""Members that share a group, for groups whose pairs are too many to be shuffled.

A member travels as one row with the numbers of its groups. Members are dealt to blocks, and a task holds two of them
(three for triangles): each group of the second block is a row of bits over its members, so that the members sharing a
group with one of the first block are the union of a few such rows. Pairs come out distinct, and only the members are
shuffled, once for each block.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from itertools import combinations_with_replacement

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..runtime import fits_broadcast, written
from ..sources import dense_ids

#: Pairs, counted group by group, up to which a join and a distinct make them.
PAIR_ROWS = 20_000_000
#: Members of a block, bytes of a block's bit rows at a time, and of the rows that are united at a time.
BLOCK, STRIP_BYTES, UNION_BYTES = 8192, 64 << 20, 2 << 20
#: Members below which a block is not divided for the sake of more tasks.
LEAST_BLOCK = 1024


def pair_count(one: DataFrame, group: list[str]) -> int:
    """Pairs of members that the groups of distinct rows make, each group's counted for itself."""
    m = F.col("members")
    sizes = one.groupBy(*group).agg(F.count(F.lit(1)).alias("members"))
    return sizes.agg(F.sum(m * (m - 1) / 2)).first()[0] or 0


def member_sets(one: DataFrame, group: list[str], member: str) -> DataFrame:
    """(id, slots): the numbers of each member's groups, from distinct rows without nulls; members are longs."""
    groups = dense_ids(one.select(F.struct(*group).alias("key"))).select(F.col("id").cast("int").alias("slot"), "key")
    groups = F.broadcast(groups) if fits_broadcast(groups) else groups
    slots = one.select(F.col(member).alias("id"), F.struct(*group).alias("key")).join(groups, "key")
    return written(slots.groupBy("id").agg(F.collect_list("slot").alias("slots")), "member-sets")


class Members:
    """A block's members: ids, and their group numbers one after the other."""

    def __init__(self, ids: np.ndarray, size: np.ndarray, slots: np.ndarray):
        order = np.argsort(ids)
        start = np.cumsum(size) - size
        self.ids, self.size = ids[order], size[order]
        self.slots = slots[_spans(start[order], self.size)]


def _spans(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    ends = np.cumsum(size)
    return np.repeat(start - ends + size, size) + np.arange(ends[-1] if len(ends) else 0)


def sharing(a: Members, b: Members) -> Iterator[tuple[np.ndarray, int, np.ndarray]]:
    """(rows of a, first member of b, bits): for rows of a with a group of b, the members of b that share one."""
    groups = np.unique(b.slots)
    if not len(groups) or not len(a.slots):
        return
    at = np.minimum(np.searchsorted(groups, a.slots), len(groups) - 1)
    found = groups[at] == a.slots
    at, of = at[found], np.repeat(np.arange(len(a.ids)), a.size)[found]
    rows, first = np.unique(of, return_index=True)
    ends = np.append(first[1:], len(of))
    b_at, b_of = np.searchsorted(groups, b.slots), np.repeat(np.arange(len(b.ids)), b.size)
    width = int(np.clip(STRIP_BYTES // len(groups) // 8, 1, -(-len(b.ids) // 64)))  # words of 64 members
    for low in range(0, len(b.ids), 64 * width):
        inside = (b_of >= low) & (b_of < low + 64 * width)
        column = b_of[inside] - low
        bits = np.zeros((len(groups), 8 * width), np.uint8)
        np.bitwise_or.at(bits, (b_at[inside], column >> 3), np.left_shift(1, column & 7).astype(np.uint8))
        bits = bits.view(np.uint64)
        begin, most = 0, max(1, UNION_BYTES // (8 * width))
        while begin < len(rows):
            stop = max(begin + 1, int(np.searchsorted(ends, first[begin] + most, "right")))
            part = at[first[begin] : ends[stop - 1]]
            yield rows[begin:stop], low, np.bitwise_or.reduceat(bits[part], first[begin:stop] - first[begin], axis=0)
            begin = stop


def _by_blocks(sets: DataFrame, blocks_of_task: int, work: Callable[[list[Members]], Iterator[list[np.ndarray]]], names: list[str]) -> DataFrame:
    """The columns `names` (longs) that work yields for every choice of blocks, repetition allowed."""
    spark, kind = sets.sparkSession, ", ".join(f"{x} long" for x in names)
    n, busy = sets.count(), math.ceil(math.sqrt(4 * spark.sparkContext.defaultParallelism))
    blocks = max(1, -(-n // BLOCK), min(busy, n // LEAST_BLOCK))
    tasks = list(combinations_with_replacement(range(blocks), blocks_of_task))
    goes = spark.createDataFrame([(b, t) for t, some in enumerate(tasks) for b in sorted(set(some))], "b int, task int")
    own = sets.select("id", "slots", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias("b"))
    sent = own.join(F.broadcast(goes), "b").repartitionById(len(tasks), F.col("task"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        for task in np.unique(t["task"].to_numpy()).tolist():
            held = {}
            for b in set(tasks[task]):
                mine = t.filter(pa.array((t["task"].to_numpy() == task) & (t["b"].to_numpy() == b)))
                lists = mine["slots"].combine_chunks()
                lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) and lists.num_chunks else lists
                size = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64) if len(mine) else np.zeros(0, np.int64)
                held[b] = Members(mine["id"].to_numpy(), size, lists.flatten().to_numpy() if len(mine) else np.zeros(0, np.int32))
            for columns in work([held[b] for b in tasks[task]]):
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in columns], names)

    return sent.select("task", "b", "id", "slots").mapInArrow(run, kind)


def _members_of(bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) of the set bits."""
    flat = np.flatnonzero(np.unpackbits(bits.view(np.uint8), bitorder="little").view(bool))
    row = np.repeat(np.arange(len(bits)), np.bitwise_count(bits).sum(1, dtype=np.int64))
    return row, flat - row * (64 * bits.shape[1])


def sharing_pairs(sets: DataFrame) -> DataFrame:
    """(src, dst), src < dst: the distinct pairs of members that share a group."""

    def work(blocks: list[Members]) -> Iterator[list[np.ndarray]]:
        a, b = blocks
        for rows, low, bits in sharing(a, b):
            x, y = _members_of(bits)
            first, second = a.ids[rows[x]], b.ids[low + y]
            if a is b:
                keep = first < second
                yield [first[keep], second[keep]]
            else:
                yield [np.minimum(first, second), np.maximum(first, second)]

    return _by_blocks(sets, 2, work, ["src", "dst"])


def sharing_counts(sets: DataFrame) -> DataFrame:
    """(id, n): how many other members share a group with a member; those without any are left out."""

    def work(blocks: list[Members]) -> Iterator[list[np.ndarray]]:
        a, b = blocks
        for one, other in ((a, b),) if a is b else ((a, b), (b, a)):
            n = np.zeros(len(one.ids), np.int64)
            for rows, _, bits in sharing(one, other):
                n[rows] += np.bitwise_count(bits).sum(1, dtype=np.int64)
            if a is b:
                n[one.size > 0] -= 1  # itself
            some = n > 0
            yield [one.ids[some], n[some]]

    return _by_blocks(sets, 2, work, ["id", "n"]).groupBy("id").agg(F.sum("n").alias("n"))


def sharing_triangles(sets: DataFrame) -> DataFrame:
    """(triangles): how many three members share groups pair by pair, in one row."""

    def matrix(a: Members, b: Members) -> np.ndarray:
        """Bits of the pairs between two blocks; within one block of those in ascending order alone."""
        out = np.zeros((len(a.ids), -(-len(b.ids) // 64)), np.uint64)
        for rows, low, bits in sharing(a, b):
            out[rows, low // 64 : low // 64 + bits.shape[1]] = bits[:, : out.shape[1] - low // 64]
        if a is b:
            for k in range(len(out)):
                out[k, : k // 64] = 0
                out[k, k // 64] &= ~np.uint64((1 << (k % 64 + 1)) - 1)
        return out

    def work(blocks: list[Members]) -> Iterator[list[np.ndarray]]:
        a, b, c = blocks
        near = matrix(a, b)
        far = near if c is b else matrix(a, c)
        last = near if a is b and c is b else far if a is b else matrix(b, c)
        total, buffer = 0, np.empty((256, far.shape[1]), np.uint64)
        ones = np.empty(buffer.shape, np.uint8)
        for k in range(len(near)):
            via = np.flatnonzero(np.unpackbits(near[k].view(np.uint8), bitorder="little").view(bool))
            for at in range(0, len(via), 256):
                m = min(256, len(via) - at)
                both = np.take(last, via[at : at + m], 0, buffer[:m], "clip")
                both &= far[k]
                total += int(np.bitwise_count(both, out=ones[:m]).sum(dtype=np.int64))
        yield [np.array([total])]

    return _by_blocks(sets, 3, work, ["n"]).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("triangles"))
