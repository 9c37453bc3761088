"""Exact near-duplicate classes: a size-aware heavy-light Jaccard join on word shingles.

1. Sets. Each text's distinct 5-word shingles are hashed to 64 bits. Which hashes occur in two texts is found by
   sending short prints, packed by bucket, and getting back a count per text; prints that clash only keep a text in
   play. A text whose shared hashes cannot make up the threshold has no link and is done. Equal sets become one.
2. Heavy-light join over what is left. Hashes are ordered from rare to frequent. Hashes of one set alone lie in front
   and can never match, so only the rest of a prefix is indexed. Small sets list the 2-subsets of a prefix one hash
   longer (a similar pair shares two hashes there); large sets and those within the threshold's ratio of them are
   put into inverted lists that the large ones scan. The boundary minimises the counted cost of both.
3. Links. Members of a list are first checked against the list's most central member; the links found make
   components. In the next rounds every list pairs neighbours of different components in a random order, until a
   round merges nothing. What then remains apart is settled for good: in each list, members outside the list's
   largest component meet all members of other components, each pair in its first common key only (see `entries`),
   by size, by parity signatures (a short one in the list, a longer one for the pairs left), and at last by both whole sets. No pair inside a component is listed, so a large
   group of copies costs its size, not its square; texts just under the threshold of a whole group cost their number
   times the group, which an exact join cannot avoid. No link between components is lost.

Exact: a pair is linked after comparing both whole sets. Sets are compared as 64-bit hashes; two different shingles of
one pair share a hash with probability below 1e-9 even for sets of 10^5.

Edge cases: null or empty text, or blanks only: empty set, linked with nothing; fewer words than a shingle: the whole
sequence is one shingle; rows with the same doc_id are one document with several sets; null doc_ids are one document,
smaller than all others; empty table: empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..runtime import fits_broadcast
from .common import drop_written, written
from .wordhash import grams, hashed, mix

SHINGLE, NUMERATOR, DENOMINATOR = 5, 75, 100
#: Bytes of text for each bucket of prints: a bucket is one Python call's work, so its size stays within these bounds at
#: any size of the corpus. A print has PRINT_BITS more bits than the logarithm of a bucket's hashes, so that few clash.
LEAST_BUCKET, MOST_BUCKET, PRINT_BITS = 4 << 20, 32 << 20, 4
#: Hashes of one packed slice (more where there are many buckets, so that rows stay packed), and the texts that 16 bits number.
SLICE_HASHES, MOST_SLICE_HASHES, SLICE_TEXTS, SHARED_HERE = 1 << 20, 4 << 20, 60_000, 0xFFFF
NO_ID = -(2**63)
#: Cost of a list member that an entry may be compared with, in units of a row that is made, shuffled and sorted. Measured
#: on 1.4 million entries, a comparison took about 1/80 of a row; only members outside a list's largest component are
#: compared with the others (see `_cross_pairs`), one in six to eight there.
SCAN_COST = 1 / 512
#: Rounds of random pairs before the exact one; more would only merge earlier what the exact round finds.
PAIR_ROUNDS = 3
_U = np.uint64


def shingle_sets(column: pa.Array, size: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, distinct hashes of the rows one after another in ascending order, their number for each row)."""
    for w in hashed(column, lower=True):
        n = w.counts()
        g = grams(w.hash, size)
        inside = w.text[: len(g)] == w.text[size - 1 : size - 1 + len(g)]
        value, text = g[inside], w.text[: len(g)][inside]
        few = np.flatnonzero((n > 0) & (n < size))
        if len(few):
            ends = np.cumsum(n)
            whole = [mix(np.array([sum(int(x) * pow(0x9E3779B97F4A7C15, k + 1, 1 << 64) for k, x in enumerate(w.hash[ends[i] - n[i] : ends[i]])) + int(n[i]) & (1 << 64) - 1], _U))[0] for i in few]
            value, text = np.append(value, np.array(whole, _U)), np.append(text, few)
        order = np.lexsort((value, text))
        value, text = value[order], text[order]
        new = np.ones(len(value), bool)
        new[1:] = (value[1:] != value[:-1]) | (text[1:] != text[:-1])
        yield w.first, value[new], np.bincount(text[new], minlength=w.rows)


def _sums(value: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit sums that name a set."""
    ends = np.cumsum(n)
    a, b = np.append(_U(0), np.cumsum(value)), np.append(_U(0), np.cumsum(mix(value ^ _U(0xD6E8FEB86659FD93))))
    return (a[ends] - a[ends - n]).view(np.int64), (b[ends] - b[ends - n]).view(np.int64)


_PACKED = "bucket int, slice long, prints binary, texts binary, n int"


def print_plan(total: int) -> tuple[int, int, int]:
    """(bits of the bucket number, bytes of a print, hashes of a slice) for so many bytes of text."""
    bucket = min(MOST_BUCKET, max(LEAST_BUCKET, total >> 14))
    bits = max(5, math.ceil(math.log2(max(1, total / bucket))))
    # A shingle takes up six bytes of text or more.
    width = math.ceil((math.log2(bucket / 6) + PRINT_BITS) / 8)
    return bits, width, min(MOST_SLICE_HASHES, max(SLICE_HASHES, 64 << bits))


def _print_rows(bits: int, width: int, slice_hashes: int, size: int):
    """mapInArrow function from (doc, mark, text) to packed prints by bucket, and one row of facts for each slice."""

    def pack(slice_id: int, parts: list) -> Iterator[pa.RecordBatch]:
        ids, marks, value, n = (np.concatenate([p[k] for p in parts]) for k in range(4))
        s1, s2 = _sums(value, n)
        text = np.repeat(np.arange(len(n), dtype=np.uint32), n)
        order = np.argsort(value)
        value, text = value[order], text[order]
        new = np.ones(len(value), bool)
        new[1:] = value[1:] != value[:-1]
        first = np.flatnonzero(new)
        times = np.diff(np.append(first, len(value)))
        shared_here = np.repeat(times > 1, times)
        local = np.bincount(text[shared_here], minlength=len(n))
        # One entry for each hash of the slice; the owner is kept only where the slice itself does not know it as shared.
        owner = np.where(times > 1, SHARED_HERE, text[first])
        value = value[first]
        prints = (value >> _U(64 - bits - 8 * width)).astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width]
        cuts = np.searchsorted(value, np.arange(1, 1 << bits, dtype=_U) << _U(64 - bits))
        cuts = np.concatenate([[0], cuts, [len(value)]])
        full = np.flatnonzero(np.diff(cuts))
        facts = np.stack([ids, marks, n, s1, s2, local], 1).astype("<i8").tobytes()
        columns = [
            [*full.tolist(), int(mix(np.array([slice_id], _U))[0] & _U((1 << bits) - 1))],
            [slice_id] * (len(full) + 1),
            [*(prints[cuts[k] : cuts[k + 1]].tobytes() for k in full), facts],
            [*(owner[cuts[k] : cuts[k + 1]].astype("<u2").tobytes() for k in full), b""],
            [0] * len(full) + [len(n)],
        ]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.int32()), strict=True)], ["bucket", "slice", "prints", "texts", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        slice_id, parts, held, texts = TaskContext.get().partitionId() << 32, [], 0, 0
        for b in batches:
            ids, marks = b.column(0).to_numpy(), b.column(1).to_numpy()
            for first, value, n in shingle_sets(b.column(2), size):
                if parts and (held + len(value) > slice_hashes or texts + len(n) > SLICE_TEXTS):
                    yield from pack(slice_id, parts)
                    slice_id, parts, held, texts = slice_id + 1, [], 0, 0
                parts.append((ids[first : first + len(n)], marks[first : first + len(n)], value, n))
                held, texts = held + len(value), texts + len(n)
        if parts:
            yield from pack(slice_id, parts)

    return run


def _answers(width: int):
    """For one bucket: how many of each slice's own prints are shared, as pairs (text, count); facts pass through."""

    def answer(table: pa.Table) -> pa.Table:
        numbers = table["n"].to_numpy()
        rows, facts = np.flatnonzero(numbers == 0), np.flatnonzero(numbers)
        slices, prints, texts = table["slice"].to_numpy(), table["prints"], table["texts"]
        sizes = np.array([len(prints[int(r)].as_buffer()) // width for r in rows], np.int64)
        value = np.zeros((int(sizes.sum()), 8 if width > 4 else 4), np.uint8)
        value[:, :width] = np.frombuffer(b"".join(prints[int(r)].as_buffer() for r in rows), np.uint8).reshape(-1, width)
        value = value.view("<u8" if width > 4 else "<u4").ravel()
        owner = np.frombuffer(b"".join(texts[int(r)].as_buffer() for r in rows), "<u2")
        order = np.argsort(value)
        ranked = value[order]
        same = np.append(ranked[1:] == ranked[:-1], False) if len(ranked) else np.zeros(0, bool)
        shared = np.empty(len(value), bool)
        shared[order] = same | np.append(False, same[:-1])[: len(same)]
        shared &= owner != SHARED_HERE
        out, at = [], 0
        for r, k in zip(rows, sizes, strict=True):
            who, count = np.unique(owner[at : at + k][shared[at : at + k]], return_counts=True)
            at += k
            if len(who):
                out.append({"slice": int(slices[r]), "n": 0, "facts": np.stack([who, count], 1).astype("<u4").tobytes()})
        out += [{"slice": int(slices[r]), "n": int(numbers[r]), "facts": prints[int(r)].as_py()} for r in facts]
        return pa.Table.from_pylist(out, pa.schema([("slice", pa.int64()), ("n", pa.int32()), ("facts", pa.binary())]))

    return answer


def _total(table: pa.Table) -> pa.Table:
    """For one slice: doc, text mark, set size, set sums, shared hashes of each text."""
    rows = table.to_pylist()
    facts = np.frombuffer(next(r["facts"] for r in rows if r["n"]), "<i8").reshape(-1, 6)
    shared = facts[:, 5].copy()
    for r in rows:
        if not r["n"]:
            pairs = np.frombuffer(r["facts"], "<u4").reshape(-1, 2)
            shared[pairs[:, 0]] += pairs[:, 1]
    return pa.table([pa.array(facts[:, k].copy()) for k in range(5)] + [pa.array(shared)], ["doc", "mark", "n", "s1", "s2", "shared"])


def set_facts(rows: DataFrame, size: int = SHINGLE) -> DataFrame:
    """(doc, mark, n, s1, s2, shared) for each (doc, mark, text); shared: hashes that another set may hold too (never too few)."""
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    bits, width, slice_hashes = print_plan(total)
    packed = rows.mapInArrow(_print_rows(bits, width, slice_hashes, size), _PACKED)
    answers = packed.groupBy("bucket").applyInArrow(_answers(width), "slice long, n int, facts binary")
    return answers.groupBy("slice").applyInArrow(_total, "doc long, mark long, n long, s1 long, s2 long, shared long")


def _enough(part, whole):
    return DENOMINATOR * part >= NUMERATOR * whole


#: Texts whose (doc, mark) may be broadcast to find the rows whose sets are needed: about 10 MB as rows.
BROADCAST_TEXTS = 250_000


def hash_sets(rows: DataFrame, wanted: DataFrame, size: int = SHINGLE) -> DataFrame:
    """(id, hashes array<long>) of the wanted (doc, mark, n, s1, s2, id) sets, from (doc, mark, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, want = b.column(0).to_numpy(), np.stack([b.column(k).to_numpy() for k in (2, 3, 4)], 1)
            for first, value, n in shingle_sets(b.column(1), size):
                s1, s2 = _sums(value, n)
                same = (np.stack([n, s1, s2], 1) == want[first : first + len(n)]).all(1)
                lists = pa.LargeListArray.from_arrays(pa.array(np.append(0, np.cumsum(n)), pa.int64()), pa.array(value.view(np.int64)))
                yield pa.RecordBatch.from_arrays([pa.array(ids[first : first + len(n)]), lists.cast(pa.list_(pa.int64()))], ["id", "hashes"]).filter(pa.array(same))

    # The texts themselves are shuffled only where the list of those needed is too long to send to every executor.
    side = F.broadcast(wanted) if fits_broadcast(wanted, BROADCAST_TEXTS) else wanted
    both = rows.join(side, ["doc", "mark"]).select("id", "text", "n", "s1", "s2")
    return both.mapInArrow(run, "id long, hashes array<long>").dropDuplicates(["id"])


def prefixes(sets: DataFrame) -> DataFrame:
    """(id, n, m, p, front): the first p + 1 shared hashes of a set, from rare to frequent, as (f, h); m: hashes that
    another set holds; p of them lie in the prefix."""
    each = sets.select("id", F.size("hashes").alias("n"), F.explode("hashes").alias("h"))
    often = each.groupBy("h").agg(F.count(F.lit(1)).alias("f")).where("f > 1")
    held = each.join(often, "h").groupBy("id", "n").agg(F.sort_array(F.collect_list(F.struct("f", "h"))).alias("held"))
    held = held.withColumn("m", F.size("held")).where(_enough(F.col("m"), F.col("n")))
    # A prefix of n - ceil(t n) + 1 hashes, of which the n - m that no other set holds come first.
    place = F.col("n") - F.ceil(F.lit(NUMERATOR) * F.col("n") / DENOMINATOR).cast("int") + 1 - (F.col("n") - F.col("m"))
    held = held.withColumn("p", place).where("p >= 1")
    return held.select("id", "n", "m", "p", F.slice("held", 1, F.col("p") + 1).alias("front"))


def boundary(held: DataFrame) -> int:
    """The size class (powers of 2^(1/2)) from which on sets scan lists, by counted cost: subsets made, against list
    entries made and the members that each is compared with."""
    scan = F.aggregate(F.slice("front", 1, F.col("p")), F.lit(0.0), lambda s, x: s + 1 + SCAN_COST * x["f"])
    sizes = held.groupBy(_size_class()).agg(F.sum(F.size("front") * (F.size("front") - 1) / 2).alias("subsets"), F.sum(scan).alias("scans"))
    sizes = sorted(sizes.collect())  # one row for each size class: under a hundred
    cost = lambda c: sum(r.subsets if r.c < c else r.scans for r in sizes)
    return min([0, *(r.c + 1 for r in sizes)], key=cost)


def _size_class():
    return F.floor(2 * F.log2("n")).alias("c")


SEEN_CELLS = 4
_NOTHING = np.iinfo(np.int64).max
_SEEN = [f"seen{k}" for k in range(SEEN_CELLS)]


def entries(held: DataFrame, first_large: int, seen: bool, carry: tuple[str, ...] = ()) -> DataFrame:
    """(key, subset, id, n, m): the members of every subset list and inverted list, with the columns `carry` (long) of
    their sets.

    seen: also, by SEEN_CELLS cells of the hash space, the least hash of a set's prefix that lies before the key. Two
    sets whose entries agree in such a number share an earlier key, so this key need not pair them; in their first
    common key they cannot agree.
    """
    least_large = math.ceil(2 ** (first_large / 2))
    rows = held.select("id", "n", "m", "p", (_size_class() < first_large).alias("small"), _enough(F.col("n"), F.lit(least_large)).alias("scans"), F.col("front.h").alias("front"), *carry)
    names = ["key", "subset", "id", "n", "m", *carry, *(_SEEN if seen else [])]

    def before(cells: np.ndarray) -> np.ndarray:
        """Least number of each cell among the columns before each column."""
        return np.minimum.accumulate(np.concatenate([np.full((SEEN_CELLS, 1), _NOTHING), cells], 1), 1)

    def one(front: np.ndarray, p: int, small: bool, scans: bool) -> Iterator[tuple[np.ndarray, bool, np.ndarray]]:
        cells = np.where((front & (SEEN_CELLS - 1)) == np.arange(SEEN_CELLS)[:, None], front, _NOTHING) if seen else None
        head = before(cells) if seen else None
        if scans or not small:
            yield front[:p], False, head[:, :p] if seen else None
        if small:
            for i in range(len(front) - 1):
                rest = front[i + 1 :]
                pair = mix(mix(np.full(len(rest), front[i]).view(_U)) + rest.view(_U)).view(np.int64)
                yield pair, True, np.minimum(before(cells[:, i + 1 :])[:, :-1], head[:, i : i + 1]) if seen else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            parts, size = [], 0
            fronts, at = b.column(6).flatten().to_numpy(), b.column(6).offsets.to_numpy() - b.column(6).offsets[0].as_py()
            facts = zip(*(b.column(k).to_pylist() for k in range(6)), strict=True)
            more = [b.column(7 + k).to_numpy() for k in range(len(carry))]
            for k, (i, n, m, p, small, scans) in enumerate(facts):
                for key, subset, cells in one(fronts[at[k] : at[k + 1]], p, small, scans):
                    parts.append((key, subset, i, n, m, cells, k))
                    size += len(key)
                if size > 1 << 17:
                    yield batch(parts, more)
                    parts, size = [], 0
            if parts:
                yield batch(parts, more)

    def batch(parts: list, more: list[np.ndarray]) -> pa.RecordBatch:
        long = [len(x[0]) for x in parts]
        columns = [np.concatenate([x[0] for x in parts]), np.repeat([x[1] for x in parts], long)]
        columns += [np.repeat(np.array([x[k] for x in parts], kind), long) for k, kind in ((2, np.int64), (3, np.int32), (4, np.int32))]
        columns += [np.repeat(c[[x[6] for x in parts]], long) for c in more]
        if seen:
            columns += list(np.concatenate([x[5] for x in parts], 1))
        return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names)

    return rows.mapInArrow(run, "key long, subset boolean, id long, n int, m int" + "".join(f", {c} long" for c in (*carry, *(_SEEN if seen else []))))


def checked(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The (a, b) pairs that reach the threshold, by their whole sets."""
    left, right = sets.select(F.col("id").alias("a"), F.col("hashes").alias("x")), sets.select(F.col("id").alias("b"), F.col("hashes").alias("y"))
    both = F.size(F.array_intersect("x", "y"))
    return pairs.join(left, "a").join(right, "b").where(_enough(both, F.size("x") + F.size("y") - both)).select("a", "b")


def components(spark: SparkSession, links: DataFrame) -> DataFrame:
    """(id, component) for every id in links (a, b): the smallest id reachable. Alternates large and small stars."""
    edges = links.where("a != b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct().checkpoint()
    before = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("low"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("low").alias("v")).where("u != v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("low"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("low").alias("v")).where("u != v")
        edges = small.unionByName(low.select("u", F.col("low").alias("v"))).distinct().checkpoint()
        state = tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if state == before:
            break
        before = state
    roots = edges.groupBy("u").agg(F.min("v").alias("component")).withColumnRenamed("u", "id")
    return roots.unionByName(roots.select(F.col("component").alias("id"), "component").distinct()).checkpoint()


def _merged(spark: SparkSession, found: DataFrame | None, links: DataFrame) -> DataFrame:
    """(id, component) after adding links (a, b) to what was found before: only the components are linked anew."""
    if found is None:
        return components(spark, links)
    a, b = (found.select(F.col("id").alias(c), F.col("component").alias(f"{c}c")) for c in "ab")
    ends = links.join(a, "a", "left").join(b, "b", "left").select(F.coalesce("ac", "a").alias("a"), F.coalesce("bc", "b").alias("b"))
    upper = components(spark, ends).withColumnRenamed("component", "top").withColumnRenamed("id", "component")
    moved = found.join(upper, "component", "left").select("id", F.coalesce("top", "component").alias("component"))
    new = upper.select(F.col("component").alias("id"), F.col("top").alias("component")).join(found.select("id"), "id", "left_anti")
    return moved.unionByName(new).checkpoint()


def jaccard_components(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", size: int = SHINGLE) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row."""
    spark = docs.sparkSession
    rows = docs.select(F.coalesce(F.col(id_column).cast("long"), F.lit(NO_ID)).alias("doc"), F.xxhash64(text_column).alias("mark"), F.col(text_column).alias("text"))
    facts = written(set_facts(rows, size), "set-facts")
    name = ["n", "s1", "s2"]
    live = facts.where((F.col("n") > 0) & _enough(F.col("shared"), F.col("n")))
    # A class is named by its set, not by a doc_id: rows of one doc_id may hold different sets.
    classes = written(live.groupBy(*name).agg(F.min(F.struct("doc", "mark")).alias("first")).select("first.*", *name).withColumn("id", F.monotonically_increasing_id()), "set-classes")
    sets = written(hash_sets(rows, classes, size), "sets")
    held = written(prefixes(sets), "prefixes")
    first_large = boundary(held)
    lists = written(entries(held, first_large, False), "lists")
    several = written(_several(facts, classes), "several-sets")
    same = several.where("id is not null").groupBy("doc").agg(F.min("id").alias("b"), F.collect_set("id").alias("a")).select(F.explode("a").alias("a"), "b")
    links = written(checked(_star_pairs(lists), sets), "links")
    found = components(spark, links.unionByName(same))
    marks = written(parities(sets), "parities")
    for k in range(PAIR_ROUNDS):
        pairs = written(_near(_random_pairs(lists, found, k), marks), "random-pairs")
        more = written(checked(pairs, sets), "links")
        drop_written(pairs)
        if more.isEmpty():
            break
        found = _merged(spark, found, more)
        drop_written(more)
    pairs = written(_near(_cross_pairs(lists, held, first_large, found, marks), marks), "cross-pairs")
    more = written(checked(pairs, sets), "links")
    if not more.isEmpty():
        found = _merged(spark, found, more)
    drop_written(sets, held, lists, links, marks, pairs, more)
    grown = classes.join(found, "id", "left").withColumn("component", F.coalesce("component", "id"))
    least = grown.groupBy("component").agg(F.min("doc").alias("least"))
    named = grown.join(least, "component").select(*name, F.col("least").alias("by_set"))
    by_doc = several.where("id is not null").select(F.col("doc").alias("doc2"), "id").join(found, "id").join(least, "component").groupBy("doc2").agg(F.min("least").alias("by_doc"))
    out = facts.join(named, name, "left").join(by_doc, F.col("doc") == F.col("doc2"), "left")
    component = F.when(F.col("n") > 0, F.coalesce("by_set", "by_doc", "doc")).otherwise(F.col("doc"))
    out = out.select(F.col("doc").alias("doc_id"), F.col("n").alias("n_shingles"), component.alias("component_id"))
    real = lambda c: F.when(F.col(c) != NO_ID, F.col(c)).alias(c)
    return out.select(real("doc_id"), "n_shingles", real("component_id"))


def _several(facts: DataFrame, classes: DataFrame) -> DataFrame:
    """(doc, id) for the documents of several rows; id: the set class of a row, null where it has no link."""
    many = facts.where("n > 0").groupBy("doc").agg(F.count(F.lit(1)).alias("k")).where("k > 1").select("doc")
    return facts.where("n > 0").join(many, "doc", "left_semi").join(classes.drop("doc", "mark"), ["n", "s1", "s2"], "left").select("doc", "id").distinct()


KEY = ["key", "subset"]


def _star_pairs(lists: DataFrame) -> DataFrame:
    """Each member with its list's most central one: the fewest hashes of its own, then the smallest id."""
    centre = lists.groupBy(*KEY).agg(F.min_by(F.struct("id", "n", "m"), F.struct((F.col("n") - F.col("m")).alias("own"), "id")).alias("c"), F.count(F.lit(1)).alias("k")).where("k > 1").drop("k")
    both = lists.join(centre, KEY).where(F.col("id") != F.col("c.id")).where(_may_link(F.col("n"), F.col("m"), F.col("c.n"), F.col("c.m")))
    return both.select(F.greatest("id", "c.id").alias("a"), F.least("id", "c.id").alias("b")).distinct()


def _in_components(lists: DataFrame, found: DataFrame) -> DataFrame:
    return lists.join(found, "id", "left").withColumn("component", F.coalesce("component", "id"))


def _random_pairs(lists: DataFrame, found: DataFrame, k: int) -> DataFrame:
    """Neighbours of different components in each list, in an order that a hash of id and round gives."""
    line = Window.partitionBy(*KEY).orderBy(F.xxhash64(F.lit(k), "id"), "id")
    last = lambda c: F.lag(c).over(line).alias(f"{c}2")
    both = _in_components(lists, found).select("id", "n", "m", "component", *[last(c) for c in ("id", "n", "m", "component")])
    both = both.where("component != component2").where(_may_link(F.col("n"), F.col("m"), F.col("n2"), F.col("m2")))
    return both.select(F.greatest("id", "id2").alias("a"), F.least("id", "id2").alias("b")).distinct()


#: 64-bit words of a parity signature, and of the short one that list entries carry (a fold of the whole one).
PARITY_WORDS, SHORT_WORDS = 32, 8
_SHORT = [f"mark{k}" for k in range(SHORT_WORDS)]


def parities(sets: DataFrame) -> DataFrame:
    """(id, n, parity array<long>): which of 64 PARITY_WORDS cells hold an odd number of a set's hashes.

    Each cell in which two sets differ needs a hash that only one of them holds, so the number of such cells never
    exceeds the sets' symmetric difference: a test that needs no whole set and loses no link.
    """
    bits = 64 * PARITY_WORDS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 1024):
                b = whole.slice(at, 1024)
                value = b.column(1).flatten().to_numpy().view(_U)
                n = np.diff(b.column(1).offsets.to_numpy())
                cell = np.repeat(np.arange(b.num_rows) * bits, n) + (mix(value) % _U(bits)).astype(np.int64)
                odd = (np.bincount(cell, minlength=bits * b.num_rows) & 1).astype(np.uint8).reshape(-1, bits)
                words = np.packbits(odd, axis=1).view("<i8").ravel()
                lists = pa.ListArray.from_arrays(pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * PARITY_WORDS), pa.array(words))
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n.astype(np.int32)), lists], ["id", "n", "parity"])

    return sets.select("id", "hashes").mapInArrow(run, "id long, n int, parity array<long>")


def _apart_enough(n1, n2, apart):
    """Whether sets that differ in so many cells may reach the threshold: (n + n2 - |x ^ y|) / 2 hashes are shared at most."""
    return _enough(n1 + n2 - apart, n1 + n2 + apart)


def _folded(marks: DataFrame) -> DataFrame:
    """(id, mark0 ..): the parity of a larger cell is the exclusive or of its parts'."""
    fold = lambda k: reduce(lambda x, y: x.bitwiseXOR(y), [F.get("parity", F.lit(j)) for j in range(k, PARITY_WORDS, SHORT_WORDS)])
    return marks.select("id", *[fold(k).alias(c) for k, c in enumerate(_SHORT)])


def _near(pairs: DataFrame, marks: DataFrame) -> DataFrame:
    """The (a, b) pairs whose parity signatures still allow the threshold."""
    a, b = (marks.select(F.col("id").alias(c), F.col("n").alias(f"{c}n"), F.col("parity").alias(f"{c}p")) for c in "ab")
    apart = F.aggregate(F.zip_with("ap", "bp", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)
    return pairs.join(a, "a").join(b, "b").where(_apart_enough(F.col("an"), F.col("bn"), apart)).select("a", "b")


def _cross_pairs(lists: DataFrame, held: DataFrame, first_large: int, found: DataFrame, marks: DataFrame) -> DataFrame:
    """Every pair of a list that lies in different components and may reach the threshold, in its first common key.

    In each list only the members outside its largest component look for partners."""
    inside = _in_components(lists, found)
    sizes = found.groupBy("component").agg(F.count(F.lit(1)).alias("members"))
    ranked = inside.join(sizes, "component", "left").groupBy(*KEY).agg(F.max(F.struct(F.coalesce("members", F.lit(1)).alias("members"), "component"))["component"].alias("major"), F.min("component").alias("x"), F.max("component").alias("y"))
    mixed = ranked.where("x != y").select(*KEY, "major")
    marked = entries(held.join(_folded(marks), "id"), first_large, True, tuple(_SHORT))
    left = written(_in_components(marked, found).join(mixed, KEY), "mixed-lists")
    right = left.select(*KEY, *[F.col(c).alias(f"{c}2") for c in ("id", "n", "m", "component", *_SEEN, *_SHORT)])
    known = reduce(lambda x, y: x | y, [(F.col(c) == F.col(f"{c}2")) & (F.col(c) != F.lit(int(_NOTHING))) for c in _SEEN])
    once = (F.col("component2") == F.col("major")) | (F.col("id") > F.col("id2"))
    both = left.where("component != major").join(right, KEY).where(F.col("component") != F.col("component2")).where(once & ~known)
    apart = sum((F.bit_count(F.col(c).bitwiseXOR(F.col(f"{c}2"))) for c in _SHORT), F.lit(0))
    both = both.where(_may_link(F.col("n"), F.col("m"), F.col("n2"), F.col("m2")) & _apart_enough(F.col("n"), F.col("n2"), apart))
    return both.select(F.greatest("id", "id2").alias("a"), F.least("id", "id2").alias("b")).distinct()


def _may_link(n1, m1, n2, m2):
    part = F.least(m1, m2)
    return _enough(part, n1 + n2 - part)
