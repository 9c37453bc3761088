"""Substring deduplication by super-k-mers.

Each window of `WINDOW` words takes the smallest hash of its `GRAM`-word grams as its minimiser. Consecutive windows
that share a minimiser travel as one packed string (a super-k-mer) to the minimiser's bucket, where equal windows must
meet; sorting the bucket's windows finds each one's first start. Equal super-k-mers of one map slice are combined
before the shuffle: only the earliest travels, for the later ones the slice itself records that they are covered.
Strings for a bucket are packed and compressed together.

Heavy minimisers (more than HEAVY_SHARE of all super-k-mers, so fewer than 1 / HEAVY_SHARE of them) would send one
passage's neighbourhood in every document to one bucket; their windows travel one by one, dealt by the hash of the
whole window, so that equal windows still meet. They are found by counting all minimisers in each slice and adding up
the counts that reach the share of the slice.

Windows with equal hashes are compared as text before a word is removed: nothing is removed on a hash alone.

Edge cases: null text or fewer words than a window: nothing to remove; windows overlapping themselves count as later
starts; rows are ordered by (doc_id, text checksum), so repeated ids have a fixed order, null first (rows
equal in both are one start); empty table: empty
result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written
from .wordhash import grams, hashed, mix

WINDOW, GRAM = 20, 4
HEAVY_SHARE = 1 / 2000
#: Bytes of packed strings that a bucket and a map slice hold: large enough for a slice to compress what it sends.
BUCKET_BYTES, SLICE_BYTES = 16 << 20, 24 << 20
NO_ID = -(2**63)
_U = np.uint64


def _minimisers(g: np.ndarray, span: int) -> np.ndarray:
    """Smallest of each `span` consecutive hashes, by doubling."""
    width, low = 1, g
    while width * 2 <= span:
        low, width = np.minimum(low[:-width], low[width:]), width * 2
    rest = span - width
    return np.minimum(low[: len(low) - rest], low[rest:]) if rest else low


def _super_kmers(words, window: int, gram: int):
    """For a slice of words: first window, number of windows, minimiser, of each run; and all window places."""
    n = len(words.hash) - window + 1
    if n <= 0:
        e = np.zeros(0, np.int64)
        return e, e, np.zeros(0, _U)
    low = _minimisers(grams(words.hash, gram), window - gram + 1)[:n]
    inside = words.text[:n] == words.text[window - 1 :]
    new = np.ones(n, bool)
    new[1:] = (low[1:] != low[:-1]) | (words.text[1:n] != words.text[: n - 1]) | ~inside[:-1]
    at = np.flatnonzero(new & inside)
    ends = np.flatnonzero(np.append(new[1:] | ~inside[1:], True) & inside) + 1
    return at, ends - at, low[at]


def _heavy(rows: DataFrame, window: int, gram: int) -> list[int]:
    """Minimisers of more than HEAVY_SHARE of all super-k-mers; a driver list of fewer than 1 / HEAVY_SHARE numbers."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [_super_kmers(w, window, gram)[2] for w in hashed(b.column(0), lower=False)]
            value, times = np.unique(np.concatenate([*found, np.zeros(0, _U)]), return_counts=True)
            much = times >= max(2, HEAVY_SHARE / 2 * times.sum())
            yield pa.RecordBatch.from_arrays([pa.array(np.append(value[much].view(np.int64), 0)), pa.array(np.append(times[much], 0), pa.int64()), pa.array(np.append(np.zeros(much.sum(), np.int64), times.sum()))], ["m", "k", "total"])

    counts = rows.select("text").mapInArrow(count, "m long, k long, total long").groupBy("m").agg(F.sum("k").alias("k"), F.sum("total").alias("total"))
    counts = written(counts, "minimisers")
    total = counts.agg(F.sum("total")).first()[0] or 0
    return [r.m for r in counts.where(F.col("k") > max(50, HEAVY_SHARE * total)).select("m").collect()]


def _blob(items: list[tuple[int, int, int, int]], texts: list[bytes]) -> bytes:
    """Columns of (doc, tie, first word, number of windows, bytes of the string), then the strings."""
    doc, tie, first, n = np.array(items, np.int64).reshape(-1, 4).T
    parts = (doc.astype("<i8"), tie.astype("<i4"), first.astype("<u4"), n.astype("<u4"), np.array([len(t) for t in texts] or np.zeros(len(items)), "<u4"))
    return struct.pack("<I", len(items)) + b"".join(x.tobytes() for x in parts) + b"".join(texts)


def _unblob(data: bytes) -> tuple[list[tuple[int, int, int, int]], list[bytes]]:
    (k,), at, columns = struct.unpack_from("<I", data), 4, []
    for kind, width in (("<i8", 8), ("<i4", 4), ("<u4", 4), ("<u4", 4), ("<u4", 4)):
        columns.append(np.frombuffer(data, kind, k, at).tolist())
        at += width * k
    ends = (at + np.cumsum(columns[4])).tolist()
    return list(zip(*columns[:4], strict=True)), [data[e - n : e] for e, n in zip(ends, columns[4], strict=True)]


def _pack(window: int, gram: int, bits: int, heavy: list[int]):
    """mapInArrow function from (doc, tie, text) to (bucket, blob) rows; a blob holds strings, or covered ranges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        squeeze = zstandard.ZstdCompressor(level=3)
        often = np.sort(np.array(heavy, np.int64).view(_U))

        def blobs(strings: dict[bytes, list], turn: int) -> Iterator[pa.RecordBatch]:
            parts: dict[int, tuple[list, list]] = {}
            covered = []
            for text, (bucket, where) in strings.items():
                first = min(where)
                items, texts = parts.setdefault(bucket, ([], []))
                items.append(first), texts.append(text)
                covered += [w for w in where if w != first]
            rows = [(bucket, 0, _blob(*p)) for bucket, p in parts.items()]
            if covered:
                rows.append((turn % (1 << bits), 1, _blob(covered, [])))
            for k in range(0, len(rows), 64):  # compressed a few at a time, to bound memory
                buckets, kinds, data = zip(*rows[k : k + 64], strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(buckets, pa.int32()), pa.array(kinds, pa.int32()), pa.array([squeeze.compress(x) for x in data], pa.binary())], ["bucket", "kind", "blob"])

        from pyspark import TaskContext

        turn, strings, held = TaskContext.get().partitionId(), {}, 0
        for b in batches:
            docs, ties = b.column(0).to_pylist(), b.column(1).to_pylist()
            for w in hashed(b.column(2), lower=False):
                at, n, low = _super_kmers(w, window, gram)
                if not len(at):
                    continue
                if len(often):
                    k = np.searchsorted(often, low).clip(max=len(often) - 1)
                    split = often[k] == low
                    whole = mix(grams(w.hash, window))
                    at, n, low = _split(at, n, low, split, whole)
                base = np.append(0, np.cumsum(w.counts()))[w.text]  # the word index where each word's text begins
                bucket = (mix(low) >> _U(64 - bits)).astype(np.int64)
                first, last = w.start[at].tolist(), w.end[at + n + window - 2].tolist()
                plain = w.raw
                if any(x in plain for x in (b"\t", b"\n", b"\r", b"\x0b", b"\x0c", b"  ")):
                    plain = None
                for i, (p, k, x, t, begin) in enumerate(zip(at.tolist(), n.tolist(), bucket.tolist(), w.text[at].tolist(), base[at].tolist(), strict=True)):
                    text = w.raw[first[i] : last[i]]
                    if plain is None:
                        text = b" ".join(text.split())
                    held += len(text)
                    strings.setdefault(text, (x, []))[1].append((docs[w.first + t], ties[w.first + t], p - begin, k))
                if held >= SLICE_BYTES:
                    yield from blobs(strings, turn)
                    turn, strings, held = turn + 7919, {}, 0
        if strings:
            yield from blobs(strings, turn)

    return run


def _split(at, n, low, split, whole):
    """Runs of heavy minimisers as single windows, dealt by their whole hash."""
    if not split.any():
        return at, n, low
    k = n[split]
    ones = np.repeat(at[split] - np.cumsum(k) + k, k) + np.arange(k.sum())
    order = np.argsort(np.concatenate([at[~split], ones]), kind="stable")
    return np.concatenate([at[~split], ones])[order], np.concatenate([n[~split], np.ones(len(ones), np.int64)])[order], np.concatenate([low[~split], whole[ones]])[order]


def _covered(window: int, gram: int):
    """For one bucket: windows that start earlier elsewhere, as ranges of windows (doc, tie, first, number)."""

    def run(table: pa.Table) -> pa.Table:
        expand = zstandard.ZstdDecompressor()
        out, items = [], []
        for kind, blob in zip(table["kind"].to_pylist(), table["blob"].to_pylist(), strict=True):
            heads, texts = _unblob(expand.decompress(blob))
            if kind:
                out += heads
            else:
                items += [(d, t, f, x) for (d, t, f, _), x in zip(heads, texts, strict=True)]
        items.sort(key=lambda x: x[:3])
        out += _later(items, window)
        names = ["doc", "tie", "first", "n"]
        columns = list(zip(*out, strict=True)) if out else [[]] * 4
        return pa.table([pa.array(c, pa.int64()) for c in columns], names)

    return run


def _later(items: list[tuple[int, int, int, bytes]], window: int) -> list[tuple[int, int, int, int]]:
    """Windows of the items (in order of their start) that start earlier in another place."""
    value, item, place = [], [], []
    for w in hashed(pa.array([x[3].decode() for x in items], pa.large_string()), lower=False):
        n = len(w.hash) - window + 1
        if n <= 0:
            continue
        inside = np.flatnonzero(w.text[:n] == w.text[window - 1 :])
        value.append(grams(w.hash, window)[inside])
        item.append(w.text[inside] + w.first)
        begin = np.append(0, np.cumsum(w.counts()))[w.text[inside]]
        place.append(inside - begin)
    if not value:
        return []
    value, item, place = np.concatenate(value), np.concatenate(item), np.concatenate(place)
    order = np.argsort(value, kind="stable")
    v = value[order]
    same = np.append(False, v[1:] == v[:-1])
    if not same.any():
        return []
    near = same | np.append(same[1:], False)
    seen: dict[bytes, tuple] = {}
    later = []
    split: dict[int, list[bytes]] = {}
    for k in np.sort(order[near]).tolist():
        i = int(item[k])
        if i not in split:
            split[i] = items[i][3].split(b" ")
        doc, tie, first, _ = items[i]
        p = int(place[k])
        text = b" ".join(split[i][p : p + window])
        start = (doc, tie, first + p)
        if text not in seen:
            seen[text] = start
        elif seen[text] != start:
            if start < seen[text]:
                start, seen[text] = seen[text], start
            later.append((*start, 1))
    return later


def repeated_ranges(rows: DataFrame, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """(doc, tie, ranges array<struct<first, n>>): windows of each (doc, tie, text) that start earlier elsewhere."""
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    bits = min(20, max(6, math.ceil(math.log2(max(1, 3 * total / BUCKET_BYTES)))))
    heavy = _heavy(rows, window, gram)
    packed = rows.mapInArrow(_pack(window, gram, bits, heavy), "bucket int, kind int, blob binary")
    found = packed.groupBy("bucket").applyInArrow(_covered(window, gram), "doc long, tie long, first long, n long")
    return found.groupBy("doc", "tie").agg(F.collect_list(F.struct("first", "n")).alias("ranges"))


def _keep(text: str | None, ranges: list | None, window: int) -> tuple[int, list[bytes]]:
    words = text.encode().split() if text else []
    if not ranges:
        return len(words), words
    edge = np.zeros(len(words) + 1, np.int64)
    for r in ranges:
        edge[r["first"]] += 1
        edge[r["first"] + r["n"] + window - 1] -= 1
    kept = np.cumsum(edge[:-1]) == 0
    return len(words), [w for w, k in zip(words, kept.tolist(), strict=True) if k]


def without_repeats(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", window: int = WINDOW, digest: bool = False) -> DataFrame:
    """(doc_id, n_words, n_removed, kept): kept words joined by one space, or with digest their sha256."""
    rows = docs.select(F.coalesce(F.col(id_column).cast("long"), F.lit(NO_ID)).alias("doc"), (F.crc32(F.coalesce(F.col(text_column), F.lit(""))) % (1 << 31)).alias("tie"), F.col(text_column).alias("text"))
    both = rows.join(repeated_ranges(rows, window), ["doc", "tie"], "left").select("doc", "text", "ranges")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            made = [_keep(t, r, window) for t, r in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True)]
            texts = [b" ".join(k) for _, k in made]
            kept = [hashlib.sha256(t).hexdigest() if digest else t.decode() for t in texts]
            ids = [None if x == NO_ID else x for x in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([n for n, _ in made], pa.int64()), pa.array([n - len(k) for n, k in made], pa.int64()), pa.array(kept, pa.string())], ["doc_id", "n_words", "n_removed", "kept"])

    return both.mapInArrow(run, "doc_id long, n_words long, n_removed long, kept string")
