"""Token ids as a compressed binary data set.

Layout of a written data set (two Parquet tables in one folder, so that Spark's committers and any store serve it):
  codebook  (id int, bits int)                     one row per token id in use; canonical codes follow from the lengths
  blocks    (shard int, block int, start long, docs array<struct<doc_id long, n long>>, n_tokens long, stride int,
             checkpoints binary, payload binary)   ascending (shard, block) is ascending doc_id; start: ids of the shard
             before the block

A block decodes alone: `payload` is its bit stream, `checkpoints` the little-endian uint32 bit offset of every
`stride`-th token. Decoding walks all checkpoints of a block side by side with one table of 2^MAX_BITS entries.

Code lengths are limited to MAX_BITS by the package-merge method on global counts; the counts that reach the
driver are one row per vocabulary id, so their number is bounded by the tokenizer (49,408), never by the data.

Edge cases: a null text is an empty text (only the end id is written); empty table: empty data set, no rows; null
doc_id sorts first; repeated doc_ids stay, ordered by text hash; other columns of the input are ignored.
"""

from __future__ import annotations

import functools
import itertools
import json
import os
import re
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..runtime import fits_broadcast, shuffles_dropped
from .chunks import LONGEST
from .common import drop_written, new_path, written
from .wordhash import HashTable, Words, grown, hashed, spans

MAX_BITS = 16
#: Tokens after which a block is closed (at the end of a document) and tokens between two checkpoints.
BLOCK_TOKENS = 1 << 19
STRIDE = 256
#: Ids and words that a worker keeps, and runs of letters (about 60 MB each); results do not depend on them.
MOST_IDS, MOST_RUNS = 6_000_000, 300_000
#: Shards whose starts may be broadcast to the readers.
BROADCAST_SHARDS = 1_000_000


# ---------------------------------------------------------------- code construction


def code_lengths(counts: np.ndarray, limit: int = MAX_BITS) -> np.ndarray:
    """Optimal code lengths of at most `limit` bits for positive counts (package-merge)."""
    n = len(counts)
    if n == 0:
        return np.zeros(0, np.int64)
    if n == 1:
        return np.ones(1, np.int64)
    if n > 1 << limit:
        raise ValueError(f"{n} symbols do not fit into {limit} bits")
    order = np.argsort(counts, kind="stable")
    leaf = counts[order].astype(object) if counts.max() > 2**40 else counts[order].astype(np.int64)
    # Level by level: merge the leaves with the pairs of the level below; remember how many leaves a prefix holds.
    is_leaf, weights = [np.ones(n, bool)], leaf
    for _ in range(limit - 1):
        m = len(weights) // 2
        packed = weights[0 : 2 * m : 2] + weights[1 : 2 * m : 2]
        both = np.concatenate([leaf, packed])
        rank = np.argsort(both, kind="stable")
        is_leaf.append(rank < n)
        weights = both[rank]
    lengths, take = np.zeros(n, np.int64), 2 * n - 2
    for flags in reversed(is_leaf):
        leaves = int(flags[:take].sum())
        lengths[:leaves] += 1
        take = 2 * (take - leaves)
    out = np.empty(n, np.int64)
    out[order] = lengths
    return out


class Code:
    """Canonical code of a codebook: ids with their lengths."""

    def __init__(self, ids: np.ndarray, bits: np.ndarray):
        order = np.lexsort((ids, bits))
        ids, bits = np.asarray(ids)[order].astype(np.int64), np.asarray(bits)[order].astype(np.int64)
        starts = np.zeros(len(ids), np.int64)  # of each code in a table of 2^MAX_BITS slots
        if len(ids):
            starts[1:] = np.cumsum(1 << (MAX_BITS - bits))[:-1]
        size = int(ids.max()) + 1 if len(ids) else 1
        self.length, self.code = np.zeros(size, np.int64), np.zeros(size, np.uint64)
        self.length[ids] = bits
        self.code[ids] = (starts >> (MAX_BITS - bits)).astype(np.uint64)
        self.symbol = np.repeat(ids, 1 << (MAX_BITS - bits)).astype(np.uint32)
        self.step = np.repeat(bits, 1 << (MAX_BITS - bits)).astype(np.int64)
        if len(self.symbol) < 1 << MAX_BITS:  # a single symbol leaves half of the table unused
            pad = (1 << MAX_BITS) - len(self.symbol)
            self.symbol, self.step = np.pad(self.symbol, (0, pad)), np.pad(self.step, (0, pad), constant_values=1)

    def encode(self, ids: np.ndarray, stride: int = STRIDE) -> tuple[bytes, bytes]:
        """Bit stream and checkpoints."""
        ids = ids.astype(np.int64, copy=False)
        n = self.length[ids]
        end = np.cumsum(n)
        at = end - n
        total = int(end[-1]) if len(end) else 0
        word, shift = at >> 5, at & 31
        span = self.code[ids] << (64 - n - shift).astype(np.uint64)  # the code's place in two 32-bit words
        words = total // 32 + 2
        high = np.bincount(word, (span >> np.uint64(32)).astype(np.float64), words)
        low = np.bincount(word + 1, (span & np.uint64(0xFFFFFFFF)).astype(np.float64), words)
        stream = (high + low[: len(high)]).astype(np.uint64).astype(">u4").tobytes()
        return stream[: (total + 7) // 8], at[::stride].astype("<u4").tobytes()

    def decode(self, payload: bytes, checkpoints: bytes, n_tokens: int, stride: int = STRIDE) -> np.ndarray:
        at = np.frombuffer(checkpoints, "<u4").astype(np.int64)
        if not n_tokens:
            return np.zeros(0, np.uint32)
        raw = np.frombuffer(payload + b"\0" * (8 - len(payload) % 4), ">u4").astype(np.uint64)
        pair = np.append((raw[:-1] << np.uint64(32)) | raw[1:], raw[-1] << np.uint64(32))
        lanes, out = len(at), np.empty((stride, len(at)), np.uint32)
        last = len(pair) - 1
        for k in range(stride):
            slot = ((pair[np.minimum(at >> 5, last)] >> (48 - (at & 31)).astype(np.uint64)) & np.uint64(0xFFFF)).astype(np.int64)
            out[k] = self.symbol[slot]
            at += self.step[slot]
        return out.T.reshape(lanes * stride)[:n_tokens]


# ---------------------------------------------------------------- the Spark side


#: The pre-tokenizer pattern for which plain words may be cut by _PLAIN_CUT, and those cuts.
_WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
_PLAIN = re.compile(r"[!#-&(-;=-~À-ÖØ-öø-ÿ]+")
_PLAIN_CUT = re.compile(r"[a-zß-öø-ÿ]+|[0-9]|[!-/:-@\[-`{-~]+|\n")  # and the line feed between two words


def _cut(raw: bytes, sizes: np.ndarray) -> list[bytes]:
    """raw in pieces of these sizes."""
    ends = np.cumsum(sizes)
    return [raw[a:b] for a, b in zip((ends - sizes).tolist(), ends.tolist(), strict=True)]


def _encoder(path: str, special: bool) -> Callable[[list[str]], list[bytes]]:
    """From words to their ids as little-endian uint16."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(path)
    tok.encode_special_tokens = special
    tok.no_truncation(), tok.no_padding()
    whole = lambda chunks: [np.asarray(e.ids, "<u2").tobytes() for e in tok.encode_batch(chunks, add_special_tokens=False)]
    spec = json.loads(tok.to_str())
    cut = json.dumps(spec["pre_tokenizer"])
    if json.dumps(_WORD_PATTERN)[1:-1] not in cut or "ByteLevel" not in cut or not cut.count("Split") == 1 or "Lowercase" not in json.dumps(spec["normalizer"]):
        return whole

    # Words of ASCII and Latin-1 letters need neither normaliser nor pre-tokenizer: their runs go to the model itself.
    # The byte-level alphabet shows byte 128..160 as code point byte + 162, byte 173 as 323, the other high bytes as themselves.
    shown = lambda x: chr(x + 162) if x <= 160 else chr(323) if x == 173 else chr(x)
    as_bytes = {c: "".join(map(shown, chr(c).encode())) for c in range(0xDF, 0x100)}
    tokenize = tok.model.tokenize
    known: dict[str, bytes] = {}

    def runs(text: list[str]) -> list[bytes]:
        """The ids of each run; unknown runs are encoded once, and packed all at once."""
        out = list(map(known.get, text))
        if None in out:
            new = list({c for c, x in zip(text, out, strict=True) if x is None})
            if len(known) + len(new) > MOST_RUNS:
                known.clear()
            ids = [[x.id for x in tokenize(c if c.isascii() else c.translate(as_bytes))] for c in new]
            made = dict(zip(new, _cut(np.fromiter(itertools.chain.from_iterable(ids), "<u2").tobytes(), 2 * np.fromiter(map(len, ids), np.int64, len(ids))), strict=True))
            out = [made[c] if x is None else x for c, x in zip(text, out, strict=True)]
            known.update((c, x) for c, x in made.items() if len(c) <= LONGEST)
        return out

    def encode(chunks: list[str]) -> list[bytes]:
        plain = list(filter(_PLAIN.fullmatch, chunks))
        made = {}
        if plain:
            found = _PLAIN_CUT.findall("\n".join(plain).lower())
            between = np.fromiter(map("\n".__eq__, found), bool, len(found))
            got = runs([c for c in found if c != "\n"])
            word, size = np.cumsum(between)[~between], np.fromiter(map(len, got), np.int64, len(got))
            made = dict(zip(plain, _cut(b"".join(got), np.bincount(word, size, len(plain)).astype(np.int64)), strict=True))
            if len(plain) == len(chunks):
                return list(map(made.__getitem__, chunks))
        rest = [c for c in chunks if c not in made]
        made.update(zip(rest, whole(rest), strict=True))
        return [made[c] for c in chunks]

    return encode


class WordIds:
    """The ids of words by their hash: one run of a growing array for each; starts anew when it holds too many."""

    def __init__(self, encode: Callable[[list[str]], list[bytes]], most_ids: int = MOST_IDS):
        self.encode, self.most = encode, most_ids
        self._clear()

    def _clear(self) -> None:
        self.rows, self.used = HashTable(), 0
        self.start, self.length, self.ids = np.zeros(1024, np.int64), np.zeros(1024, np.int64), np.zeros(4096, np.uint16)

    def of(self, w: Words) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all words one after another, their number for each word)."""
        key, first, back = np.unique(w.hash, return_index=True, return_inverse=True)
        at = self.rows.find(key)
        new = np.flatnonzero(at < 0)
        if len(new):
            if self.used + self.rows.n > self.most:
                self._clear()
                new = np.arange(len(key))
            at[new] = self.rows.add(key[new])
            made = self.encode([w.raw[a:b].decode("utf-8") for a, b in zip(w.start[first[new]].tolist(), w.end[first[new]].tolist(), strict=True)])
            length = np.array([len(x) // 2 for x in made], np.int64)
            total = int(length.sum())
            self.start, self.length, self.ids = grown(self.start, self.rows.n), grown(self.length, self.rows.n), grown(self.ids, self.used + total)
            self.start[at[new]], self.length[at[new]] = self.used + np.cumsum(length) - length, length
            self.ids[self.used : self.used + total] = np.frombuffer(b"".join(made), "<u2")
            self.used += total
        row = at[back]
        return self.ids[spans(self.start[row], self.length[row])], self.length[row]


@functools.lru_cache(maxsize=2)
def _word_ids(path: str, special: bool) -> WordIds:
    """One table per Python worker, kept from task to task."""
    return WordIds(_encoder(path, special))


def _texts_of(w: Words, ids: np.ndarray, length: np.ndarray, end_id: int | None) -> tuple[np.ndarray, pa.Array]:
    """(number of ids, ids as binary) of each text of some words, the end id appended."""
    tail = 0 if end_id is None else 1
    n = np.bincount(w.text, length, w.rows).astype(np.int64) + tail
    ends = np.cumsum(n)
    out = np.full(int(ends[-1]) if len(ends) else 0, end_id or 0, "<u2")
    out[np.arange(len(ids)) + tail * np.repeat(w.text, length)] = ids
    return n, pa.Array.from_buffers(pa.large_binary(), len(n), [None, pa.py_buffer(np.append(0, 2 * ends).astype(np.int64)), pa.py_buffer(out)])


def tokenized(docs: DataFrame, tokenizer_path: str, end_id: int | None, id_column: str = "doc_id", text_column: str = "text", special_as_text: bool = False) -> DataFrame:
    """(doc_id, tie long, n long, ids binary): little-endian uint16 ids of each whole text, end id appended.

    Words are segmented once per worker and found again by hash: the tokenizer's pre-tokens never cross ASCII white space.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = _word_ids(tokenizer_path, special_as_text)
        for b in batches:
            for w in hashed(b.column(2), lower=False):
                n, ids = _texts_of(w, *known.of(w), end_id)
                part = b.slice(w.first, w.rows)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(n), ids.cast(pa.binary())], ["doc_id", "tie", "n", "ids"])

    rows = docs.select(F.col(id_column).cast("long").alias("doc_id"), F.xxhash64(text_column).alias("tie"), F.col(text_column).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, tie long, n long, ids binary")


def codebook(tokens: DataFrame) -> list[tuple[int, int]]:
    """(id, bits) from the counts over all documents."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << 16, np.int64)
        for b in batches:
            ids, n = b.column(0).cast(pa.large_binary()), b.num_rows
            at = np.frombuffer(ids.buffers()[1], np.int64)[ids.offset : ids.offset + n + 1]
            if n and at[-1] > at[0]:
                raw = np.frombuffer(ids.buffers()[2], np.uint8)[at[0] : at[-1]].view("<u2")
                for k in range(0, len(raw), 1 << 20):
                    total += np.bincount(raw[k : k + (1 << 20)], minlength=1 << 16)
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(used, pa.int32()), pa.array(total[used], pa.int64())], ["id", "n"])

    # One row per vocabulary id at most: bounded by the uint16 id space.
    rows = tokens.select("ids").mapInArrow(count, "id int, n long").groupBy("id").agg(F.sum("n").alias("n")).collect()
    ids, counts = np.array([r.id for r in rows], np.int64), np.array([r.n for r in rows], np.int64)
    order = np.argsort(ids)
    return [(int(i), int(b)) for i, b in zip(ids[order], code_lengths(counts[order]), strict=True)]


def write_token_file(docs: DataFrame, path: str, tokenizer_path: str, end_id: int | None = 2, max_partition_tokens: int = 1 << 22, **columns: str) -> None:
    """Encode every text and write the data set to `path` in ascending doc_id order."""
    spark = docs.sparkSession
    tokens = written(tokenized(docs, tokenizer_path, end_id, **columns), "tokens")
    book = codebook(tokens)
    spark.createDataFrame(book, "id int, bits int").coalesce(1).write.parquet(f"{path}/codebook")
    total = tokens.agg(F.sum("n")).first()[0] or 0
    shards = max(1, -(-total // max_partition_tokens), spark.sparkContext.defaultParallelism)
    ids, bits = np.array([x[0] for x in book], np.int64), np.array([x[1] for x in book], np.int64)

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code, docs_in, parts, size, k, before = Code(ids, bits), [], [], 0, 0, 0

        def close() -> pa.RecordBatch:
            payload, marks = code.encode(np.frombuffer(b"".join(parts), "<u2"))
            kind = pa.list_(pa.struct([("doc_id", pa.int64()), ("n", pa.int64())]))
            return pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([k], pa.int32()), pa.array([before], pa.int64()), pa.array([docs_in], kind), pa.array([size], pa.int64()), pa.array([STRIDE], pa.int32()), pa.array([marks], pa.binary()), pa.array([payload], pa.binary())], ["shard", "block", "start", "docs", "n_tokens", "stride", "checkpoints", "payload"])

        shard = 0
        for b in batches:
            for d, n, x, s in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                shard = s
                docs_in.append({"doc_id": d, "n": n})
                parts.append(x)
                size += n
                if size >= BLOCK_TOKENS:
                    yield close()
                    docs_in, parts, size, k, before = [], [], 0, k + 1, before + size
        if docs_in:
            yield close()

    ordered = tokens.repartitionByRange(int(shards), "doc_id", "tie").sortWithinPartitions("doc_id", "tie")
    ordered = ordered.select("doc_id", "n", "ids", F.spark_partition_id().alias("shard"))
    schema = "shard int, block int, start bigint, docs array<struct<doc_id: bigint, n: bigint>>, n_tokens bigint, stride int, checkpoints binary, payload binary"
    with shuffles_dropped(spark):
        ordered.mapInArrow(blocks, schema).write.option("compression", "none").parquet(f"{path}/blocks")
    drop_written(tokens)


def read_token_file(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids binary): ids as little-endian uint32, start counts the ids of all documents before."""
    return _decoded(spark, path, "ids binary", lambda raw: raw, pa.binary())


def token_digests(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) decoded from the files."""
    return _decoded(spark, path, "ids_crc32 bigint", zlib.crc32, pa.int64())


def _decoded(spark: SparkSession, path: str, column: str, made, kind: pa.DataType) -> DataFrame:
    book = spark.read.parquet(f"{path}/codebook").collect()  # bounded by the vocabulary
    stored = spark.read.parquet(f"{path}/blocks")
    # One row per shard (of some millions of ids): a running sum over them is small work at any size of the data.
    totals = stored.groupBy("shard").agg(F.sum("n_tokens").alias("n"))
    before = F.sum("n").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1))
    shards = totals.select("shard", F.coalesce(before, F.lit(0)).alias("before"))
    shards = F.broadcast(shards) if fits_broadcast(totals, BROADCAST_SHARDS) else shards
    ids, bits = np.array([r.id for r in book], np.int64), np.array([r.bits for r in book], np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code = Code(ids, bits)
        for b in batches:
            for docs, n, stride, marks, payload, start in zip(*(b.column(i).to_pylist() for i in range(6)), strict=True):
                raw = memoryview(code.decode(payload, marks, n, stride).astype("<u4").tobytes())
                lengths = np.array([d["n"] for d in docs], np.int64)
                ends = np.cumsum(lengths)
                out = [made(bytes(raw[4 * (e - k) : 4 * e])) for e, k in zip(ends.tolist(), lengths.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array([d["doc_id"] for d in docs], pa.int64()), pa.array(ends - lengths + start), pa.array(lengths), pa.array(out, kind)], ["doc_id", "start", "n_tokens", column.split()[0]])

    rows = stored.join(shards, "shard").select("docs", "n_tokens", "stride", "checkpoints", "payload", F.col("before") + F.col("start"))
    return rows.mapInArrow(run, f"doc_id bigint, start bigint, n_tokens bigint, {column}")


def token_file_path(spark: SparkSession) -> str:
    return new_path(spark, "token-file")
