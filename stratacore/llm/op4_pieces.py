"""SentencePiece encoding and decoding by a table of distinct marked words.

The text is cut where a non-marker is followed by a marker (white space mark U+2581 or the space that becomes one).
No piece of the model may have a marker after another character (`check_model` proves it for the loaded file), so no
merge crosses a cut and each distinct marked word is segmented once per worker; its ids, their decimal form and its
decoded text are joined back by position. A join by position inside the task replaces a shuffle of every word.

Edge cases: a null or empty text has no ids and decodes to the empty text; blank-only texts keep their blanks as the
library does; very long texts are handled word by word; repeated rows and ids, extra columns: one output row per input
row; empty table: empty result.
"""

from __future__ import annotations

import functools
import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .chunks import ChunkTable

MARK = "▁"
_CHUNK = re.compile(f"[ {MARK}]*[^ {MARK}]+|[ {MARK}]+")


def check_model(sp) -> None:
    """Raise unless cuts before markers are safe: byte fallback, identity normaliser, no piece over a cut."""
    pieces = [sp.id_to_piece(i) for i in range(sp.get_piece_size())]
    if any(re.search(f"[^{MARK}]{MARK}", p) for p in pieces):
        raise ValueError("the model has pieces that cross a white space mark")
    # The normaliser must keep blanks, add one mark in front, and map nothing else.
    for probe, want in (("a  b", f"{MARK}a{MARK}{MARK}b"), ("ℌÅ", None), (" a ", f"{MARK}{MARK}a{MARK}")):
        if want and "".join(sp.encode(probe, out_type=str)) != want:
            raise ValueError("the model's normaliser changes white space")
        if sp.decode(sp.encode(probe)) != probe:
            raise ValueError("the model's normaliser changes characters")


@functools.lru_cache(maxsize=2)
def _table(model_path: str) -> ChunkTable:
    """One table per Python worker, kept from task to task: chunk -> (number of ids, ids in decimal, decoded text)."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
    check_model(sp)
    mark = sp.piece_to_id(MARK)

    def encode(chunks: list[str]) -> list[tuple[int, str, str]]:
        # The library puts the first mark back; a lone mark at the end of a text has nothing left to put it before.
        ids = [x if len(c) > 1 else [mark] for c, x in zip(chunks, sp.encode([c[1:] for c in chunks], num_threads=1), strict=True)]
        text = [" " + x if len(c) > 1 else " " for c, x in zip(chunks, sp.decode(ids, num_threads=1), strict=True)]
        return [(len(x), ",".join(map(str, x)), c if c == t else t) for c, x, t in zip(chunks, ids, text, strict=True)]

    return ChunkTable(encode)


def _chunks(text: str) -> list[str]:
    return _CHUNK.findall(" " + text)


def encode_pieces(docs: DataFrame, model_path: str, text_column: str = "text", ids_column: str = "ids", decoded_column: str = "decoded") -> DataFrame:
    """docs with two more columns: array<int> ids and the decoded text. An input column of such a name is replaced."""
    kept = docs.drop(ids_column, decoded_column)
    schema = T.StructType([*kept.schema.fields, T.StructField(ids_column, T.ArrayType(T.IntegerType())), T.StructField(decoded_column, T.StringType())])
    at = kept.columns.index(text_column)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _table(model_path)
        for b in batches:
            found = list(table.of_texts(b.column(at).to_pylist(), _chunks))
            ids = pa.array([[int(i) for x in f for i in x[1].split(",")] for f in found], pa.list_(pa.int32()))
            text = pa.array(["".join([x[2] for x in f])[1:] for f in found], pa.string())
            yield pa.RecordBatch.from_arrays([*b.columns, ids, text], [*b.schema.names, ids_column, decoded_column])

    return kept.mapInArrow(run, schema)


def piece_digests(docs: DataFrame, model_path: str, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of the same encoding, without moving the ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _table(model_path)
        sha = lambda s: hashlib.sha256(s.encode("utf-8")).hexdigest()
        for b in batches:
            n, ids, text = [], [], []
            for found in table.of_texts(b.column(1).to_pylist(), _chunks):
                n.append(sum([x[0] for x in found]))
                ids.append(sha(",".join([x[1] for x in found])))
                text.append(sha("".join([x[2] for x in found])[1:]))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(ids), pa.array(text)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    rows = docs.select(F.col(id_column).cast("long").alias("doc_id"), F.col(text_column).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
