"""Benchmark decontamination: pigeonhole pieces, then Myers' bit-parallel distance.

An item occurs in a text when some substring of the normalised text (A-Z and other letters lower-cased, white space
runs as one space) is within floor(ERROR_RATE * length) edits of the normalised item. An item with budget k is cut
into k + 1 pieces; any occurrence holds one piece unchanged, so an automaton over all pieces finds every candidate
place, and the bit-parallel distance decides each. Items form the query set; they are taken in blocks of at most
BLOCK_CHARS characters, each a scan over all documents, so the automaton's size is bounded.

Items under SHORT_ITEM normalised characters have no error budget and must stand in the text as whole words, since
parts of words would hold them by chance. Every other item is searched by the rule above.

Edge cases: null or empty texts hold no item; null and empty items occur nowhere; an item with a null id is searched and
reported as a null in item_ids; equal items are all reported; very long texts are scanned whole, and only candidate
places are verified; repeated rows give repeated results; empty tables: no hits; other columns are ignored.
"""

from __future__ import annotations

import functools
from collections import defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ERROR_RATE = 0.08
SHORT_ITEM = 24
BLOCK_CHARS = 4_000_000


def normalised(text: str) -> str:
    return " ".join(text.lower().split())


def pieces(item: str, rate: float = ERROR_RATE) -> tuple[int, list[tuple[int, str]]]:
    """Error budget, and budget + 1 pieces with their offsets, of lengths that differ by one at most."""
    k = int(rate * len(item)) if len(item) >= SHORT_ITEM else 0
    cuts = [len(item) * i // (k + 1) for i in range(k + 2)]
    return k, [(a, item[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]


def best_distance(masks: dict[str, int], m: int, text: str) -> tuple[int, int]:
    """Least edit distance of the pattern to any substring, and where that substring ends (the first such)."""
    ones, high = (1 << m) - 1, 1 << (m - 1)
    rise, fall, score, best, end = ones, 0, m, m, 0  # vertical differences of +1 and of -1
    get = masks.get
    for j, c in enumerate(text, 1):
        eq = get(c, 0)
        flat = (((eq & rise) + rise) ^ rise) | eq | fall
        right = fall | (ones & ~(flat | rise))  # horizontal differences
        left = rise & flat
        if right & high:
            score += 1
        elif left & high:
            score -= 1
        right, left = (right << 1) & ones, (left << 1) & ones
        stay = eq | fall
        rise, fall = left | (ones & ~(stay | right)), right & stay
        if score < best:
            best, end = score, j
    return best, end


@functools.lru_cache(maxsize=2)
def _automaton(items: tuple[tuple[int, str], ...], rate: float):
    import ahocorasick

    places, known = defaultdict(list), []
    for n, (item_id, text) in enumerate(items):
        k, parts = pieces(text, rate)
        masks: dict[str, int] = defaultdict(int)
        for i, c in enumerate(text):
            masks[c] |= 1 << i
        known.append((item_id, text, k, dict(masks)))
        for at, part in parts:
            places[part].append((n, at + len(part)))
    found = ahocorasick.Automaton()
    for part, where in places.items():
        found.add_word(part, where)
    found.make_automaton()
    return found, known


def _whole_words(text: str, start: int, end: int) -> bool:
    return not (start and text[start - 1].isalnum() and text[start].isalnum()) and not (end < len(text) and text[end].isalnum() and text[end - 1].isalnum())


def hits(text: str, automaton, known) -> list[tuple[int | None, int]]:
    """(item id, distance) of every item that occurs in a normalised text."""
    spots: dict[int, list[int]] = defaultdict(list)
    for end, where in automaton.iter(text):
        for n, offset in where:
            spots[n].append(end + 1 - offset)
    out = []
    for n, starts in spots.items():
        item_id, item, k, masks = known[n]
        m, best = len(item), len(item)
        if m < SHORT_ITEM:
            best = 0 if any(_whole_words(text, s, s + m) for s in starts) else m
        elif k == 0 or item in text:
            best = 0
        else:
            low, high = None, None
            for s in [*sorted(set(starts)), None]:
                if low is not None and (s is None or s - k > high):
                    best = min(best, best_distance(masks, m, text[low:high])[0])
                    low = None
                if s is not None:
                    low, high = max(0, s - k) if low is None else low, s + m + k
        if best <= k:
            out.append((item_id, best))
    return sorted(out, key=lambda h: (h[0] is not None, h))


def _blocks(items: DataFrame, id_column: str, text_column: str, most: int) -> Iterator[tuple[tuple[int, str], ...]]:
    block, size = [], 0
    for r in items.select(F.col(id_column).cast("long"), F.col(text_column)).orderBy(id_column).toLocalIterator():
        text = normalised(r[1] or "")
        if text:
            block.append((r[0], text))
            size += len(text)
            if size >= most:
                yield tuple(block)
                block, size = [], 0
    if block:
        yield tuple(block)


def contamination(docs: DataFrame, items: DataFrame, text_column: str = "text", item_id: str = "item_id", item_text: str = "text", rate: float = ERROR_RATE, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """docs with item_ids array<long> and distances array<int> of the items in each text (such columns are replaced)."""
    docs = docs.drop("item_ids", "distances")
    none = docs.withColumns({"item_ids": F.array().cast("array<bigint>"), "distances": F.array().cast("array<int>")})
    for block in _blocks(items, item_id, item_text, block_chars):
        none = _with_block(none, block, text_column, rate)
    return none


def _with_block(docs: DataFrame, block: tuple[tuple[int, str], ...], text_column: str, rate: float) -> DataFrame:
    names = docs.columns
    at, ids_at, dist_at = names.index(text_column), names.index("item_ids"), names.index("distances")
    items = docs.sparkSession.sparkContext.broadcast(block)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton, known = _automaton(items.value, rate)
        for b in batches:
            found = [hits(normalised(t), automaton, known) if t else [] for t in b.column(at).to_pylist()]
            ids = [x + [h[0] for h in f] for x, f in zip(b.column(ids_at).to_pylist(), found, strict=True)]
            far = [x + [h[1] for h in f] for x, f in zip(b.column(dist_at).to_pylist(), found, strict=True)]
            columns = list(b.columns)
            columns[ids_at], columns[dist_at] = pa.array(ids, pa.list_(pa.int64())), pa.array(far, pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays(columns, names)

    return docs.mapInArrow(run, docs.schema)
