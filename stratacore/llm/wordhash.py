"""64-bit word hashes straight from Arrow string buffers, without making Python strings."""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[32, 9, 10, 11, 12, 13]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Bytes of text hashed at a time; one longer text is taken alone.
SLICE_BYTES = 1 << 16


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_powers: dict[int, np.ndarray] = {}


def _power(base: int, n: int) -> np.ndarray:
    known = _powers.get(base)
    if known is None or len(known) < n:
        size = max(n, SLICE_BYTES + 1)
        known = np.full(size, base, _U)
        known[0] = 1
        known = np.multiply.accumulate(known)
        if size <= 4 * SLICE_BYTES:
            _powers[base] = known
    return known[:n]


class Words(NamedTuple):
    """Words of some consecutive texts: `first` row, their count `rows`, for each word its text (from 0), hash, and place in `raw`."""

    first: int
    rows: int
    text: np.ndarray
    hash: np.ndarray
    start: np.ndarray
    end: np.ndarray
    raw: bytes

    def counts(self) -> np.ndarray:
        return np.bincount(self.text, minlength=self.rows)


def hashed(column: pa.Array, lower: bool) -> Iterator[Words]:
    """The words `[^\\x20\\x09-\\x0D]+` of a string column, slice by slice; lower: A-Z are hashed as a-z. Null: no words."""
    column = column.cast(pa.large_string()) if not pa.types.is_large_string(column.type) else column
    if column.null_count:
        column = column.fill_null("")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    a = 0
    while a < len(column):
        b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + SLICE_BYTES, side="right")) - 1)
        raw = data[offsets[a] : offsets[b]]
        chars = _LOWER[raw] if lower else raw
        at = offsets[a : b + 1] - offsets[a]
        inside = np.append(~_IS_SPACE[raw], False)
        before = np.append(False, inside[:-1])
        before[at[:-1]] = False  # a text begins anew
        start = np.flatnonzero(inside & ~before)
        after = np.append(inside[1:], False)
        last = at[1:] - 1
        after[last[last >= 0]] = False
        end = np.flatnonzero(inside & ~after) + 1
        sums = np.append(_U(0), np.cumsum((chars.astype(_U) + _U(1)) * _power(_BASE, len(chars))))
        values = (sums[end] - sums[start]) * _power(_INVERSE, len(chars) + 1)[start]
        yield Words(a, b - a, np.searchsorted(at, start, side="right") - 1, mix(values ^ (end - start).astype(_U)), start, end, raw.tobytes())
        a = b


def grams(hashes: np.ndarray, size: int) -> np.ndarray:
    """Hashes of `size` consecutive words at every place (across texts too; the caller masks those)."""
    n = len(hashes) - size + 1
    if n <= 0:
        return np.zeros(0, _U)
    total = np.zeros(n, _U)
    for k in range(size):
        total = total * _U(0x2545F4914F6CDD1D) + hashes[k : k + n]
    return mix(total)


class HashTable:
    """Row numbers of 64-bit hashes: a sorted array, and a small one of recent hashes that is merged into it now and then."""

    def __init__(self):
        self.n = 0
        self.key, self.row = np.zeros(0, _U), np.zeros(0, np.int64)
        self.new_key, self.new_row = np.zeros(0, _U), np.zeros(0, np.int64)

    def find(self, key: np.ndarray) -> np.ndarray:
        """The row of each hash, or -1."""
        out = np.full(len(key), -1, np.int64)
        for k, r in ((self.key, self.row), (self.new_key, self.new_row)):
            if len(k):
                at = np.minimum(np.searchsorted(k, key), len(k) - 1)
                hit = k[at] == key
                out[hit] = r[at[hit]]
        return out

    def add(self, key: np.ndarray) -> np.ndarray:
        """Give new rows to distinct hashes that are not in the table."""
        rows = np.arange(self.n, self.n + len(key))
        self.n += len(key)
        self.new_key, self.new_row = _merged(self.new_key, self.new_row, key, rows)
        if len(self.new_key) > 4096 + len(self.key) // 8:
            self.key, self.row = _merged(self.key, self.row, self.new_key, self.new_row)
            self.new_key, self.new_row = np.zeros(0, _U), np.zeros(0, np.int64)
        return rows


def _merged(key: np.ndarray, row: np.ndarray, more_key: np.ndarray, more_row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    keys, rows = np.concatenate([key, more_key]), np.concatenate([row, more_row])
    order = np.argsort(keys, kind="stable")
    return keys[order], rows[order]


def grown(a: np.ndarray, n: int) -> np.ndarray:
    """a with room for n rows, doubled as long as it is too short."""
    if len(a) >= n:
        return a
    out = np.zeros((max(n, 2 * len(a)), *a.shape[1:]), a.dtype)
    out[: len(a)] = a
    return out


def spans(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """start[0], start[0] + 1, .. (length[0] of them), then the same for the others."""
    ends = np.cumsum(length)
    return np.repeat(start - ends + length, length) + np.arange(ends[-1] if len(ends) else 0)
