"""Vectorised text primitives over Arrow string buffers (numpy, no Python objects per word).

A *word* is a maximal run of ASCII letters, digits, underscore or non-ASCII bytes; letters A-Z are
folded to lower case. A *mark* is any other byte that is not white space. Hashes are 64-bit, do not
depend on the process, and are the same on every executor.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text that one vectorised step works on (a longer document is a step of its own).
STEP_BYTES = 2 << 20
_WINDOW = 1 << 21

_BYTES = np.arange(256)
_IS_WORD = (
    ((_BYTES >= 48) & (_BYTES <= 57))
    | ((_BYTES >= 65) & (_BYTES <= 90))
    | ((_BYTES >= 97) & (_BYTES <= 122))
    | (_BYTES == 95)
    | (_BYTES >= 128)
)
_IS_SPACE = (_BYTES == 32) | ((_BYTES >= 9) & (_BYTES <= 13))
_LOWER = np.where((_BYTES >= 65) & (_BYTES <= 90), _BYTES + 32, _BYTES).astype(np.uint8)

_BASE = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of unsigned 64-bit values (the finaliser of splitmix64)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _powers_upto(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(12, int(n - 1).bit_length())
    if size not in _powers:
        _powers.clear()
        up, down = np.full(size, _BASE), np.full(size, _INVERSE)
        up[0] = down[0] = 1
        _powers[size] = np.multiply.accumulate(up), np.multiply.accumulate(down)
    return _powers[size]


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all rows and the offsets of each row; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None and at[-1] > at[0] else np.zeros(0, np.uint8)
    return raw, at - at[0]


def steps(batches: Iterator[pa.RecordBatch], column: str, most: int = STEP_BYTES) -> Iterator[pa.RecordBatch]:
    """The same rows in slices of about *most* bytes of text."""
    for batch in batches:
        text = batch.column(column)
        sizes = pc.fill_null(pc.binary_length(text), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        total = np.cumsum(sizes)
        first = 0
        while first < batch.num_rows:
            done = total[first - 1] if first else 0
            last = max(first + 1, int(np.searchsorted(total, done + most, side="right")))
            yield batch.slice(first, last - first)
            first = last


def tokens(raw: np.ndarray, offsets: np.ndarray, marks: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of words in the bytes, and the index of the first word of each row (rows + 1).

    With *marks*, every mark is a token of its own as well.
    """
    is_word = _IS_WORD[raw]
    first = np.zeros(len(raw) + 1, bool)
    first[offsets] = True
    before = np.empty(len(raw), bool)
    if len(raw):
        before[0] = False
        before[1:] = is_word[:-1]
    starts = is_word & (~before | first[:-1])
    after = np.empty(len(raw), bool)
    if len(raw):
        after[-1] = False
        after[:-1] = is_word[1:]
    ends = is_word & (~after | first[1:])
    if marks:
        lone = ~is_word & ~_IS_SPACE[raw]
        starts |= lone
        ends |= lone
    s, e = np.flatnonzero(starts), np.flatnonzero(ends) + 1
    return s, e, np.searchsorted(s, offsets)


def token_hashes(raw: np.ndarray, s: np.ndarray, e: np.ndarray, fold: bool = True) -> np.ndarray:
    """64-bit hash of each span of the bytes, in windows of bounded memory."""
    out = np.empty(len(s), np.uint64)
    i = 0
    while i < len(s):
        j = max(i + 1, int(np.searchsorted(e, s[i] + _WINDOW, side="right")))
        a, b = int(s[i]), int(e[j - 1])
        part = raw[a:b]
        up, down = _powers_upto(b - a + 1)
        total = np.zeros(b - a + 1, np.uint64)
        np.cumsum(((_LOWER[part] if fold else part).astype(np.uint64) + np.uint64(1)) * up[: b - a], out=total[1:])
        left, right = s[i:j] - a, e[i:j] - a
        out[i:j] = (total[right] - total[left]) * down[left] + (right - left).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
        i = j
    return mix(out)


def grams(words: np.ndarray, first: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all n-grams of words, row by row, and the index of the first gram of each row.

    A row of 1 to n-1 words has one gram of all its words; a row without words has none.
    """
    count = np.diff(first)
    size = np.where(count >= n, count - n + 1, np.minimum(count, 1))
    begin = np.concatenate([[0], np.cumsum(size)])
    if not begin[-1]:
        return np.zeros(0, np.uint64), begin
    factors = mix(np.arange(1, n + 1, dtype=np.uint64)) | np.uint64(1)
    padded = np.concatenate([words, np.zeros(n, np.uint64)])
    row = np.repeat(np.arange(len(count)), size)
    at = np.arange(begin[-1]) - begin[row] + first[row]
    out = np.zeros(begin[-1], np.uint64)
    for k in range(n):
        part = padded[at + k] * factors[k]
        out += np.where(k < count[row], part, np.uint64(0)) if (count < n).any() else part
    return mix(out), begin


def distinct_per_row(values: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of each row, and the index of the first of each row."""
    row = np.repeat(np.arange(len(begin) - 1), np.diff(begin))
    order = np.lexsort((values, row))
    values, row = values[order], row[order]
    keep = np.ones(len(values), bool)
    keep[1:] = (values[1:] != values[:-1]) | (row[1:] != row[:-1])
    return values[keep], np.concatenate([[0], np.cumsum(np.bincount(row[keep], minlength=len(begin) - 1))]).astype(np.int64)


def segment_sum(values: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """Sum of the values of each row (0 for a row without values)."""
    total = np.concatenate([[0], np.cumsum(values, dtype=np.float64)])
    return total[begin[1:]] - total[begin[:-1]]


def segment_min(values: np.ndarray, begin: np.ndarray, empty) -> np.ndarray:
    """Least value of each row; *empty* for a row without values."""
    count = np.diff(begin)
    out = np.full(len(count), empty, values.dtype)
    full = np.flatnonzero(count > 0)
    if len(full):
        out[full] = np.minimum.reduceat(values, begin[:-1][full])
    return out
