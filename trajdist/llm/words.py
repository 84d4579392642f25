"""White-space words of Arrow string columns as 64-bit hashes, without a Python loop per word.

A word is a maximal run of bytes outside 0x20 and 0x09-0x0D.  ``hash_words`` reads the value
buffer of a column directly, in segments of bounded size that are cut between words, so memory
follows the segment and the number of words, not the length of a text.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa

SEGMENT = 1 << 20
SEPARATOR = np.zeros(256, bool)
SEPARATOR[[0x20, *range(0x09, 0x0E)]] = True

_M = (1 << 64) - 1
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit values (xor-shift and multiply)."""
    h = h ^ (h >> np.uint64(31))
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xA0761D6478BD642F)
    h ^= h >> np.uint64(32)
    return h


def mix_int(x: int) -> int:
    return int(mix(np.array([x & _M], np.uint64))[0])


def _byte_codes(lower: bool) -> np.ndarray:
    b = np.arange(256, dtype=np.uint64)
    if lower:
        b[65:91] += 32
    return mix(b + np.uint64(0x5851F42D4C957F2D))


_CODES = {lower: _byte_codes(lower) for lower in (False, True)}
_powers: dict[str, np.ndarray] = {}


def _power_table(n: int) -> tuple[np.ndarray, np.ndarray]:
    have = _powers.get("up")
    if have is None or len(have) < n:
        size = max(n, SEGMENT + 4096)
        for name, base in (("up", _BASE), ("down", _INVERSE)):
            a = np.full(size, base, np.uint64)
            a[0] = 1
            _powers[name] = np.cumprod(a)
    return _powers["up"], _powers["down"]


class Words(NamedTuple):
    """Hashes of all words of a column, and where each row's words begin (one more than rows)."""

    hashes: np.ndarray
    bounds: np.ndarray


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a string or binary column; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null(b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    kind = np.int64 if wide else np.int32
    _, offsets, data = column.buffers()
    if len(column) == 0 or offsets is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    off = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, off - off[0]


def slices(batch: pa.RecordBatch, column: int, most: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """Consecutive rows of a batch with at most ``most`` bytes of text together; a longer text stands alone."""
    _, offsets = text_buffer(batch.column(column))
    at, n = 0, batch.num_rows
    while at < n:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + most, "right")) - 1)
        yield batch.slice(at, to - at)
        at = to


def _segments(data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[int, int]]:
    """Byte ranges of about SEGMENT bytes that end at a row's end or before a separator."""
    at, end = 0, len(data)
    while at < end:
        to = at + SEGMENT
        if to >= end:
            yield at, end
            return
        row_end = int(offsets[np.searchsorted(offsets, to, "right") - 1])
        if row_end > at:
            to = row_end
        else:
            seps = np.flatnonzero(SEPARATOR[data[at + 1 : to]])
            if len(seps):
                to = at + 1 + int(seps[-1])
            else:  # one word longer than a segment
                row_to = int(offsets[np.searchsorted(offsets, at, "right")])
                later = np.flatnonzero(SEPARATOR[data[to:row_to]])
                to = to + int(later[0]) if len(later) else row_to
        yield at, to
        at = to


def word_spans(data: np.ndarray, offsets: np.ndarray, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words in data[lo:hi], relative to lo."""
    inside = ~SEPARATOR[data[lo:hi]]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    cuts = offsets[np.searchsorted(offsets, lo, "right") : np.searchsorted(offsets, hi, "left")] - lo
    if len(cuts):
        first[cuts] = inside[cuts]
        last[cuts - 1] = inside[cuts - 1]
    return np.flatnonzero(first), np.flatnonzero(last) + 1


def hash_words(column: pa.Array, lower: bool = True) -> Words:
    """Hashes of the words of each row; equal words (A-Z folded if ``lower``) have equal hashes."""
    data, offsets = text_buffer(column)
    codes = _CODES[lower]
    parts, begins = [], []
    for lo, hi in _segments(data, offsets):
        up, down = _power_table(hi - lo + 1)
        total = np.empty(hi - lo + 1, np.uint64)
        total[0] = 0
        np.cumsum(codes[data[lo:hi]] * up[: hi - lo], out=total[1:])
        a, b = word_spans(data, offsets, lo, hi)
        parts.append(mix((total[b] - total[a]) * down[a] + (b - a).astype(np.uint64)))
        begins.append(a + lo)
    if not parts:
        return Words(np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64))
    begin = np.concatenate(begins)
    return Words(np.concatenate(parts), np.searchsorted(begin, offsets, "left"))


def grams(words: Words, n: int, short: bool = False) -> Words:
    """Hashes of the n consecutive words at each place of each row.

    With ``short`` a row of fewer words, but not none, has its whole sequence as one gram."""
    h, bounds = words
    sizes = np.diff(bounds)
    counts = np.maximum(sizes - n + 1, 0)
    if len(h) >= n:
        total = np.zeros(len(h) - n + 1, np.uint64)
        for k in range(n):
            total = total * np.uint64(_BASE) + h[k : len(h) - n + 1 + k]
        total = mix(total + np.uint64(n))
    else:
        total = np.zeros(0, np.uint64)
    rows = np.flatnonzero(counts)
    keep = np.zeros(len(total) + 1, np.int64)
    if len(rows):
        np.add.at(keep, bounds[rows], 1)
        np.add.at(keep, bounds[rows] + counts[rows], -1)
    kept = total[np.cumsum(keep)[: len(total)] > 0]
    if short and (few := np.flatnonzero((sizes > 0) & (sizes < n))).size:
        whole = np.empty(len(few), np.uint64)
        for i, r in enumerate(few):
            x = 0
            for v in h[bounds[r] : bounds[r + 1]].tolist():
                x = (x * _BASE + v) & _M
            whole[i] = mix_int(x + int(sizes[r]) + (1 << 40))
        at = np.concatenate([[0], np.cumsum(counts)])[few]
        kept = np.insert(kept, at, whole)
        counts = counts.copy()
        counts[few] = 1
    return Words(kept, np.concatenate([[0], np.cumsum(counts)]))
