"""Vectorised words and word hashes over Arrow string columns.

A word is a longest run of bytes other than space and U+0009 to U+000D. Every function works on the
column's own UTF-8 buffer, so no Python object is made per word. Null texts count as empty.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 20
"""Bytes hashed at once: the working set of word_hashes, whatever a text's length."""

U = np.uint64
_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BASE = 0x9E6C63D0876A9A47 | 1
_BYTE = np.random.default_rng(20240607).integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


class _Powers:
    up = np.ones(1, np.uint64)
    down = np.ones(1, np.uint64)

    @classmethod
    def to(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(cls.up) < n:
            n = max(n, SLICE_BYTES)
            full = np.full(n, U(_BASE))
            full[0] = U(1)
            cls.up = np.cumprod(full, dtype=np.uint64)
            full[1:] = U(pow(_BASE, -1, 2**64))
            cls.down = np.cumprod(full, dtype=np.uint64)
        return cls.up, cls.down


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The column's bytes and its n + 1 offsets into them, from 0."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def word_spans(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and for each text its first word's index (n + 1 entries)."""
    if not len(raw):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(off), np.int64)
    word = np.zeros(len(raw) + 2, bool)
    word[1:-1] = ~_IS_SPACE[raw]
    edge = np.zeros(len(raw) + 1, bool)
    edge[off] = True
    starts = np.flatnonzero(word[1:-1] & (~word[:-2] | edge[:-1]))
    ends = np.flatnonzero(word[1:-1] & (~word[2:] | edge[1:])) + 1
    return starts, ends, np.searchsorted(starts, off)


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool) -> np.ndarray:
    """A 64-bit hash of each word's bytes (A-Z lower-cased first on request)."""
    out = np.empty(len(starts), np.uint64)
    at = 0
    while at < len(starts):
        to = max(at + 1, int(np.searchsorted(ends, starts[at] + SLICE_BYTES, "right")))
        s, e = starts[at], ends[to - 1]
        piece = raw[s:e]
        up, down = _Powers.to(e - s + 1)
        sums = np.zeros(e - s + 1, np.uint64)
        np.cumsum(_BYTE[_LOWER[piece] if lower else piece] * up[: e - s], out=sums[1:], dtype=np.uint64)
        lo, hi = starts[at:to] - s, ends[at:to] - s
        out[at:to] = mix((sums[hi] - sums[lo]) * down[lo] + (hi - lo).astype(np.uint64))
        at = to
    return out


def gram_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all runs of k neighbouring words, in place of their first; runs may cross texts."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    acc = words[:n].copy()
    for i in range(1, k):
        acc = acc * U(0xD6E8FEB86659FD93) + words[i : i + n]
    return mix(acc)


def slices(batch: pa.RecordBatch, column: str, most: int = 1 << 21) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows whose texts have about `most` bytes together; a longer text comes alone."""
    at = batch.schema.get_field_index(column)
    _, off = text_buffer(batch.column(at))
    i = 0
    while i < batch.num_rows:
        j = max(i + 1, int(np.searchsorted(off, off[i] + most, "right")) - 1)
        yield batch.slice(i, j - i)
        i = j
