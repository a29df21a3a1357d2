"""Vectorised word and shingle hashing over Arrow string buffers.

Words are runs of bytes outside ``\\x20\\x09-\\x0D`` after lower-casing A-Z, as in the operator contracts. A batch is
cut into chunks of whole documents, so memory follows the chunk and not the batch; a single longer document is
its own chunk.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_BLANK = np.zeros(256, dtype=bool)
_BLANK[[32, 9, 10, 11, 12, 13]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
# odd multipliers of the polynomial and mixing hashes
_BASE = np.uint64(0x9E3779B97F4A7C15)
_STEP = np.uint64(0xD6E8FEB86659FD93)
_M1 = np.uint64(0xBF58476D1CE4E5B9)
_M2 = np.uint64(0x94D049BB133111EB)
CHUNK_BYTES = 1 << 19

_powers = np.ones(1, dtype=np.uint64)


def _pow_table(n: int) -> np.ndarray:
    global _powers
    if len(_powers) < n:
        grown = np.full(max(n, 2 * len(_powers), 64), _BASE, dtype=np.uint64)
        grown[0] = 1
        _powers = np.multiply.accumulate(grown)
    return _powers


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    x = x ^ (x >> np.uint64(30))
    x = x * _M1
    x = x ^ (x >> np.uint64(27))
    x = x * _M2
    return x ^ (x >> np.uint64(31))


def buffers(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null counts as empty."""
    col = col.fill_null("") if col.null_count else col
    col = col.cast(pa.large_string())
    _, off, data = col.buffers()
    offsets = np.frombuffer(off, dtype=np.int64)[col.offset : col.offset + len(col) + 1] if len(col) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw, offsets


def chunks(offsets: np.ndarray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges whose texts hold about ``limit`` bytes."""
    row, n = 0, len(offsets) - 1
    while row < n:
        end = int(np.searchsorted(offsets, offsets[row] + limit, side="right")) - 1
        end = min(n, max(row + 1, end))
        yield row, end
        row = end


def lowered(b: np.ndarray) -> np.ndarray:
    """Bytes with A-Z in lower case."""
    return _LOWER[b]


def word_hashes(raw: np.ndarray, offsets: np.ndarray, blank: np.ndarray = _BLANK) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word hashes of the documents of one chunk, each document's word range, and each word's byte start in the chunk."""
    base = int(offsets[0])
    b = raw[base : int(offsets[-1])]
    local = (offsets - base).astype(np.int64)
    if not len(b):
        return np.zeros(0, np.uint64), np.zeros(len(local), np.int64), np.zeros(0, np.int64)
    b = _LOWER[b]
    solid = ~blank[b]
    first = np.empty(len(b), dtype=bool)
    first[0] = solid[0]
    np.logical_and(solid[1:], ~solid[:-1], out=first[1:])
    heads = local[:-1][local[:-1] < len(b)]
    first[heads] = solid[heads]
    starts = np.flatnonzero(first)
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(len(local), np.int64), starts
    lens = np.diff(np.append(starts, len(b)))
    at = np.arange(starts[0], len(b)) - np.repeat(starts, lens)
    v = (b[starts[0] :].astype(np.uint64) + np.uint64(1)) * solid[starts[0] :]
    v *= _pow_table(int(lens.max()))[at]
    return mix(np.add.reduceat(v, starts - starts[0])), np.searchsorted(starts, local), starts


def shingle_hashes(words: np.ndarray, bounds: np.ndarray, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every k-word shingle and each document's shingle range; a shorter document is one shingle, an empty one none."""
    n = np.diff(bounds)
    out_n = np.where(n >= k, n - k + 1, (n > 0).astype(np.int64))
    ends = np.concatenate(([0], np.cumsum(out_n)))
    out = np.empty(int(ends[-1]), dtype=np.uint64)
    if len(words) >= k:
        h = words[: len(words) - k + 1].copy()
        for j in range(1, k):
            h *= _STEP
            h += words[j : len(words) - k + 1 + j]
        h = mix(h)
        # a shingle's place in `words` is its place in `out` plus what shorter and earlier documents shift it by
        long = n >= k
        own = np.repeat(long, out_n)
        out[own] = h[(np.arange(len(out)) + np.repeat(bounds[:-1] - ends[:-1], out_n))[own]]
    for d in np.flatnonzero((n > 0) & (n < k)):
        h = np.array([n[d]], dtype=np.uint64)
        for w in words[bounds[d] : bounds[d + 1]]:
            h = h * _STEP + w
        out[ends[d]] = mix(h)[0]
    return out, ends


def documents_of(batch: pa.RecordBatch, text: str = "text") -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """(first row, row end, word hashes, word ranges, byte starts) for each chunk of a record batch."""
    raw, offsets = buffers(batch.column(text))
    for a, b in chunks(offsets):
        yield a, b, *word_hashes(raw, offsets[a : b + 1])
