"""Numpy kernels over Arrow text columns, shared by the operators that run on Arrow batches.

Texts are never turned into Python strings here: a string column is an offsets array and a
byte buffer, and words, hashes and shingles are arrays computed for many documents at once.
Batches are cut into slices of bounded bytes, so temporary memory does not follow the batch;
one document longer than a slice is a slice of its own and is hashed segment by segment.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLICE_BYTES = 1 << 19
SEGMENT = 1 << 20
_R = 0x9E3779B97F4A7C15
_RINV = pow(_R, -1, 1 << 64)


@lru_cache(maxsize=2)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    out = []
    for base in (_R, _RINV):
        x = np.full(n, base, dtype=np.uint64)
        x[0] = 1
        out.append(np.cumprod(x, dtype=np.uint64))
    return out[0], out[1]


def mix(h: np.ndarray) -> np.ndarray:
    """Finalizer of a 64-bit mixer, on a uint64 array."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def space_lut() -> np.ndarray:
    """True for bytes of words split at white space: all but 0x20 and 0x09-0x0D."""
    lut = np.ones(256, dtype=bool)
    lut[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = False
    return lut


def alnum_lut() -> np.ndarray:
    """True for ASCII letters and digits and for every byte of a longer character."""
    lut = np.zeros(256, dtype=bool)
    lut[0x30:0x3A] = lut[0x41:0x5B] = lut[0x61:0x7B] = True
    lut[0x80:] = True
    return lut


SPACE_WORDS, ALNUM_WORDS = space_lut(), alnum_lut()
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32


def slices(column: pa.Array, most: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets from 0) for runs of rows of at most `most` bytes.
    Null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    if not n:
        return
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_binary())
    _, offs, data = column.buffers()
    off = np.frombuffer(offs, dtype=np.int64)[column.offset : column.offset + n + 1]
    buf = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    i = 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + most, side="right")) - 1)
        j = min(j, n)
        yield i, j, buf[off[i] : off[j]], off[i : j + 1] - off[i]
        i = j


def lowered(column: pa.Array) -> pa.Array:
    """Lower case in every script; ASCII alone where the text isn't valid UTF-8."""
    try:
        return pc.utf8_lower(column)
    except pa.ArrowInvalid:
        return pc.ascii_lower(column)


def words(data: np.ndarray, offsets: np.ndarray, lut: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends (byte positions) of all words, and the number of words of each document."""
    n = len(data)
    inside = np.zeros(n + 1, dtype=bool)
    if n:
        inside[:n] = lut[data]
    prev = np.zeros(n + 1, dtype=bool)
    prev[1:] = inside[:n]
    cut = np.zeros(n + 1, dtype=bool)
    cut[offsets] = True  # a document's first byte begins a word even where the one before has not ended
    starts = np.flatnonzero(inside & (~prev | cut))
    ends = np.flatnonzero(prev & (~inside | cut))
    counts = np.diff(np.searchsorted(starts, offsets))
    return starts, ends, counts


def hash_words(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool = True) -> np.ndarray:
    """64-bit hashes of the words; A-Z count as a-z if `lower`."""
    out = np.zeros(len(starts), dtype=np.uint64)
    i = 0
    while i < len(starts):
        j = max(i + 1, int(np.searchsorted(ends, starts[i] + SEGMENT, side="right")))
        lo, hi = int(starts[i]), int(ends[j - 1])
        seg = data[lo:hi]
        if lower:
            seg = LOWER[seg]
        size = 1 << max(12, int(hi - lo).bit_length())
        pw, inv = _powers(size)
        acc = np.zeros(hi - lo + 1, dtype=np.uint64)
        np.cumsum((seg.astype(np.uint64) + np.uint64(1)) * pw[: hi - lo], out=acc[1:])
        s, e = starts[i:j] - lo, ends[i:j] - lo
        h = (acc[e] - acc[s]) * inv[s]
        out[i:j] = mix(h + (e - s).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
        i = j
    return out


def shingles(h: np.ndarray, counts: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all k-word shingles, document after document, and how many each has. A document
    of 1 to k-1 words has one: its whole sequence."""
    n = np.where(counts >= k, counts - k + 1, (counts > 0).astype(counts.dtype))
    first = np.cumsum(counts) - counts
    total = int(n.sum())
    doc = np.repeat(np.arange(len(counts)), n)
    at = np.arange(total) - np.repeat(np.cumsum(n) - n, n) + first[doc]
    size = np.minimum(counts, k)[doc]
    out = np.zeros(total, dtype=np.uint64)
    for i in range(k):
        live = i < size
        if live.all():
            out = out * np.uint64(_R) + h[at + i]
        else:
            out[live] = out[live] * np.uint64(_R) + h[at[live] + i]
    return mix(out + size.astype(np.uint64)), n


def distinct(values: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of each document, and how many."""
    v = values.copy()
    ends = np.cumsum(counts)
    first = ends - counts
    for a, b in zip(first.tolist(), ends.tolist(), strict=True):
        v[a:b].sort()
    keep = np.ones(len(v), dtype=bool)
    keep[1:] = v[1:] != v[:-1]
    keep[first[counts > 0]] = True
    total = np.concatenate([[0], np.cumsum(keep)])
    return v[keep], total[ends] - total[first]
