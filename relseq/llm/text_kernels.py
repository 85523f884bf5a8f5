"""Vectorised kernels over the bytes of Arrow string columns.

A column of texts is handled as one byte array plus offsets, cut into slices of a quarter of a megabyte, so memory
is bounded by the slice (or by one very long text) and there is no per-word Python object.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 18
U = np.uint64
# Word separators of the engine: space and the control characters tab to carriage return (fixed values).
SPACE = np.zeros(256, bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_rng = np.random.default_rng(0x5EED)
_BYTE_CODE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * U(2) + U(1)
_FOLDED_CODE = _BYTE_CODE.copy()
_FOLDED_CODE[65:91] = _BYTE_CODE[97:123]
_BYTE_CODE[SPACE] = 0
_FOLDED_CODE[SPACE] = 0
_STEP = int(_rng.integers(1, 2**60)) * 8 + 5
_PLACE = _rng.integers(1, 2**63, 64, dtype=np.uint64) * U(2) + U(1)
_powers = np.ones(1, np.uint64)


def powers(n: int, step: int = _STEP) -> np.ndarray:
    """step**0 .. step**(n-1) modulo 2**64, kept between calls for the default step."""
    global _powers
    if step == _STEP and len(_powers) >= n:
        return _powers[:n]
    size = 1 << max(10, (n - 1).bit_length())
    out = np.full(size, step, np.uint64)
    out[0] = 1
    out = np.multiply.accumulate(out)
    if step == _STEP:
        _powers = out
    return out[:n]


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply), applied element by element."""
    h = h ^ (h >> U(30))
    h = h * U(0xBF58476D1CE4E5B9)
    h ^= h >> U(27)
    h *= U(0x94D049BB133111EB)
    h ^= h >> U(31)
    return h


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (one more than rows) of a string or binary column; null reads as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    if len(column) == 0 or offsets is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def slices(data: np.ndarray, off: np.ndarray, size: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of whole texts of about ``size`` bytes: first row, end row, bytes, offsets from 0."""
    lo, n = 0, len(off) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(off, off[lo] + size, "right")) - 1)
        yield lo, hi, data[off[lo] : off[hi]], off[lo : hi + 1] - off[lo]
        lo = hi


def word_starts(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions at which words begin, and for each text the number of words before it."""
    blank = SPACE[data]
    begins = ~blank
    begins[1:] &= blank[:-1]
    first = off[:-1][off[:-1] < off[1:]]
    begins[first] = ~blank[first]
    starts = np.flatnonzero(begins)
    return starts, np.searchsorted(starts, off)


def word_hashes(data: np.ndarray, off: np.ndarray, fold: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """64-bit hash of every word (A-Z folded if asked), word bounds by text, and word starts."""
    starts, bounds = word_starts(data, off)
    if not len(starts):
        return np.zeros(0, np.uint64), bounds, starts
    at = starts[0]
    spans = np.diff(starts, append=len(data))
    place = np.arange(len(data) - at, dtype=np.int32) - np.repeat((starts - at).astype(np.int32), spans)
    terms = (_FOLDED_CODE if fold else _BYTE_CODE)[data[at:]]
    terms *= powers(int(spans.max()) + 1)[place]
    return mix(np.add.reduceat(terms, starts - at)), bounds, starts


def shingle_hashes(words: np.ndarray, bounds: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of ``width`` consecutive words inside each text; a shorter text gives its whole sequence once.

    Returns the hashes in text order and their bounds by text. Texts without words have none.
    """
    n = np.diff(bounds)
    count = np.where(n >= width, n - width + 1, (n > 0).astype(n.dtype))
    out_bounds = np.concatenate(([0], np.cumsum(count)))
    if not out_bounds[-1]:
        return np.zeros(0, np.uint64), out_bounds
    total = np.zeros(len(words), np.uint64)
    for i in range(min(width, len(words))):
        total[: len(words) - i] += words[i:] * _PLACE[i]
    owner = np.repeat(np.arange(len(n)), n)
    keep = np.arange(len(words)) + width <= bounds[1:][owner]
    short = np.flatnonzero((n > 0) & (n < width))
    for t in short:  # at most one value for each short text
        own = words[bounds[t] : bounds[t + 1]]
        total[bounds[t]] = np.add.reduce(np.append(own * _PLACE[: len(own)], _PLACE[40 + min(len(own), 20)]))
        keep[bounds[t]] = True
    return mix(total[keep]), out_bounds


# Letters for hashed-text features: ASCII letters and every byte of a multi-byte character.
LETTER = np.zeros(256, bool)
LETTER[65:91] = LETTER[97:123] = LETTER[128:] = True
_LETTER_CODE = np.where(LETTER, _FOLDED_CODE, U(0))


def letter_runs(data: np.ndarray, off: np.ndarray, prefixes: tuple[int, ...] = ()) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Hashes of maximal letter runs (A-Z folded) and of their first bytes: one array for whole runs, one for
    each length in ``prefixes`` (0 where the run is not longer); bounds by text; run starts."""
    letter = LETTER[data]
    begins = letter.copy()
    begins[1:] &= ~letter[:-1]
    first = off[:-1][off[:-1] < off[1:]]
    begins[first] = letter[first]
    starts = np.flatnonzero(begins)
    bounds = np.searchsorted(starts, off)
    if not len(starts):
        return [np.zeros(0, np.uint64)] * (1 + len(prefixes)), bounds, starts
    at = starts[0]
    spans = np.diff(starts, append=len(data))
    place = np.arange(len(data) - at, dtype=np.int32) - np.repeat((starts - at).astype(np.int32), spans)
    terms = _LETTER_CODE[data[at:]]
    terms *= powers(int(spans.max()) + 1)[place]
    sizes = np.add.reduceat(letter[at:].astype(np.int32), starts - at)
    out = [mix(np.add.reduceat(terms, starts - at))]
    for n in prefixes:
        terms[place >= max(prefixes)] = 0
        head = np.where(place < n, terms, U(0))
        out.append(np.where(sizes > n, mix(np.add.reduceat(head, starts - at) + U(n)), U(0)))
    return out, bounds, starts
