"""Words and their hashes straight from Arrow's UTF-8 buffers, a block of rows at a time, without a Python object per word.

A word is a run of bytes outside one class of separators; it never crosses a row. Its hash is a polynomial over the
bytes modulo 2**64, taken from one running sum, so that a block costs a few array passes whatever its words are.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK = 1 << 19

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
_fold = np.arange(256)
_fold[65:91] += 32
_bytes = np.random.default_rng(20240229).integers(1 << 63, size=256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
FOLDED, EXACT = _bytes[_fold], _bytes
_BASE = 0x9E3779B97F4A7C15
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The base's powers and those of its inverse, at least n of them; only as many as blocks need are kept."""
    if len(_powers[0]) >= n:
        return _powers[0], _powers[1]
    size, out = max(n, 2 * BLOCK + 1), []
    for base in (_BASE, pow(_BASE, -1, 1 << 64)):
        steps = np.full(size, base, np.uint64)
        steps[0] = 1
        out.append(np.multiply.accumulate(steps))
    if size == 2 * BLOCK + 1:
        _powers[:] = out
    return out[0], out[1]


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    h = h ^ (h >> np.uint64(30))
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


def blocks(column: pa.Array | pa.ChunkedArray, size: int = BLOCK) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, offsets) for runs of rows of about size bytes; a longer row is a block of its own. Null is empty."""
    first = 0
    for part in column.chunks if isinstance(column, pa.ChunkedArray) else [column]:
        if part.null_count:
            part = pc.fill_null(part, "")
        part = part.cast(pa.large_string())
        if len(part):
            _, where, data = part.buffers()
            at = np.frombuffer(where, np.int64)[part.offset : part.offset + len(part) + 1]
            raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
            k = 0
            while k < len(part):
                end = max(k + 1, int(np.searchsorted(at, at[k] + size, side="right")) - 1)
                yield first + k, raw[at[k] : at[end]], at[k : end + 1] - at[k]
                k = end
        first += len(part)


def runs(inside: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of true bytes, cut at row borders."""
    n = len(inside)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    up, down = inside.copy(), inside.copy()
    up[1:] &= ~inside[:-1]
    down[:-1] &= ~inside[1:]
    border = offsets[1:-1]
    border = border[(border > 0) & (border < n)]
    up[border] = inside[border]
    down[border - 1] = inside[border - 1]
    return np.flatnonzero(up), np.flatnonzero(down) + 1


def hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, codes: np.ndarray = FOLDED) -> np.ndarray:
    """A 64-bit hash of each span; FOLDED takes A-Z for a-z. Spans are in order; long blocks are taken in parts."""
    if len(data) > 2 * BLOCK:
        out, k = np.zeros(len(starts), np.uint64), 0
        while k < len(starts):
            end = max(k + 1, int(np.searchsorted(ends, starts[k] + 2 * BLOCK, side="right")))
            base = starts[k]
            out[k:end] = _hashes(data[base : ends[end - 1]], starts[k:end] - base, ends[k:end] - base, codes)
            k = end
        return out
    return _hashes(data, starts, ends, codes)


def _hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, codes: np.ndarray) -> np.ndarray:
    up, down = powers(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    part = codes[data]
    part *= up[: len(data)]
    np.cumsum(part, out=total[1:])
    h = total[ends] - total[starts]
    h *= down[starts]
    h += (ends - starts).astype(np.uint64)
    return mix(h)


def words(data: np.ndarray, offsets: np.ndarray, codes: np.ndarray = FOLDED) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words between white space: starts, ends, hashes, and where each row's words begin (one more than rows)."""
    starts, ends = runs(~SPACE[data], offsets)
    return starts, ends, hashes(data, starts, ends, codes), np.searchsorted(starts, offsets)


def shingles(h: np.ndarray, n: int) -> np.ndarray:
    """A hash of every n words in a row; the caller cuts at its own borders."""
    if len(h) < n:
        return np.zeros(0, np.uint64)
    m = len(h) - n + 1
    out = h[:m].copy()
    for k in range(1, n):
        out *= np.uint64(0xD6E8FEB86659FD93)
        out += h[k : k + m]
    return mix(out)


def whole(h: np.ndarray) -> np.uint64:
    """One hash of a whole sequence, apart from all shingles by its length."""
    up, _ = powers(len(h))
    n = np.array([len(h)], np.uint64) * np.uint64(0xA0761D6478BD642F)
    return mix((h * up[: len(h)]).sum(dtype=np.uint64, keepdims=True) + n)[0]
