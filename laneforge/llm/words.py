"""Words of many texts at once: numpy over the bytes of an Arrow string column."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes handled at once, so that the arrays of a piece stay small; a longer text is one piece of its own.
PIECE = 1 << 19
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
SPACE = np.zeros(256, bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if n > PIECE + 1:  # for one long text, and not kept
        return _raised(_BASE, n), _raised(_INVERSE, n)
    if not _POWERS:
        _POWERS["up"], _POWERS["down"] = _raised(_BASE, PIECE + 1), _raised(_INVERSE, PIECE + 1)
    return _POWERS["up"][:n], _POWERS["down"]


def _raised(base: np.uint64, n: int) -> np.ndarray:
    a = np.full(n, base)
    a[0] = 1
    return np.multiply.accumulate(a)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection on 64 bits that spreads every bit."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def pieces(column: pa.Array, size: int = PIECE):
    """Runs of texts of about `size` bytes: (first text, offsets from 0, A-Z-lower-cased bytes). Null texts are empty."""
    column = pc.fill_null(column.cast(pa.large_string()), "")
    if not len(column):
        return
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(column.buffers()[2] or b"", np.uint8)
    at = 0
    while at < len(column):
        end = max(at + 1, int(np.searchsorted(offsets, offsets[at] + size, "right")) - 1)
        yield at, offsets[at : end + 1] - offsets[at], LOWER[data[offsets[at] : offsets[end]]]
        at = end


def word_spans(offsets: np.ndarray, data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words, and how many each text has. White space and the ends of texts divide words."""
    inside = ~SPACE[data]
    starts, ends = inside.copy(), inside.copy()
    starts[1:] &= ~inside[:-1]
    ends[:-1] &= ~inside[1:]
    bounds = offsets[1:-1]
    bounds = bounds[(bounds > 0) & (bounds < len(data))]
    starts[bounds] = inside[bounds]
    ends[bounds - 1] = inside[bounds - 1]
    first = np.flatnonzero(starts)
    return first, np.flatnonzero(ends) + 1, np.diff(np.searchsorted(first, offsets))


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word: a polynomial over its bytes, from prefix sums, then mixed."""
    up, down = _powers(len(data) + 1)
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=sums[1:])
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))
