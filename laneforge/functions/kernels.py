"""Numpy kernels: deltas, widths, packing. Arrays play the part of vector registers: one operation serves many blocks."""

from __future__ import annotations

import numpy as np

U32, U64 = np.uint32, np.uint64


def bit_length(v: np.ndarray) -> np.ndarray:
    """Bits of each unsigned integer below 2^53: the exponent field of its exact float64; 0 for 0."""
    return np.maximum((v.astype(np.float64).view(np.int64) >> 52) - 1022, 0)


#: Values that the in-place differences copy at a time.
PIECE = 1 << 12


def delta(x: np.ndarray, stride: int = 1, out: np.ndarray | None = None) -> np.ndarray:
    """Differences to the value `stride` places before; the first `stride` values stay.

    In place where out is x: from the last places down, a piece at a time, so a value is read before it is overwritten
    and nothing but one piece is ever copied.
    """
    if out is x:
        for end in range(len(x), stride, -PIECE):
            at = max(stride, end - PIECE)
            x[at:end] -= x[at - stride : end - stride].copy()
        return x
    d = x.copy()
    d[stride:] -= x[:-stride] if len(x) > stride else x[:0]
    return d


def undelta(d: np.ndarray, stride: int = 1, out: np.ndarray | None = None) -> np.ndarray:
    """The inverse: prefix sums, `stride` of them side by side."""
    if stride == 1:
        return np.cumsum(d, out=out, dtype=d.dtype)
    n = len(d)
    full = n - n % stride
    x = d.copy() if out is None else out
    rows = x[:full].reshape(-1, stride)
    np.cumsum(d[:full].reshape(-1, stride), axis=0, out=rows)
    for i in range(full, n):
        x[i] = d[i] + (x[i - stride] if i >= stride else 0)
    return x


def undelta_many(d: np.ndarray, offsets: np.ndarray, stride: int) -> np.ndarray:
    """Prefix sums within each chunk of a flat buffer, `stride` lanes side by side.

    Chunks are padded to whole rows of lanes, so that every lane is a column of one running sum.
    """
    n = np.diff(offsets)
    if stride == 1:
        total = np.concatenate([[0], np.cumsum(d, dtype=np.int64)])
        return total[1:] - np.repeat(total[offsets[:-1]], n)
    first = np.concatenate([[0], np.cumsum(-(-n // stride))])
    padding = len(n) > 1 and bool((n[:-1] % stride).any())
    place = np.arange(len(d)) + np.repeat(stride * first[:-1] - offsets[:-1], n) if padding else slice(0, len(d))
    padded = np.zeros(int(first[-1]) * stride, np.int64)
    padded[place] = d
    total = np.zeros((int(first[-1]) + 1, stride), np.int64)
    np.cumsum(padded.reshape(-1, stride), axis=0, out=total[1:])
    own = total[1:]
    if len(n) > 1:
        own = own - np.repeat(total[first[:-1]], np.diff(first), axis=0)
    return own.reshape(-1)[place]


def or_widths(blocks: np.ndarray) -> np.ndarray:
    """Width that all values of each row fit in: one logarithm of the OR of the row."""
    return bit_length(np.bitwise_or.reduce(blocks, axis=1)) if blocks.size else np.zeros(len(blocks), np.int64)


#: Rows that the scalar kernels handle at once: their values stay in the cache.
ROWS = 2048


def pack_scalar(blocks: np.ndarray, b: int, mask: bool = False) -> np.ndarray:
    """Rows of k values of b bits -> rows of ceil(k b / 32) words; values follow each other and may cross words.

    The values at one place of all rows of a tile are one contiguous vector.
    """
    m, k = blocks.shape
    out = np.zeros((m, -(-k * b // 32)), U32)
    for at in range(0, m if b else 0, ROWS):
        v = np.ascontiguousarray(blocks[at : at + ROWS].T, U32)
        if mask and b < 32:
            v &= U32((1 << b) - 1)
        words = np.zeros((out.shape[1], v.shape[1]), U32)
        for i in range(k):
            w, s = divmod(i * b, 32)
            words[w] |= v[i] << U32(s) if s else v[i]
            if s + b > 32:
                words[w + 1] |= v[i] >> U32(32 - s)
        out[at : at + ROWS] = words.T
    return out


def unpack_scalar(words: np.ndarray, b: int, k: int, dtype=U64) -> np.ndarray:
    m = len(words)
    if not b:
        return np.zeros((m, k), dtype)
    out, low = np.empty((m, k), dtype), U32((1 << b) - 1 if b < 32 else 0xFFFFFFFF)
    for at in range(0, m, ROWS):
        w32 = np.ascontiguousarray(words[at : at + ROWS].T, U32)
        v = np.empty((k, w32.shape[1]), U32)
        for i in range(k):
            w, s = divmod(i * b, 32)
            np.right_shift(w32[w], U32(s), out=v[i])
            if s + b > 32:
                v[i] |= w32[w + 1] << U32(32 - s)
        v &= low
        out[at : at + ROWS] = v.T
    return out


#: Blocks that the vertical kernels handle at once: their values stay in the cache.
TILE = 512


def pack_vertical(blocks: np.ndarray, b: int, lanes: int = 4, mask: bool = False) -> np.ndarray:
    """Rows of 32 * lanes values -> rows of b * lanes words. Value i lies in lane i mod lanes: all lanes pack alike.

    The values of one row of lanes, for all blocks of a tile, are one contiguous vector.
    """
    m = len(blocks)
    out = np.empty((m, b * lanes), U32)
    for at in range(0, m if b else 0, TILE):
        k = min(TILE, m - at)
        v = np.ascontiguousarray(blocks[at : at + k].reshape(k, 32, lanes).astype(U32).transpose(1, 0, 2)).reshape(32, -1)
        if mask and b < 32:
            v &= U32((1 << b) - 1)
        words = np.zeros((b, k * lanes), U32)
        for r in range(32):
            w, s = divmod(r * b, 32)
            words[w] |= v[r] << U32(s) if s else v[r]
            if s + b > 32:
                words[w + 1] |= v[r] >> U32(32 - s)
        out[at : at + k] = words.reshape(b, k, lanes).transpose(1, 0, 2).reshape(k, -1)
    return out


def unpack_vertical(words: np.ndarray, b: int, lanes: int = 4, dtype=U64, running: bool = False) -> np.ndarray:
    """The inverse of pack_vertical. With `running` each lane is summed up while its tile is in the cache."""
    m = len(words)
    if not b:
        return np.zeros((m, 32 * lanes), dtype)
    out, low = np.empty((m, 32 * lanes), dtype), U32((1 << b) - 1 if b < 32 else 0xFFFFFFFF)
    for at in range(0, m, TILE):
        k = min(TILE, m - at)
        w32 = np.ascontiguousarray(words[at : at + k].reshape(k, b, lanes).transpose(1, 0, 2)).reshape(b, -1)
        v = np.empty((32, k * lanes), U32)
        for r in range(32):
            w, s = divmod(r * b, 32)
            np.right_shift(w32[w], U32(s), out=v[r])
            if s + b > 32:
                v[r] |= w32[w + 1] << U32(32 - s)
        v &= low
        if running:
            for r in range(1, 32):
                v[r] += v[r - 1]
        out[at : at + k] = v.reshape(32, k, lanes).transpose(1, 0, 2).reshape(k, -1)
    return out


def unpack_horizontal(words: np.ndarray, b: int, k: int) -> np.ndarray:
    """The scalar layout by gathers: bytes of each value, one multiplication to align them, one shift, one mask."""
    m = len(words)
    if not b:
        return np.zeros((m, k), U64)
    raw = np.zeros((m, words.shape[1] * 4 + 8), np.uint8)
    raw[:, : words.shape[1] * 4] = np.ascontiguousarray(words, "<u4").view(np.uint8)
    bit = np.arange(k) * b
    taken = raw[:, (bit >> 3)[:, None] + np.arange(8)]
    v = np.ascontiguousarray(taken).view("<u8").reshape(m, k)
    v = v * (U64(1) << (U64(7) - (bit & 7).astype(U64)))  # the field now begins at bit 7 for every value
    return (v >> U64(7)) & U64((1 << b) - 1)


def wasted_bits(k: int, b: int) -> int:
    """Spare bits of a packed block of k values of b bits."""
    return -(-k * b // 32) * 32 - k * b


def vbyte_sizes(v: np.ndarray) -> np.ndarray:
    return np.maximum(1, (bit_length(v) + 6) // 7)


def vbyte_encode(v: np.ndarray) -> np.ndarray:
    """Seven bits a byte, low bits first; the last byte of a value has its top bit set."""
    v = v.astype(U64)
    n = vbyte_sizes(v)
    ends = np.cumsum(n)
    out = np.zeros(int(ends[-1]) if len(n) else 0, np.uint8)
    starts = ends - n
    for k in range(int(n.max()) if len(n) else 0):
        has = n > k
        out[starts[has] + k] = ((v[has] >> U64(7 * k)) & U64(127)).astype(np.uint8)
    out[ends - 1] |= 128
    return out


def vbyte_decode(raw: np.ndarray, n: int) -> np.ndarray:
    if not n:
        return np.zeros(0, U64)
    ends = np.flatnonzero(raw & 128)[:n]
    starts = np.concatenate([[0], ends[:-1] + 1])
    sizes = ends - starts + 1
    out = np.zeros(n, U64)
    for k in range(int(sizes.max())):
        has = sizes > k
        out[has] |= (raw[starts[has] + k].astype(U64) & U64(127)) << U64(7 * k)
    return out


def put_bits(values: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Bytes of values of the given numbers of bits (at most 57), one after the other, low bits first."""
    ends = np.cumsum(sizes)
    total = int(ends[-1]) if len(sizes) else 0
    out = np.zeros(-(-total // 8) + 8, np.uint8)
    if total:
        at = ends - sizes
        v = values.astype(U64) << (at & 7).astype(U64)
        for k in range(8):
            np.bitwise_or.at(out, (at >> 3) + k, ((v >> U64(8 * k)) & U64(255)).astype(np.uint8))
    return out[: -(-total // 8)]


def put_bits_of(values: np.ndarray, sizes: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """put_bits for each of many segments of values of at most 32 bits, and the edges of their bytes; ends has the edges of the segments."""
    upto = np.concatenate([[0], np.cumsum(sizes)])
    edges = np.concatenate([[0], np.cumsum(-(-np.diff(upto[ends]) // 8))])
    at = upto[:-1] + np.repeat(8 * edges[:-1] - upto[ends[:-1]], np.diff(ends))
    v = values.astype(U64) << (at & 31).astype(U64)
    n = int(edges[-1]) // 4 + 2
    # The parts of a word share no bit, so their sum is their OR; it is below 2^32, which a float64 holds.
    words = np.bincount(at >> 5, (v & U64(0xFFFFFFFF)).astype(np.float64), n) + np.bincount((at >> 5) + 1, (v >> U64(32)).astype(np.float64), n)
    return words.astype("<u4").view(np.uint8)[: int(edges[-1])], edges


def get_bits(raw: np.ndarray, at: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The values that lie at the given bit positions."""
    padded = np.concatenate([raw, np.zeros(8, np.uint8)])
    taken = np.ascontiguousarray(padded[(at >> 3)[:, None] + np.arange(8)]).view("<u8").reshape(-1)
    return (taken >> (at & 7).astype(U64)) & ((U64(1) << sizes.astype(U64)) - U64(1))
