"""The codes: integers of a chunk to bytes and back. Length, code and delta mode are columns, not part of the bytes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from . import kernels as K
from .layout import BLOCK, EXCEPTION_TENTHS, LANES, LOCATION_BITS, META, PAGE_SAMPLE, SPLIT_LENGTHS, SPLIT_WIDTHS, WORD_LAYOUTS

U8, U32, U64 = np.uint8, np.uint32, np.uint64


def _bytes(words: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(words, "<u4").view(U8).reshape(-1)


def _words(raw: np.ndarray) -> np.ndarray:
    return np.frombuffer(raw.tobytes(), "<u4")


def _number(n: int, size: int = 4) -> np.ndarray:
    return np.frombuffer(int(n).to_bytes(size, "little"), U8)


def _pad(n: int, to: int) -> int:
    return -n % to


def _by_width(widths: np.ndarray):
    for b in np.unique(widths):
        yield int(b), np.flatnonzero(widths == b)


class Codec:
    """encode(values) -> bytes; decode(bytes, n) -> values, both unsigned."""

    name = ""
    block = 1

    def encode(self, v: np.ndarray) -> bytes:
        full = len(v) - len(v) % self.block
        main = self.pack(v[:full].reshape(-1, self.block).astype(U64)) if full else np.zeros(0, U8)
        return main.tobytes() + K.vbyte_encode(v[full:]).tobytes()

    def decode(self, raw: bytes, n: int) -> np.ndarray:
        data, full = np.frombuffer(raw, U8), n - n % self.block
        values, used = self.unpack(data, full // self.block) if full else (np.zeros((0, self.block), U64), 0)
        return np.concatenate([values.reshape(-1), K.vbyte_decode(data[used:], n - full)])

    def encode_many(self, d: np.ndarray, offsets: np.ndarray) -> list[bytes]:
        """Payloads of the chunks of a flat buffer; here one after the other."""
        return [self.encode(d[a:b]) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())]

    def decode_many(self, payloads: list[bytes], n: np.ndarray) -> np.ndarray:
        """The flat buffer of many chunks."""
        parts = [self.decode(p, int(k)) for p, k in zip(payloads, n)]
        return np.concatenate(parts) if parts else np.zeros(0, U64)


def _cut(raw: np.ndarray, edges: np.ndarray) -> list[bytes]:
    """The bytes between neighbouring edges."""
    data, at = raw.tobytes(), edges.tolist()
    return [data[a:b] for a, b in zip(at[:-1], at[1:])]


class BinaryPacking(Codec):
    """Each block at the width of its largest value; a descriptor of widths goes before each meta-block."""

    def __init__(self, name: str, block: int, vertical: bool, gathers: bool = False, lanes: int = LANES):
        self.name, self.block, self.vertical, self.gathers, self.lanes = name, block, vertical, gathers, lanes
        self.meta = META.get(block, 16)

    def _pack(self, rows, b):
        return K.pack_vertical(rows, b, self.lanes) if self.vertical else K.pack_scalar(rows, b)

    def _unpack(self, words, b, dtype=U64, running=False):
        if self.vertical:
            return K.unpack_vertical(words, b, self.lanes, dtype, running)
        return K.unpack_horizontal(words, b, self.block) if self.gathers else K.unpack_scalar(words, b, self.block, dtype)

    def encode_many(self, d, offsets):
        return pack_many(self, d, offsets)

    def decode_many(self, payloads, n):
        return unpack_many(self, payloads, np.asarray(n))

    def pack(self, rows: np.ndarray) -> np.ndarray:
        m = K.or_widths(rows)
        size = -(-self.block * m // 32)
        groups = -(-len(m) // self.meta)
        start = np.cumsum(size) - size + (np.arange(len(m)) // self.meta + 1) * (self.meta // 4)
        out = np.zeros(groups * (self.meta // 4) + int(size.sum()), U32)
        widths = np.zeros(groups * self.meta, U8)
        widths[: len(m)] = m
        heads = start[:: self.meta] - self.meta // 4
        out[heads[:, None] + np.arange(self.meta // 4)] = np.frombuffer(widths.tobytes(), "<u4").reshape(groups, -1)
        for b, at in _by_width(m):
            if b:
                out[start[at][:, None] + np.arange(size[at[0]])] = self._pack(rows[at], b)
        return _bytes(out)

    def unpack(self, raw: np.ndarray, blocks: int) -> tuple[np.ndarray, int]:
        m, start, at = np.zeros(blocks, np.int64), np.zeros(blocks, np.int64), 0
        for first in range(0, blocks, self.meta):
            own = min(self.meta, blocks - first)
            m[first : first + own] = raw[at : at + own]
            size = -(-self.block * m[first : first + own] // 32)
            start[first : first + own] = at // 4 + self.meta // 4 + np.cumsum(size) - size
            at += self.meta + 4 * int(size.sum())
        words, out = _words(raw[:at]), np.zeros((blocks, self.block), U64)
        for b, k in _by_width(m):
            if b:
                out[k] = self._unpack(words[start[k][:, None] + np.arange(-(-self.block * b // 32))], b)
        return out, at


def _block_starts(offsets: np.ndarray, block: int) -> tuple[np.ndarray, np.ndarray]:
    """Where the whole blocks of the chunks of a flat buffer begin, and how many each chunk has."""
    n = np.diff(offsets) // block
    first = np.repeat(offsets[:-1], n)
    return first + block * (np.arange(len(first)) - np.repeat(np.cumsum(n) - n, n)), n


def _tails(offsets: np.ndarray, block: int) -> tuple[np.ndarray, np.ndarray]:
    """Places of the values after the whole blocks, and how many each chunk has."""
    n = np.diff(offsets)
    rest = n % block
    start = np.repeat(offsets[1:] - rest, rest)
    return start + np.arange(len(start)) - np.repeat(np.cumsum(rest) - rest, rest), rest


def pack_many(codec: BinaryPacking, d: np.ndarray, offsets: np.ndarray) -> list[bytes]:
    """Payloads of many chunks at once: all blocks of one width, of whichever chunk, are packed together."""
    block, group = codec.block, codec.meta // 4
    starts, count = _block_starts(offsets, block)
    whole = len(starts) * block == len(d)
    rows = d.astype(U32).reshape(-1, block) if whole else d.astype(U32)[starts[:, None] + np.arange(block)]
    m = K.or_widths(rows)
    size = -(-block * m // 32)
    heads = -(-count // codec.meta)
    chunk_first = np.cumsum(count) - count
    number = np.arange(len(m)) - np.repeat(chunk_first, count)
    before = np.cumsum(size) - size
    own = before - np.repeat(np.append(before, size.sum())[chunk_first], count)
    words = np.add.reduceat(np.append(size, 0), chunk_first) * (count > 0) + heads * group if len(count) else heads
    base = np.cumsum(words) - words
    at = np.repeat(base, count) + own + (number // codec.meta + 1) * group
    out = np.zeros(int(words.sum()), U32)
    descriptor = out.view(U8)
    head_at = np.repeat(base, count) + (own[np.arange(len(m)) - number % codec.meta] if len(m) else own) + (number // codec.meta) * group
    descriptor[4 * head_at + number % codec.meta] = m
    for b, k in _by_width(m):
        if b:
            out[at[k][:, None] + np.arange(size[k[0]])] = codec._pack(rows[k], b)
    places, rest = _tails(offsets, block)
    tail = K.vbyte_encode(d[places])
    ends = np.concatenate([[0], np.cumsum(K.vbyte_sizes(d[places]))])[np.concatenate([[0], np.cumsum(rest)])].tolist()
    main, tail = out.tobytes(), tail.tobytes()
    edge = (4 * np.append(base, words.sum())).tolist()
    return [main[edge[i] : edge[i + 1]] + tail[ends[i] : ends[i + 1]] for i in range(len(count))]


def _carried(rows: np.ndarray, count: np.ndarray, stride: int) -> np.ndarray:
    """Adds to each block's running sums what the blocks of its chunk before it come to; the sums of each chunk's lanes."""
    last = rows[:, rows.shape[1] - stride :].copy()
    total = np.cumsum(last, axis=0, dtype=U32)
    before = np.concatenate([np.zeros((1, stride), U32), total])
    first = np.cumsum(count) - count
    carry = before[:-1] - np.repeat(before[first], count, axis=0)
    rows += np.tile(carry, (1, rows.shape[1] // stride))
    return before[first + count] - before[first]


def unpack_many(codec: BinaryPacking, payloads: list[bytes], n: np.ndarray, stride: int = 0) -> np.ndarray:
    """The flat buffer of many chunks at once. With a stride, of their running sums instead of the differences, made in the same pass."""
    block, group = codec.block, codec.meta // 4
    offsets = np.concatenate([[0], np.cumsum(n)])
    starts, count = _block_starts(offsets, block)
    mains, tails, heads, base = [], [], [], 0
    words_of = -(-block * np.arange(33) // 32)
    each = words_of.tolist()
    for raw, blocks in zip(payloads, count.tolist()):
        place = 0
        for first in range(0, blocks, codec.meta):  # where a meta-block ends depends on its widths
            heads.append(base + place)
            width = raw[place : place + min(codec.meta, blocks - first)]
            place += 4 * (group + (sum(width) * block // 32 if block % 32 == 0 else sum([each[w] for w in width])))
        mains.append(raw[:place])
        tails.append(raw[place:])
        base += place
    joined = b"".join(mains)
    number = np.arange(len(starts)) - np.repeat(np.cumsum(count) - count, count)
    of_meta = np.cumsum(number % codec.meta == 0) - 1
    head = np.array(heads, np.int64)[of_meta]
    m = np.frombuffer(joined, U8)[head + number % codec.meta].astype(np.int64)
    size = words_of[m]
    before = np.cumsum(size) - size
    at = head // 4 + group + before - before[np.arange(len(m)) - number % codec.meta]
    words, out = np.frombuffer(joined, "<u4"), np.zeros(int(offsets[-1]), U32)
    whole = len(starts) * block == len(out)
    rows = out.reshape(-1, block) if whole else np.zeros((len(starts), block), U32)
    for b, own in _by_width(m):
        if b:
            gathered = words[at[own][:, None] + np.arange(words_of[b])]
            rows[own] = codec._unpack(gathered, b, U32, running=codec.vertical and stride == codec.lanes)
    sums = None
    if stride:
        if not (codec.vertical and stride == codec.lanes):
            lanes = rows.reshape(len(rows), -1, stride)
            np.cumsum(lanes, axis=1, dtype=U32, out=lanes)
        sums = _carried(rows, count, stride) if len(rows) else np.zeros((len(count), stride), U32)
    if not whole:
        out[starts[:, None] + np.arange(block)] = rows
        places, rest = _tails(offsets, block)
        tail = K.vbyte_decode(np.frombuffer(b"".join(tails), U8), int(rest.sum()))
        if stride:
            ends = np.concatenate([[0], np.cumsum(rest)])
            chunk = np.repeat(np.arange(len(rest)), rest)
            tail = K.undelta_many(tail, ends, stride) + sums[chunk, (np.arange(len(chunk)) - ends[chunk]) % stride]
        out[places] = tail
    return out


def width_counts(rows: np.ndarray) -> np.ndarray:
    """For each block, how many values have each width 0 to 32."""
    width = K.bit_length(rows.reshape(-1))
    block = np.repeat(np.arange(len(rows)), rows.shape[1])
    return np.bincount(block * 33 + width, minlength=33 * len(rows)).reshape(-1, 33)


def choose_widths(rows: np.ndarray, location_bits: int = LOCATION_BITS):
    """Width b, largest width m and exceptions c of each block at the least cost; the larger b on ties.

    Cost in bits: the block at b, and for each exception its location and the bits beyond b.
    """
    counts = width_counts(rows)
    above = counts[:, ::-1].cumsum(axis=1)[:, ::-1]  # values of at least each width
    m = np.where(counts > 0, np.arange(33), 0).max(axis=1)
    b = np.arange(33)
    c = np.concatenate([above[:, 1:], np.zeros((len(rows), 1), np.int64)], axis=1)
    cost = rows.shape[1] * b + c * (location_bits + m[:, None] - b)
    cost = np.where(b <= m[:, None], cost, np.iinfo(np.int64).max)
    best = 32 - cost[:, ::-1].argmin(axis=1)
    at = np.arange(len(rows))
    return best, m, c[at, best], cost[at, best]


class Paged(Codec):
    """A code of whole blocks whose pages are coded together.

    pack_rows(rows, count) -> the bytes of each page's blocks; unpack_rows(pages, count) -> all rows, and the bytes used
    of each page. count: the blocks of each page, none of them 0.
    """

    block = BLOCK

    def pack(self, rows: np.ndarray) -> np.ndarray:
        return np.frombuffer(self.pack_rows(rows, np.array([len(rows)]))[0], U8)

    def encode_many(self, d, offsets):
        return pack_pages(self, d, offsets)

    def decode_many(self, payloads, n):
        return unpack_pages(self, payloads, np.asarray(n))

    def unpack(self, raw: np.ndarray, blocks: int) -> tuple[np.ndarray, int]:
        rows, used = self.unpack_rows([raw.tobytes()], np.array([blocks]))
        return rows.astype(U64), used[0]


def pack_pages(codec: Paged, d: np.ndarray, offsets: np.ndarray) -> list[bytes]:
    """Payloads of many chunks at once."""
    starts, count = _block_starts(offsets, codec.block)
    own = count > 0
    rows = d.astype(U64)[starts[:, None] + np.arange(codec.block)]
    mains = iter(codec.pack_rows(rows, count[own]) if own.any() else [])
    places, rest = _tails(offsets, codec.block)
    tail = K.vbyte_encode(d[places]).tobytes()
    ends = np.concatenate([[0], np.cumsum(K.vbyte_sizes(d[places]))])[np.concatenate([[0], np.cumsum(rest)])].tolist()
    return [(next(mains) if has else b"") + tail[a:b] for has, a, b in zip(own.tolist(), ends[:-1], ends[1:])]


def unpack_pages(codec: Paged, payloads: list[bytes], n: np.ndarray) -> np.ndarray:
    """The flat buffer of many chunks at once."""
    offsets = np.concatenate([[0], np.cumsum(n)])
    starts, count = _block_starts(offsets, codec.block)
    own = count > 0
    pages = [p for p, has in zip(payloads, own.tolist()) if has]
    rows, used = codec.unpack_rows(pages, count[own]) if pages else (np.zeros((0, codec.block), U32), [])
    out, cut = np.zeros(int(offsets[-1]), U64), iter(used)
    out[starts[:, None] + np.arange(codec.block)] = rows
    places, rest = _tails(offsets, codec.block)
    tails = [p[next(cut) :] if has else p for p, has in zip(payloads, own.tolist())]
    out[places] = K.vbyte_decode(np.frombuffer(b"".join(tails), U8), int(rest.sum()))
    return out


def _low_words(rows: np.ndarray, b: np.ndarray, pack) -> bytes:
    """Blocks of 128 at b bits each, one after the other."""
    start = 4 * (np.cumsum(b) - b)
    low = np.zeros(4 * int(b.sum()), U32)
    for w, at in _by_width(b):
        if w:
            low[start[at][:, None] + np.arange(4 * w)] = pack(rows[at], w)
    return _bytes(low).tobytes()


def _low_rows(words: np.ndarray, start: np.ndarray, b: np.ndarray, unpack) -> np.ndarray:
    """Blocks of 128 of b bits each whose words begin at `start`."""
    out = np.zeros((len(b), BLOCK), U32)
    for w, k in _by_width(b):
        if w:
            out[k] = unpack(words[start[k][:, None] + np.arange(4 * w)], w)
    return out


class PagePatched(Paged):
    """Low bits of all blocks, then per block widths and exception places, then the high bits of the page's exceptions.

    High bits go to one packed array per number of bits (`words=False`), or all to one Simple-8b array. The vertical
    version packs both parts in lanes, pads arrays to 128 values and starts packed data on 16 bytes.
    """

    def __init__(self, name: str, vertical: bool = False, words: bool = False):
        self.name, self.vertical, self.words = name, vertical, words
        self.align = 16 if vertical else 4
        self.unit = BLOCK if vertical else 32
        self.head = 4 + _pad(4, self.align)

    def _pack(self, rows, b, mask=False):
        return K.pack_vertical(rows, b, mask=mask) if self.vertical else K.pack_scalar(rows, b, mask=mask)

    def _unpack(self, words, b, k):
        return K.unpack_vertical(words, b, dtype=U32) if self.vertical else K.unpack_scalar(words, b, k, U32)

    def pack_rows(self, rows, count):
        b, m, c, _ = choose_widths(rows)
        low = _low_words(rows, b, lambda r, w: self._pack(r, w, mask=True))
        block, place = np.nonzero(K.bit_length(rows.reshape(-1)).reshape(rows.shape) > b[:, None])
        patched = m > b
        sizes = 2 + patched * (1 + c)
        ends = np.cumsum(sizes)
        head, before = ends - sizes, np.cumsum(c) - c
        notes = np.zeros(int(ends[-1]), U8)
        notes[head], notes[head + 1] = b, m
        notes[head[patched] + 2] = c[patched]
        notes[head[block] + 3 + np.arange(len(block)) - before[block]] = place
        high = rows[block, place] >> b[block].astype(U64)
        edge = np.concatenate([[0], np.cumsum(count)])
        page = np.searchsorted(edge, block, "right") - 1
        cut = lambda a: np.concatenate([[0], np.cumsum(a)])[edge].tolist()
        low_at, note_at, high_at = cut(16 * b), cut(sizes), cut(c)
        buckets = [] if self.words else self._buckets(high, (m - b)[block], page, len(count))
        words = Simple8b().encode_many(high, np.array(high_at)) if self.words else []
        notes, out = notes.tobytes(), []
        for i in range(len(count)):
            own, note = low[low_at[i] : low_at[i + 1]], notes[note_at[i] : note_at[i + 1]]
            parts = [(self.head + len(own)).to_bytes(4, "little"), bytes(self.head - 4), own, len(note).to_bytes(4, "little"), note, bytes(_pad(len(note), 4))]
            if self.words:
                parts += [(high_at[i + 1] - high_at[i]).to_bytes(4, "little"), words[i]]
            else:
                parts.append(sum(1 << (k - 1) for k, _, _ in buckets[i]).to_bytes(4, "little"))
                parts.append(bytes(_pad(sum(map(len, parts[3:])), self.align)))
                for _, size, raw in buckets[i]:
                    parts += [size.to_bytes(4, "little"), bytes(_pad(4, self.align)), raw]
            out.append(b"".join(parts))
        return out

    def _buckets(self, high, bucket, page, pages):
        """(bits, values, bytes) of every page's arrays of high parts; those of all pages are packed together."""
        out = [[] for _ in range(pages)]
        for k in np.unique(bucket).tolist():
            own = np.flatnonzero(bucket == k)
            n = np.bincount(page[own], minlength=pages)
            rows = -(-n // self.unit)
            first = self.unit * (np.cumsum(rows) - rows)
            padded = np.zeros(self.unit * int(rows.sum()), U64)
            padded[first[page[own]] + np.arange(len(own)) - np.repeat(np.cumsum(n) - n, n)] = high[own]
            words = self._pack(padded.reshape(-1, self.unit), k)
            raw, span = _bytes(words).tobytes(), 4 * words.shape[1]
            at = (first // self.unit * span).tolist()
            for i in np.flatnonzero(n).tolist():
                out[i].append((k, int(n[i]), raw[at[i] : at[i] + int(rows[i]) * span]))
        return out

    def unpack_rows(self, pages, count):
        b, m, places, patched, lows, used, numbers, coded = [], [], [], [], [], [], [], []
        arrays: dict[int, list] = {}
        for raw, blocks in zip(pages, count.tolist()):
            number = lambda at: int.from_bytes(raw[at : at + 4], "little")  # noqa: B023, E731
            at = number(0)
            lows.append(raw[self.head : at])
            size, tail_start = number(at), at
            i = at = at + 4
            for _ in range(blocks):
                low, top = raw[i], raw[i + 1]
                b.append(low)
                m.append(top)
                i += 2
                if top > low:
                    c = raw[i]
                    patched.append(c)
                    places.append(raw[i + 1 : i + 1 + c])
                    i += 1 + c
                else:
                    patched.append(0)
            at += size + _pad(size, 4)
            if self.words:
                numbers.append(number(at))
                at += 4
                coded.append(raw[at : len(raw) - (len(raw) - at) % 8])
            else:
                set_of, at = number(at), at + 4
                at += _pad(at - tail_start, self.align)
                for k in range(1, 33):
                    if set_of >> (k - 1) & 1:
                        n, at = number(at), at + self.head
                        span = 4 * -(-n // self.unit) * -(-self.unit * k // 32)
                        arrays.setdefault(k, []).append((n, raw[at : at + span]))
                        at += span
            used.append(at)
        if self.words:
            values, length = simple8b_read(coded, np.array(numbers))
            arrays[0], used = [values], (np.array(used) + length).tolist()
        b, m, c = (np.array(x, np.int64) for x in (b, m, patched))
        words = np.frombuffer(b"".join(lows), "<u4")
        out = _low_rows(words, 4 * (np.cumsum(b) - b), b, lambda w, k: self._unpack(w, k, BLOCK))
        block, place = np.repeat(np.arange(len(b)), c), np.frombuffer(b"".join(places), U8)
        if len(block):
            high, bucket = np.zeros(len(block), U32), (m - b)[block]
            for k, own in arrays.items():
                if self.words:
                    high[:] = np.concatenate(own)
                    continue
                n = np.array([x for x, _ in own])
                rows = self._unpack(np.frombuffer(b"".join(x for _, x in own), "<u4").reshape(-1, -(-self.unit * k // 32)), k, self.unit).reshape(-1)
                first = self.unit * (np.cumsum(-(-n // self.unit)) - -(-n // self.unit))
                high[bucket == k] = rows[np.repeat(first, n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)]
            out[block, place] |= high << b[block].astype(U32)
        return out, used


class LinkPatched(Paged):
    """One width for the page; an exception's slot holds the distance to the next one of its block.

    Where the distance does not fit, a value in between becomes an exception too. Exceptions follow the packed blocks
    whole, in 4 bytes, or (`sized`) in the 1, 2 or 4 bytes that the largest one needs.
    Layout (our own): [4 bytes: width, bytes of an exception, exceptions][4 bytes a block: first place or 255, exceptions so
    far][blocks][exceptions].
    """

    def __init__(self, name: str, sized: bool):
        self.name, self.sized = name, sized

    def page_widths(self, rows: np.ndarray, count: np.ndarray) -> np.ndarray:
        """Chosen once from the first values of each page: packed bits plus 32 for each exception, larger width on ties."""
        first = np.cumsum(count) - count
        taken = np.minimum(count, PAGE_SAMPLE // BLOCK)
        counts = np.add.reduceat(width_counts(rows[_ranges(first, taken)]), np.cumsum(taken) - taken)
        c = counts[:, ::-1].cumsum(axis=1)[:, ::-1] - counts
        cost = counts.sum(axis=1, keepdims=True) * np.arange(33) + 32 * c
        top = np.where(counts > 0, np.arange(33), 0).max(axis=1)
        cost = np.where(np.arange(33) <= top[:, None], cost, np.iinfo(np.int64).max)
        return 32 - cost[:, ::-1].argmin(axis=1)

    def pack_rows(self, rows, count):
        width = self.page_widths(rows, count)
        b = np.repeat(width, count)
        reach, kept = np.int64(1) << b, rows.copy()
        block, place = np.nonzero(rows >= reach[:, None].astype(U64))
        # Links that are too long get steps of the full reach in between; all blocks at once.
        gap = np.diff(place, prepend=0)
        fresh = np.diff(block, prepend=-1) != 0
        extra = np.where(fresh, 0, (gap - 1) // reach[block])
        ends = np.cumsum(extra + 1)
        chain_block, back = np.repeat(block, extra + 1), np.repeat(ends, extra + 1) - 1 - np.arange(int(ends[-1]) if len(ends) else 0)
        before = place - gap
        chain = np.where(back == 0, np.repeat(place, extra + 1), np.repeat(before, extra + 1) + reach[chain_block] * (np.repeat(extra, extra + 1) - back + 1))
        n = len(chain)
        exceptions = rows[chain_block, chain]
        same = np.append(chain_block[1:] == chain_block[:-1], False) if n else np.zeros(0, bool)
        kept[chain_block, chain] = np.where(same, np.append(np.diff(chain), 0) - 1, 0) if n else 0
        edge = np.concatenate([[0], np.cumsum(count)])
        so_far = np.searchsorted(chain_block, np.arange(len(rows) + 1))
        cut = so_far[edge]  # exceptions before each page
        total = np.diff(cut)
        first = np.full(len(rows), 255, np.int64)
        has = so_far[1:] > so_far[:-1]
        first[has] = chain[so_far[:-1][has]]
        number = np.where(has, so_far[:-1] - np.repeat(cut[:-1], count), np.repeat(total, count))
        size = np.full(len(count), 4)
        if self.sized and n:
            own = np.flatnonzero(total)
            most = np.maximum.reduceat(exceptions, cut[own])
            size[own] = np.where(most < 1 << 8, 1, np.where(most < 1 << 16, 2, 4))
        entry = np.stack([first, number & 255, number >> 8 & 255, number >> 16 & 255], axis=1).astype(U8).tobytes()
        low = _low_words(kept, b, K.pack_scalar)
        each = np.repeat(size, total)
        raw = np.ascontiguousarray(exceptions, "<u8").view(U8).reshape(-1, 8)[np.arange(8) < each[:, None]].tobytes()
        head = (width | size << 6 | total << 9).tolist()
        low_at = (16 * np.concatenate([[0], np.cumsum(b)])[edge]).tolist()
        raw_at = np.concatenate([[0], np.cumsum(size * total)]).tolist()
        edge = (4 * edge).tolist()
        return [head[i].to_bytes(4, "little") + entry[edge[i] : edge[i + 1]] + low[low_at[i] : low_at[i + 1]] + raw[raw_at[i] : raw_at[i + 1]] for i in range(len(count))]

    def unpack_rows(self, pages, count):
        width, size, total, entries, lows, raws, used = [], [], [], [], [], [], []
        for raw, blocks in zip(pages, count.tolist()):
            head = int.from_bytes(raw[:4], "little")
            b, each, n = head & 63, head >> 6 & 7, head >> 9
            at = 4 + 4 * blocks
            stop = at + 16 * b * blocks
            width.append(b)
            size.append(each)
            total.append(n)
            entries.append(raw[4:at])
            lows.append(raw[at:stop])
            raws.append(raw[stop : stop + each * n])
            used.append(stop + each * n)
        b, total = np.repeat(np.array(width), count), np.array(total)
        out = _low_rows(np.frombuffer(b"".join(lows), "<u4"), 4 * (np.cumsum(b) - b), b, lambda w, k: K.unpack_scalar(w, k, BLOCK, U32))
        if total.any():
            wide = np.zeros((int(total.sum()), 8), U8)
            wide[np.arange(8) < np.repeat(np.array(size), total)[:, None]] = np.frombuffer(b"".join(raws), U8)
            values = wide.view("<u8").reshape(-1).astype(U32)
            entry = np.frombuffer(b"".join(entries), U8).reshape(-1, 4).astype(np.int64)
            rows = np.flatnonzero(entry[:, 0] != 255)
            place, number = entry[rows, 0], (entry[:, 1] | entry[:, 2] << 8 | entry[:, 3] << 16)[rows] + np.repeat(np.cumsum(total) - total, count)[rows]
            left = np.diff(np.append(number, len(values)))
            # All blocks follow their chains at once.
            while len(rows):
                step = out[rows, place].astype(np.int64) + 1
                out[rows, place] = values[number]
                place, number, left = place + step, number + 1, left - 1
                live = left > 0
                rows, place, number, left = rows[live], place[live], number[live], left[live]
        return out, used


def _ranges(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """first[0], first[0] + 1, ... n[0] numbers, then those from first[1], and so on."""
    return np.repeat(first - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))


class BlockPatched(Paged):
    """Each block patched on its own: [b, c, words of the exceptions, 0][block at b bits][Simple-8b of gaps and high parts].

    The fast rule takes the least width with at most a tenth of exceptions; `optimal` tries every width for the
    least bytes, the larger on ties. The exceptions of all blocks, and of all widths tried, are coded together.
    """

    #: Pairs of a block and a width that are tried together.
    TRIED = 4096

    def __init__(self, name: str, optimal: bool):
        self.name, self.optimal = name, optimal

    @staticmethod
    def _exceptions(rows, width, at, b):
        """Gaps and high parts of the blocks `at` at widths b, laid end to end, and where each begins."""
        seg, place = np.nonzero(width[at] > b[:, None])
        c = np.bincount(seg, minlength=len(at))
        gaps = np.diff(place, prepend=0) - 1
        fresh = np.diff(seg, prepend=-1) != 0
        gaps[fresh] = place[fresh]
        ends = np.concatenate([[0], np.cumsum(2 * c)])
        own = np.arange(len(seg)) - (np.cumsum(c) - c)[seg]
        flat = np.zeros(int(ends[-1]), U64)
        flat[ends[seg] + own] = gaps
        flat[ends[seg] + c[seg] + own] = rows[at[seg], place] >> b[seg].astype(U64)
        return flat, ends, c

    def _sizes(self, width, at, b):
        """Bytes of the blocks `at` at widths b: those of _exceptions(), from the widths of its values alone."""
        size = 16 * b
        for i in range(0, len(b), self.TRIED):
            own = b[i : i + self.TRIED].astype(U8)[:, None]
            taken = width[at[i : i + self.TRIED]]
            above = taken > own
            place = np.flatnonzero(above)
            c = np.count_nonzero(above, axis=1)
            ends = np.concatenate([[0], np.cumsum(c)])
            gaps = np.diff(place, prepend=-1) - 1
            fresh = ends[:-1][c > 0]
            gaps[fresh] = place[fresh] % BLOCK
            flat, own_at = np.empty(2 * len(place), U8), np.arange(len(place))
            flat[own_at + np.repeat(ends[:-1], c)] = _GAP_WIDTHS[gaps]
            flat[own_at + np.repeat(ends[1:], c)] = (taken - own).reshape(-1)[place]
            size[i : i + self.TRIED] += 8 * np.diff(simple8b_starts(flat, 2 * ends)[1])
        return size

    def _best(self, width):
        """The width of the least bytes of each block, the larger on ties."""
        top = width.max(axis=1).astype(np.int64) + 1
        block, b = np.repeat(np.arange(len(top)), top), _ranges(np.zeros(len(top), np.int64), top)
        order = np.lexsort((-b, self._sizes(width, block, b), block))
        return b[order[np.cumsum(top) - top]]

    def pack_rows(self, rows, count):
        counts = width_counts(rows)
        width = K.bit_length(rows.reshape(-1)).astype(U8).reshape(rows.shape)
        above = np.concatenate([counts[:, ::-1].cumsum(axis=1)[:, ::-1][:, 1:], np.zeros((len(rows), 1), np.int64)], axis=1)
        b = self._best(width) if self.optimal else (above * 10 <= EXCEPTION_TENTHS * BLOCK).argmax(axis=1)
        flat, ends, c = self._exceptions(rows, width, np.arange(len(rows)), b)
        words, per = simple8b_words(flat, ends)
        number = np.diff(per)
        low = np.frombuffer(_low_words(rows, b, lambda r, w: K.pack_scalar(r, w, mask=True)), "<u4")
        size = 1 + 4 * b + 2 * number
        start = np.cumsum(size) - size
        out = np.zeros(int(size.sum()), U32)
        out.view(U8).reshape(-1, 4)[start] = np.stack([b, c, number, np.zeros(len(b), np.int64)], axis=1)
        out[_ranges(start + 1, 4 * b)] = low
        out[_ranges(start + 1 + 4 * b, 2 * number)] = words.view("<u4")
        raw, edge = out.tobytes(), (4 * np.concatenate([[0], np.cumsum(size)])[np.concatenate([[0], np.cumsum(count)])]).tolist()
        return [raw[i:j] for i, j in zip(edge[:-1], edge[1:])]

    def unpack_rows(self, pages, count):
        b, c, number, start, mains, used, base = [], [], [], [], [], [], 0
        for raw, blocks in zip(pages, count.tolist()):
            at = 0
            for _ in range(blocks):
                low, n = raw[at], raw[at + 2]
                b.append(low)
                c.append(raw[at + 1])
                number.append(n)
                start.append(base + at)
                at += 4 + 16 * low + 8 * n
            mains.append(raw[:at])
            used.append(at)
            base += at
        words = np.frombuffer(b"".join(mains), "<u4")
        b, c, number, start = (np.array(x, np.int64) for x in (b, c, number, start))
        start //= 4
        out = _low_rows(words, start + 1, b, lambda w, k: K.unpack_scalar(w, k, BLOCK, U32))
        if c.any():
            coded = np.ascontiguousarray(words[_ranges(start + 1 + 4 * b, 2 * number)]).view("<u8")
            both = simple8b_values(coded, np.concatenate([[0], np.cumsum(number)]), 2 * c)
            at = np.cumsum(2 * c) - 2 * c
            gaps, high = both[_ranges(at, c)].astype(np.int64) + 1, both[_ranges(at + c, c)].astype(U32)
            total = np.concatenate([[0], np.cumsum(gaps)])
            block, first = np.repeat(np.arange(len(c)), c), np.cumsum(c) - c
            place = total[1:] - np.repeat(total[first], c) - 1
            out[block, place] |= high << b[block].astype(U32)
        return out, used


_COUNTS = np.array([c for c, _ in WORD_LAYOUTS])
_BITS = np.array([b for _, b in WORD_LAYOUTS])
#: Bits of the gaps in a block.
_GAP_WIDTHS = K.bit_length(np.arange(BLOCK)).astype(U8)


def simple8b_starts(width: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where the words of each segment begin, how many words came before each segment, and the words' selectors. Segments lie end to end; ends has their edges from 0.

    A word's values fit where the largest width of its places does, or that of all to the segment's end: the less of the two is
    that of the places of the segment. Widths and selectors are bytes, so that one instruction takes many.
    """
    n, size = len(width), np.diff(ends)
    width = width.astype(U8)
    segment = np.repeat(np.arange(len(size), 0, -1, dtype=np.int32 if len(size) < 1 << 22 else np.int64) << 8, size)  # falls, so that the running maximum from the end begins anew with each
    rest = np.maximum.accumulate((segment | width)[::-1])[::-1].astype(U8)
    least = int(width.min()) if n else 0
    pick, top, reach = np.full(n, len(_BITS) - 1, U8), np.append(width, np.zeros(int(_COUNTS[0]), U8)), 1
    for s in range(len(_BITS) - 1, -1, -1):
        count, bits = WORD_LAYOUTS[s]
        if bits < least:
            break
        while reach < count:  # the largest of `reach` widths from each place on, to that of `count`
            more = min(reach, count - reach)
            top[:-more] = np.maximum(top[:-more], top[more:])
            reach += more
        fits = np.minimum(top[:n], rest) <= bits
        np.minimum(pick, (fits.view(U8) - U8(1)) | U8(s), out=pick)
    far = np.arange(n)
    starts, per = _followed(far + _COUNTS[pick], ends)
    return starts, per, pick[starts].astype(np.int64)


#: Segments of more values are followed one by one.
LONG_SEGMENT = 2048


def _followed(step: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The places that one meets by going from i to step[i], from each segment's beginning to its end, and how many come before each segment."""
    size = np.diff(ends)
    found, per = [], np.zeros(len(size), np.int64)
    for j in np.flatnonzero(size > LONG_SEGMENT).tolist():
        i, stop, own, go = 0, int(size[j]), [], (step[ends[j] : ends[j + 1]] - ends[j]).tolist()
        while i < stop:
            own.append(i)
            i = go[i]
        found.append(np.array(own) + ends[j])
        per[j] = len(own)
    segment = np.flatnonzero((size > 0) & (size <= LONG_SEGMENT))
    at = ends[segment]
    while len(at):  # one step in every segment that is not done
        found.append(at)
        per[segment] += 1
        at = step[at]
        live = at < ends[segment + 1]
        at, segment = at[live], segment[live]
    return np.sort(np.concatenate(found)) if found else np.zeros(0, np.int64), np.concatenate([[0], np.cumsum(per)])


def simple8b_words(v: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The words of segments of values, and where each segment's words begin. A segment's last word is padded with zeros."""
    width = K.bit_length(v)
    if len(v) and int(width.max()) > 60:
        raise ValueError("a value needs more than 60 bits")
    starts, per, chosen = simple8b_starts(width, ends)
    stop = ends[np.repeat(np.arange(1, len(ends)), np.diff(per))]
    padded = np.concatenate([v.astype(U64), np.zeros(240, U64)])
    words = chosen.astype(U64)
    for s in np.unique(chosen).tolist():
        count, b = WORD_LAYOUTS[s]
        at = np.flatnonzero(chosen == s)
        if b:
            place = starts[at][:, None] + np.arange(count)
            own = padded[place] << (4 + b * np.arange(count)).astype(U64)
            own[place >= stop[at][:, None]] = 0
            words[at] |= np.bitwise_or.reduce(own, axis=1)
    return words.astype("<u8"), per


def simple8b_values(words: np.ndarray, per: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The first n values of each segment of words, end to end; per: where each segment's words begin."""
    chosen = (words & U64(15)).astype(np.int64)
    counts = _COUNTS[chosen]
    ends = np.concatenate([[0], np.cumsum(counts)])
    out = np.zeros(int(ends[-1]), U64)
    for s in np.unique(chosen).tolist():
        count, b = WORD_LAYOUTS[s]
        at = np.flatnonzero(chosen == s)
        if b:
            out[ends[at][:, None] + np.arange(count)] = words[at][:, None] >> (4 + b * np.arange(count)).astype(U64) & U64((1 << b) - 1)
    return out[_ranges(ends[per[:-1]], n)]


def simple8b_read(coded: list[bytes], n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first n values of each array of whole words, end to end, and the bytes that they take; what follows them in an array is not decoded."""
    begin = np.concatenate([[0], np.cumsum([len(x) // 8 for x in coded])])[:-1]
    words = np.frombuffer(b"".join(coded), "<u8")
    ends = np.concatenate([[0], np.cumsum(_COUNTS[(words & U64(15)).astype(np.int64)])])
    took = np.searchsorted(ends, ends[begin] + n) - begin
    return simple8b_values(words[_ranges(begin, took)], np.concatenate([[0], np.cumsum(took)]), n), 8 * took


class Simple8b(Codec):
    """64-bit words: 4 bits of selector and 60 of values; each word takes as many values as fit, the last is padded."""

    name = "simple8b"

    def encode(self, v: np.ndarray) -> bytes:
        return simple8b_words(v, np.array([0, len(v)]))[0].tobytes() if len(v) else b""

    def encode_many(self, d, offsets):
        words, per = simple8b_words(d, offsets)
        return _cut(words.view(U8), 8 * per)

    def decode_many(self, payloads, n):
        per = np.concatenate([[0], np.cumsum([len(p) // 8 for p in payloads])])
        return simple8b_values(np.frombuffer(b"".join(payloads), "<u8"), per, np.asarray(n))

    def read(self, raw: np.ndarray, n: int) -> tuple[np.ndarray, int]:
        if not n:
            return np.zeros(0, U64), 0
        words = np.frombuffer(raw[: len(raw) - len(raw) % 8].tobytes(), "<u8")
        used = int(np.searchsorted(np.cumsum(_COUNTS[(words & U64(15)).astype(np.int64)]), n)) + 1
        return simple8b_values(words[:used], np.array([0, used]), np.array([n])), used * 8

    def decode(self, raw: bytes, n: int) -> np.ndarray:
        return self.read(np.frombuffer(raw, U8), n)[0]


class VariableByte(Codec):
    name = "vbyte"

    def encode(self, v):
        return K.vbyte_encode(v).tobytes()

    def decode(self, raw, n):
        return K.vbyte_decode(np.frombuffer(raw, U8), n)

    def encode_many(self, d, offsets):
        return _cut(K.vbyte_encode(d), np.concatenate([[0], np.cumsum(K.vbyte_sizes(d))])[offsets])

    def decode_many(self, payloads, n):
        return K.vbyte_decode(np.frombuffer(b"".join(payloads), U8), int(np.sum(n)))


def _byte_lengths(v: np.ndarray) -> np.ndarray:
    return np.maximum(1, (K.bit_length(v) + 7) // 8)


class GroupVarint(Codec):
    """Four values behind one byte with their four lengths, two bits each."""

    name = "groupvarint"

    def encode(self, v):
        n = len(v)
        size = _byte_lengths(v)
        group = np.arange(n) // 4
        start = np.cumsum(size) - size + group + 1
        out = np.zeros(int(size.sum()) + -(-n // 4), U8)
        heads = start[::4] - 1
        np.bitwise_or.at(out, heads[group], ((size - 1) << (2 * (np.arange(n) % 4))).astype(U8))
        for k in range(4):
            has = size > k
            out[start[has] + k] = (v[has].astype(U64) >> U64(8 * k)) & U64(255)
        return out.tobytes()

    def decode(self, raw, n):
        data, at, size = np.frombuffer(raw, U8), 0, []
        heads = []
        view = data.tolist()
        for first in range(0, n, 4):
            d = view[at]
            own = [(d >> 2 * k & 3) + 1 for k in range(min(4, n - first))]
            heads.append(at)
            size += own
            at += 1 + sum(own)
        size = np.array(size, np.int64)
        start = np.cumsum(size) - size + np.arange(n) // 4 + 1
        out = np.zeros(n, U64)
        for k in range(4):
            has = size > k
            out[has] |= data[start[has] + k].astype(U64) << U64(8 * k)
        return out


class ByteGroup8(Codec):
    """Groups of one descriptor byte and eight data bytes: as many whole values as fit, none astride. A set bit of the descriptor marks the last byte of a value."""

    name = "bytegroup8"

    def encode_many(self, d, offsets):
        size = _byte_lengths(d)
        ends = np.concatenate([[0], np.cumsum(size)])
        # The value that holds each byte, and so the first that does not end within eight bytes.
        holder = np.append(np.repeat(np.arange(len(d)), size), np.full(8, len(d)))
        after = np.minimum(holder[ends[:-1] + 8], np.repeat(offsets[1:], np.diff(offsets)))
        starts, per = _followed(after, offsets)
        group = np.repeat(np.arange(len(starts)), np.diff(np.append(starts, len(d))))
        place = ends[:-1] - ends[starts][group]
        out = np.zeros((len(starts), 9), U8)
        out[:, 0] = np.add.reduceat((1 << (place + size - 1)), starts) if len(starts) else 0
        v = d.astype(U64)
        for k in range(4):
            has = size > k
            out[group[has], 1 + place[has] + k] = (v[has] >> U64(8 * k)) & U64(255)
        return _cut(out.reshape(-1), 9 * per)

    def decode_many(self, payloads, n):
        groups = np.frombuffer(b"".join(payloads), U8).reshape(-1, 9)
        last = np.unpackbits(groups[:, :1], axis=1, bitorder="little").astype(bool)
        g, end = np.nonzero(last)
        fresh = np.append(True, g[1:] != g[:-1])[: len(g)]
        first = np.where(fresh, 0, np.append(0, end[:-1] + 1)[: len(g)])
        size, out, data = end - first + 1, np.zeros(len(g), U64), groups[:, 1:].reshape(-1)
        at = 8 * g + first
        for k in range(4):
            has = np.flatnonzero(size > k)
            out[has] |= data[at[has] + k].astype(U64) << U64(8 * k)
        return out

    def encode(self, v):
        return self.encode_many(v, np.array([0, len(v)]))[0]

    def decode(self, raw, n):
        return self.decode_many([raw], np.array([n]))


class TinyGroups(Codec):
    """Groups of four values at one width: a byte of width each, then all bits."""

    name = "tinygroup4"

    def encode(self, v):
        n = len(v)
        padded = np.concatenate([v.astype(U64), np.zeros(_pad(n, 4), U64)]).reshape(-1, 4)
        m = K.or_widths(padded)
        return m.astype(U8).tobytes() + K.put_bits(padded.reshape(-1), np.repeat(m, 4)).tobytes()

    def decode(self, raw, n):
        data, groups = np.frombuffer(raw, U8), -(-n // 4)
        m = np.repeat(data[:groups].astype(np.int64), 4)
        return K.get_bits(data[groups:], np.cumsum(m) - m, m)[:n] if n else np.zeros(0, U64)


#: The number of the split-vector code's width for each width.
_SPLIT_CODES = np.searchsorted(SPLIT_WIDTHS, np.arange(33))


class SplitVector(Codec):
    """Runs of values, each at its own width, cut where dynamic programming finds the least bits. Four bits each for the width's and the length's number.

    The lists of a batch are cut into pieces, and the programs of all pieces go back from their ends in step. What a piece
    starts from is what the piece after it comes to: pieces are run again until no start differs from that, so the runs are
    those of one program over the whole list.
    """

    name = "splitvec"
    #: Values of a piece; values of lists that are cut together.
    PIECE, TOGETHER = 256, 1 << 17
    #: Bits of a run that leaves its list.
    NEVER = 1 << 26

    def encode(self, v):
        return self.encode_many(v, np.array([0, len(v)]))[0]

    def decode(self, raw, n):
        return self.decode_many([raw], np.array([n]))

    def encode_many(self, d, offsets):
        out, at = [], 0
        while at < len(offsets) - 1:
            to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + self.TOGETHER, "right")) - 1)
            out += self._coded(d[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at])
            at = to
        return out

    def _coded(self, v, ends):
        if not len(v):
            return [b""] * (len(ends) - 1)
        widths, pick = self._cuts(v, ends)
        starts, per = _followed(np.arange(len(v)) + np.array(SPLIT_LENGTHS)[pick], ends)
        j = pick[starts].astype(np.int64)
        w, size = _SPLIT_CODES[widths[j, starts]], np.array(SPLIT_LENGTHS)[j]
        bits, runs = K.put_bits_of(v, np.repeat(np.array(SPLIT_WIDTHS)[w], size), ends), np.diff(per)
        heads, tails = (w | j << 4).astype(U8).tobytes(), bits[0].tobytes()
        per, at = per.tolist(), bits[1].tolist()
        return [n.to_bytes(4, "little") + heads[a:b] + tails[c:e] if n else b"" for n, a, b, c, e in zip(runs.tolist(), per[:-1], per[1:], at[:-1], at[1:])]

    def _cuts(self, v, ends):
        """For each length the largest width of a run from each place, and the number of the best length there."""
        n, lengths = len(v), np.array(SPLIT_LENGTHS)
        top = {1: K.bit_length(v).astype(U8)}
        for length in SPLIT_LENGTHS[1:]:
            half = next(k for k in reversed(SPLIT_LENGTHS) if k < length and 2 * k >= length)
            top[length] = top[half].copy()
            np.maximum(top[half][: max(0, n - length + half)], top[half][length - half :], out=top[length][: max(0, n - length + half)])
        # Bits and, on ties, the greater length first, in one number.
        cost = ((8 + lengths[:, None] * np.array(SPLIT_WIDTHS)[_SPLIT_CODES]) << 4 | np.arange(len(lengths))[::-1, None]).astype(np.int32)
        widths = np.stack([top[length] for length in SPLIT_LENGTHS])
        pieces = -(-np.diff(ends) // self.PIECE)
        list_of = np.repeat(np.arange(len(pieces)), pieces)
        left = np.cumsum(pieces)[list_of] - 1 - np.arange(len(list_of))  # pieces of its list after this one
        stop = ends[1:][list_of] - self.PIECE * left
        size = np.minimum(self.PIECE, stop - ends[:-1][list_of])
        tail = np.zeros((max(SPLIT_LENGTHS), len(stop)), np.int32)  # from the farthest place after the end to the next
        tail[:, left == 0] = self.NEVER << 4
        pick, todo = np.empty(n, U8), np.arange(len(stop))
        while len(todo):
            todo = todo[np.argsort(-size[todo], kind="stable")]
            begun = self._run(widths, cost, pick, stop[todo], size[todo], tail[:, todo])
            before = left[todo] < pieces[list_of[todo]] - 1  # has a piece before it
            todo, begun = todo[before] - 1, begun[:, before]
            changed = (tail[:, todo] != begun).any(axis=0)
            todo, begun = todo[changed], begun[:, changed]
            tail[:, todo] = begun
        return widths, pick

    def _run(self, widths, cost, pick, stop, size, tail):
        """Sets the picks of pieces, the longest first; returns what whole pieces come to, as a tail."""
        deep = len(tail)
        least = np.zeros((deep + 1 + int(size[0]), len(stop)), np.int32)
        least[:deep] = tail
        back, live = np.array(SPLIT_LENGTHS), np.searchsorted(-size, -np.arange(1, int(size[0]) + 1), "right")
        # What the steps read, in their order.
        step = np.repeat(np.arange(1, len(live) + 1), live)
        edges = np.concatenate([[0], np.cumsum(live)])
        at = stop[np.arange(len(step)) - edges[step - 1]] - step
        read, best = np.empty((len(back), len(step)), np.int32), np.empty(len(step), np.int32)
        for own, of_width, out in zip(widths, cost, read):
            of_width.take(own.take(at), out=out, mode="clip")
        edges = edges.tolist()
        for r, (a, b) in enumerate(zip(edges[:-1], edges[1:]), 1):
            from_here = least[deep + r - back, : b - a]
            from_here += read[:, a:b]
            np.minimum.reduce(from_here, axis=0, out=best[a:b])
            np.bitwise_and(best[a:b], ~15, out=least[deep + r, : b - a])
        pick[at] = 15 - (best & 15)
        return least[-deep - 1 : -1] - least[-1]

    def decode_many(self, payloads, n):
        n = np.asarray(n)
        data = np.frombuffer(b"".join(payloads), U8)
        own = np.flatnonzero(n)
        size = np.array(list(map(len, payloads)), np.int64)
        start = (np.cumsum(size) - size)[own]
        if not len(own):
            return np.zeros(0, U64)
        runs = np.ascontiguousarray(data[start[:, None] + np.arange(4)]).view("<u4").reshape(-1).astype(np.int64)
        head = data[_ranges(start + 4, runs)]
        bits = np.repeat(np.array(SPLIT_WIDTHS)[head & 15], np.array(SPLIT_LENGTHS)[head >> 4])
        at, first = np.cumsum(bits) - bits, np.cumsum(n[own]) - n[own]
        return K.get_bits(data, at + np.repeat(8 * (start + 4 + runs) - at[first], n[own]), bits)


class EliasCode(Codec):
    """Of v + 1: its number of bits (unary, or again in gamma), then its bits without the first."""

    def __init__(self, name: str, twice: bool):
        self.name, self.twice = name, twice

    def encode(self, v):
        x = v.astype(U64) + U64(1)
        n = K.bit_length(x)
        low = x ^ (U64(1) << (n - 1).astype(U64))
        if not self.twice:
            values = np.stack([U64(1) << (n - 1).astype(U64), low], axis=1).reshape(-1)
            return K.put_bits(values, np.stack([n, n - 1], axis=1).reshape(-1)).tobytes()
        m = K.bit_length(n)
        values = np.stack([U64(1) << (m - 1).astype(U64), n.astype(U64) ^ (U64(1) << (m - 1).astype(U64)), low], axis=1).reshape(-1)
        return K.put_bits(values, np.stack([m, m - 1, n - 1], axis=1).reshape(-1)).tobytes()

    def decode(self, raw, n):
        out, at = [], 0
        bits = np.unpackbits(np.frombuffer(raw, U8), bitorder="little")
        ones = np.flatnonzero(bits)

        def field(size):
            nonlocal at
            got = int(np.dot(bits[at : at + size].astype(object), [1 << k for k in range(size)])) if size else 0
            at += size
            return got

        for _ in range(n):
            stop = int(ones[np.searchsorted(ones, at)])
            size = stop - at + 1
            at = stop + 1
            if self.twice:
                size = field(size - 1) | 1 << size - 1
            out.append((field(size - 1) | 1 << size - 1) - 1)
        return np.array(out, U64)


class RiceCode(Codec):
    """Quotients by 2^k in unary, remainders in k bits; k is the bits of the mean less one, its byte goes first."""

    name = "golomb_rice"

    @staticmethod
    def parameter(total: int, n: int) -> int:
        return max(0, (total // n).bit_length() - 1) if n else 0

    def encode(self, v):
        if not len(v):
            return b""
        k = self.parameter(int(v.sum(dtype=object)), len(v))
        quotient = (v.astype(U64) >> U64(k)).astype(np.int64)
        ends = np.cumsum(quotient + 1 + k)
        bits = np.zeros(int(ends[-1]), U8)
        bits[ends - 1 - k] = 1
        for j in range(k):
            bits[ends - k + j] = (v.astype(U64) >> U64(j)) & U64(1)
        return bytes([k]) + np.packbits(bits, bitorder="little").tobytes()

    def decode(self, raw, n):
        if not n:
            return np.zeros(0, U64)
        k, bits = raw[0], np.unpackbits(np.frombuffer(raw[1:], U8), bitorder="little")
        ones, at, q, starts = np.flatnonzero(bits), 0, [], []
        for _ in range(n):
            stop = int(ones[np.searchsorted(ones, at)])
            q.append(stop - at)
            starts.append(stop + 1)
            at = stop + 1 + k
        out = np.array(q, U64) << U64(k)
        for j in range(k):
            out |= bits[np.array(starts) + j].astype(U64) << U64(j)
        return out


class GenericCompressor(Codec):
    """A byte compressor over the values as 4-byte words."""

    def __init__(self, method: str):
        self.name, self.method = f"generic_{method}", method

    def encode(self, v):
        raw = v.astype("<u4").tobytes()
        return pa.compress(raw, self.method, asbytes=True) if raw else b""

    def decode(self, raw, n):
        return np.frombuffer(pa.decompress(raw, 4 * n, self.method, asbytes=True), "<u4").astype(U64) if n else np.zeros(0, U64)


class Raw32(Codec):
    name = "raw32"

    def encode(self, v):
        return v.astype("<u4").tobytes()

    def decode(self, raw, n):
        return np.frombuffer(raw, "<u4").astype(U64)

    def encode_many(self, d, offsets):
        return _cut(d.astype("<u4").view(U8), 4 * offsets)

    def decode_many(self, payloads, n):
        return self.decode(b"".join(payloads), 0)


class Raw16(Codec):
    """Integers below 2^16 in two bytes each: the low halves of ids under one high half."""

    name = "raw16"

    def encode(self, v):
        if len(v) and int(v.max()) >> 16:
            raise ValueError("a value needs more than 16 bits")
        return v.astype("<u2").tobytes()

    def decode(self, raw, n):
        return np.frombuffer(raw, "<u2").astype(U64)


class ParquetDelta(Codec):
    """What Parquet's own integer coding makes of the values: a file of one uncompressed column, delta or dictionary coded."""

    def __init__(self, name: str, encoding: str | None):
        self.name, self.encoding = name, encoding

    def encode(self, v):
        import pyarrow.parquet as pq

        out = pa.BufferOutputStream()
        options = {"use_dictionary": False, "column_encoding": self.encoding} if self.encoding else {"use_dictionary": True}
        pq.write_table(pa.table({"v": v.astype("<u4").astype(np.int64)}), out, compression="none", write_statistics=False, store_schema=False, **options)
        return out.getvalue().to_pybytes()

    def decode(self, raw, n):
        import pyarrow.parquet as pq

        return pq.read_table(pa.BufferReader(raw)).column(0).to_numpy().astype(U64)


ALL: dict[str, Codec] = {
    c.name: c
    for c in [
        BinaryPacking("vpack128", 128, True),
        BinaryPacking("pack32", 32, False),
        BinaryPacking("pack16", 16, False),
        BinaryPacking("pack8", 8, False),
        BinaryPacking("horizpack", 128, False, gathers=True),
        BinaryPacking("vpack256", 256, True, lanes=8),
        BinaryPacking("vpack512", 512, True, lanes=16),
        PagePatched("vpatch", vertical=True),
        PagePatched("bucketpatch"),
        PagePatched("wordpatch", words=True),
        LinkPatched("linkpatch", sized=False),
        LinkPatched("sizedpatch", sized=True),
        BlockPatched("blockpatch10", optimal=False),
        BlockPatched("blockpatchopt", optimal=True),
        Simple8b(),
        ByteGroup8(),
        GroupVarint(),
        VariableByte(),
        SplitVector(),
        TinyGroups(),
        EliasCode("elias_gamma", False),
        EliasCode("elias_delta", True),
        RiceCode(),
        *[GenericCompressor(m) for m in ("snappy", "lz4", "zstd", "gzip")],
        Raw32(),
        Raw16(),
        ParquetDelta("parquet_delta", "DELTA_BINARY_PACKED"),
        ParquetDelta("parquet_dictionary", None),
    ]
}
#: Codes that take any unsigned 32-bit integer; the others are for comparison or for a narrower range.
GENERAL = [name for name in ALL if name != "raw16" and not name.startswith("parquet")]
