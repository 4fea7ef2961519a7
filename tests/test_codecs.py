"""Kernels and codes: worked examples, layouts, round trips, sizes."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from laneforge.functions import codecs
from laneforge.functions import kernels as K
from laneforge.functions.codecs import ALL, GENERAL, choose_widths
from laneforge.plans.pipeline import batch_deltas, batch_undeltas, decode_batch, decode_fused, encode_batch

EXAMPLE = np.array([2, 2, 1, 2, 38, 2, 1, 3, 2, 32, 2, 52, 2, 3, 3, 1], np.uint64)
SLOW = {"splitvec", "blockpatchopt", "elias_gamma", "elias_delta", "golomb_rice"}


def test_worked_example():
    b, m, c, cost = choose_widths(EXAMPLE.reshape(1, -1))
    assert (b[0], m[0], c[0], cost[0]) == (2, 6, 3, 68)
    width = K.bit_length(EXAMPLE)
    costs = [16 * w + int((width > w).sum()) * (8 + 6 - w) for w in range(7)]
    assert costs == [224, 185, 68, 81, 94, 107, 96]
    place = np.flatnonzero(width > 2)
    assert place.tolist() == [4, 9, 11] and (EXAMPLE[place] >> np.uint64(2)).tolist() == [9, 8, 13]
    # Width, largest width, number of exceptions and their places; truncated values; high parts of 4 bits.
    assert 8 * (3 + 3) + 2 * 16 + 3 * 4 == 92


def test_delta_example():
    x = np.array([1, 4, 13])
    d = x.copy()
    assert K.delta(d, out=d).tolist() == [1, 3, 9]
    assert K.undelta(d, out=d).tolist() == [1, 4, 13]
    assert K.delta(np.array([3, 5, 6, 9, 10, 20, 30]), 4).tolist() == [3, 5, 6, 9, 7, 15, 24]
    for stride in (1, 4):
        for n in range(12):
            x = np.sort(np.random.default_rng(n).integers(0, 1000, n))
            assert K.undelta(K.delta(x, stride), stride).tolist() == x.tolist()


def test_or_identity():
    assert K.or_widths(np.array([[1, 3]], np.uint64)).tolist() == [2]
    rows = np.random.default_rng(1).integers(0, 1 << 32, (50, 16)).astype(np.uint64) >> np.random.default_rng(2).integers(0, 32, (50, 1)).astype(np.uint64)
    assert K.or_widths(rows).tolist() == K.bit_length(rows.reshape(-1)).reshape(rows.shape).max(axis=1).tolist()
    assert K.bit_length(np.array([0, 1, 2, 2**32 - 1, 2**31], np.uint64)).tolist() == [0, 1, 2, 32, 32]


def test_scalar_layout():
    v = np.arange(1, 9, dtype=np.uint64).reshape(1, -1)
    assert K.pack_scalar(v, 4).shape == (1, 1)
    assert int(K.pack_scalar(v, 4)[0, 0]) == sum(x << 4 * i for i, x in enumerate(range(1, 9)))
    five = K.pack_scalar(v, 5)
    assert five.shape == (1, 2) and K.wasted_bits(8, 5) == 24
    assert int(five[0, 0]) >> 30 == 7 & 3 and int(five[0, 1]) & 7 == 7 >> 2


def test_vertical_layout():
    v = np.arange(32, dtype=np.uint64).reshape(1, -1)
    padded = np.zeros((1, 128), np.uint64)
    padded[0, :32] = v
    words = K.pack_vertical(padded, 5)[0].reshape(5, 4)
    for lane in range(4):
        own = [int(x) for x in v[0, lane::4]]
        stream = sum(x << 5 * i for i, x in enumerate(own))
        assert [int(words[0, lane]), int(words[1, lane])] == [stream & 0xFFFFFFFF, stream >> 32]


@pytest.mark.parametrize("b", range(33))
def test_packing(b):
    rng = np.random.default_rng(b)
    v = rng.integers(0, 1 << b, (5, 128)).astype(np.uint64) if b else np.zeros((5, 128), np.uint64)
    for k in (8, 16, 32, 128):
        w = K.pack_scalar(v[:, :k], b)
        assert w.shape[1] == -(-k * b // 32)
        assert (K.unpack_scalar(w, b, k) == v[:, :k]).all() and (K.unpack_horizontal(w, b, k) == v[:, :k]).all()
        spare = K.wasted_bits(k, b)
        if spare and b:
            w[:, -1] |= np.uint32((0xFFFFFFFF << (32 - spare)) & 0xFFFFFFFF)
            assert (K.unpack_scalar(w, b, k) == v[:, :k]).all() and (K.unpack_horizontal(w, b, k) == v[:, :k]).all()
    vert = K.pack_vertical(v, b)
    assert vert.shape[1] == 4 * b and (K.unpack_vertical(vert, b) == v).all()
    big = v | np.uint64(1 << 40)
    assert (K.pack_scalar(big, b, mask=True) == K.pack_scalar(v, b)).all()
    if b < 32:
        assert (K.pack_vertical(v | np.uint64(1 << b), b, mask=True) == vert).all()


def arrays():
    rng = np.random.default_rng(7)
    yield from (np.zeros(n, np.uint64) for n in (0, 1, 3, 128, 500))
    yield from (np.full(n, 2**32 - 1, np.uint64) for n in (1, 4, 128, 300))
    for n in (1, 3, 4, 5, 31, 32, 33, 127, 128, 129, 640, 2047, 2048, 2049):
        yield rng.integers(0, 1 << 9, n).astype(np.uint64)
        yield (rng.integers(0, 1 << 32, n) >> rng.integers(0, 33, n)).astype(np.uint64)
        spiked = rng.integers(0, 4, n).astype(np.uint64)
        spiked[:: 97] = 2**32 - 1
        yield spiked
        rare = rng.integers(0, 8, n).astype(np.uint64)
        rare[rng.random(n) < 0.08] += np.uint64(1 << 20)
        yield rare


@pytest.mark.parametrize("name", [*GENERAL, "parquet_delta", "parquet_dictionary"])
def test_round_trip(name):
    for v in arrays():
        raw = ALL[name].encode(v)
        assert isinstance(raw, bytes)
        assert np.array_equal(ALL[name].decode(raw, len(v)), v), (name, len(v))


@pytest.mark.parametrize("name", [n for n in GENERAL if n not in SLOW])
def test_round_trip_of_pages(name):
    rng = np.random.default_rng(3)
    for n in (65535, 65536):
        v = (rng.integers(0, 1 << 32, n) >> rng.integers(10, 33, n)).astype(np.uint64)
        assert np.array_equal(ALL[name].decode(ALL[name].encode(v), n), v)


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, 2**32 - 1), max_size=300), st.sampled_from(sorted(GENERAL)))
def test_round_trip_of_anything(values, name):
    v = np.array(values, np.uint64)
    assert ALL[name].decode(ALL[name].encode(v), len(v)).tolist() == values


def test_sizes_compare():
    rng = np.random.default_rng(5)
    size = lambda name, v: len(ALL[name].encode(v))
    for v in arrays():
        if len(v) >= 128:
            assert size("vpatch", v) >= size("bucketpatch", v)
            assert size("blockpatchopt", v) <= size("blockpatch10", v)
        assert size("bytegroup8", v) * 8 >= 9 * len(v)
    dense = rng.geometric(0.06, 65536).astype(np.uint64)
    bits = {n: 8 * size(n, dense) / len(dense) for n in ("vpack128", "pack32", "vpatch", "bucketpatch", "linkpatch", "sizedpatch", "simple8b", "vbyte", "bytegroup8", "splitvec")}
    assert bits["bucketpatch"] <= bits["vpatch"] < bits["pack32"] < bits["vpack128"] < bits["vbyte"] < bits["bytegroup8"]
    assert bits["sizedpatch"] <= bits["linkpatch"]


def test_page_layout_sizes():
    """Bytes of the page-patched page, part by part, for a page of one block."""
    v = np.tile(EXAMPLE, 8)
    b, m, c, _ = choose_widths(v.reshape(1, -1))
    notes = 2 + 1 + int(c[0])
    want = 4 + 16 * int(b[0]) + 4 + notes + -notes % 4 + 4 + 4 + 4 * int(m[0] - b[0]) * -(-int(c[0]) // 32)
    assert len(ALL["bucketpatch"].encode(v)) == want


def test_batches():
    rng = np.random.default_rng(9)
    lists = [np.unique(rng.integers(0, 1 << 20, n)) for n in (0, 1, 5, 130, 4000, 2, 127, 700)]
    x, offsets = np.concatenate(lists), np.concatenate([[0], np.cumsum(list(map(len, lists)))])
    for stride in (0, 1, 4):
        d = batch_deltas(x, offsets, stride)
        assert np.array_equal(batch_undeltas(d, offsets, stride), x)
        for codec in GENERAL:
            payloads = encode_batch(d, offsets, codec)
            assert payloads == [ALL[codec].encode(d[a:b]) for a, b in zip(offsets[:-1], offsets[1:])], codec
            assert np.array_equal(decode_batch(payloads, np.diff(offsets), codec), d), codec
            assert np.array_equal(decode_fused(payloads, np.diff(offsets), codec, stride), x), codec
        assert encode_batch(d[:0], np.array([0]), "vpatch") == [] and len(decode_batch([], np.zeros(0, np.int64), "blockpatch10")) == 0


def test_narrow_code():
    v = np.array([0, 5, 65535], np.uint64)
    assert ALL["raw16"].decode(ALL["raw16"].encode(v), 3).tolist() == v.tolist()
    with pytest.raises(ValueError, match="16 bits"):
        ALL["raw16"].encode(v + np.uint64(1))


def test_links_of_any_distance():
    """Exceptions so far apart that links need steps in between, against following them one by one."""
    rng = np.random.default_rng(4)
    for b in (0, 1, 2, 3):
        for share in (0.005, 0.03, 0.3):
            v = rng.integers(0, 1 << b, 128 * 20).astype(np.uint64) if b else np.zeros(128 * 20, np.uint64)
            v[rng.random(len(v)) < share] += np.uint64(1 << 12)
            for name in ("linkpatch", "sizedpatch"):
                assert np.array_equal(ALL[name].decode(ALL[name].encode(v), len(v)), v)


def test_word_code_of_segments():
    """Segments coded together are what they are on their own, long ones too."""
    from laneforge.functions.codecs import simple8b_values, simple8b_words

    rng = np.random.default_rng(6)
    n = [0, 1, 300, 5000, 7, 0, 2049]
    v = (rng.integers(0, 1 << 32, sum(n)) >> rng.integers(0, 33, sum(n))).astype(np.uint64)
    ends = np.concatenate([[0], np.cumsum(n)])
    words, per = simple8b_words(v, ends)
    for k in range(len(n)):
        assert words[per[k] : per[k + 1]].tobytes() == ALL["simple8b"].encode(v[ends[k] : ends[k + 1]])
    assert np.array_equal(simple8b_values(words, per, np.array(n)), v)


def test_word_patched_pages_share_their_calls(monkeypatch):
    """The high parts of all pages are coded and decoded together, as if alone; bytes after them are not read as words."""
    rng = np.random.default_rng(9)
    n = rng.integers(0, 500, 40)
    d = (rng.integers(0, 1 << 32, int(n.sum())) >> rng.choice([4, 20, 28, 31], int(n.sum()))).astype(np.uint64)
    offsets, code = np.concatenate([[0], np.cumsum(n)]), ALL["wordpatch"]
    alone = [code.encode(d[a:b]) for a, b in zip(offsets[:-1], offsets[1:])]
    calls = []
    for name in ("simple8b_words", "simple8b_values"):
        own = getattr(codecs, name)
        monkeypatch.setattr(codecs, name, lambda *a, own=own: (calls.append(1), own(*a))[1])
    payloads = code.encode_many(d, offsets)
    assert payloads == alone
    assert np.array_equal(code.decode_many(payloads, n), d)
    assert len(calls) == 2


def test_best_width_is_the_best():
    """The optimal per-block rule against coding every block at every width alone."""
    rng = np.random.default_rng(8)
    rows = (rng.integers(0, 1 << 20, (6, 128)) >> rng.choice([0, 8, 12, 16], (6, 128))).astype(np.uint64)
    best = len(ALL["blockpatchopt"].encode(rows.reshape(-1)))
    total = 0
    for row in rows:
        sizes = []
        for b in range(33):
            place = np.flatnonzero(row >> np.uint64(b)) if b < 32 else np.zeros(0, np.int64)
            coded = np.concatenate([np.diff(place, prepend=-1) - 1, (row[place] >> np.uint64(b)).astype(np.int64)]).astype(np.uint64)
            sizes.append(4 + 16 * b + len(ALL["simple8b"].encode(coded)))
        total += min(sizes)
    assert best == total


def test_rejects():
    with pytest.raises(ValueError, match="1 values are not"):
        batch_deltas(np.array([-1, 2]), np.array([0, 2]), 1)
    with pytest.raises(ValueError, match="1 values are not"):
        batch_deltas(np.array([1, 2**32]), np.array([0, 2]), 1)
    with pytest.raises(ValueError, match="sorted"):
        batch_deltas(np.array([5, 2]), np.array([0, 2]), 1)


@pytest.mark.parametrize("name", ["splitvec", "linkpatch", "sizedpatch"])
def test_lists_of_a_batch_are_coded_together(name, monkeypatch):
    """Thousands of lists need no call for each of them, and come out as they do alone."""
    rng = np.random.default_rng(12)
    n = np.concatenate([rng.integers(1, 4, 3000), [0, 128, 700, 256, 5000]])
    v = (rng.integers(0, 1 << 32, n.sum()) >> rng.integers(0, 33, n.sum())).astype(np.uint64)
    offsets = np.concatenate([[0], np.cumsum(n)])
    want = [ALL[name].encode(v[a:b]) for a, b in zip(offsets[:-1], offsets[1:])]

    def alone(self, *_):
        raise AssertionError("a list was coded alone")

    monkeypatch.setattr(type(ALL[name]), "encode", alone)
    monkeypatch.setattr(type(ALL[name]), "decode", alone)
    assert encode_batch(v, offsets, name) == want
    assert np.array_equal(decode_batch(want, n, name), v)


def test_runs_of_long_lists_are_the_cheapest():
    """Lists of many pieces against one program over the whole list, on widths whose cuts depend on values far away too."""
    from laneforge.functions.layout import SPLIT_LENGTHS, SPLIT_WIDTHS

    rng = np.random.default_rng(13)
    for v in (np.zeros(2100, np.uint64), np.full(1500, 7, np.uint64), np.tile(EXAMPLE, 80), (rng.integers(0, 1 << 32, 1801) >> rng.integers(0, 33, 1801)).astype(np.uint64)):
        width, n = K.bit_length(v).tolist(), len(v)
        least, pick = [0] * (n + 1), [0] * n
        for i in range(n - 1, -1, -1):
            cost = {k: 8 + k * min(w for w in SPLIT_WIDTHS if w >= max(width[i : i + k])) + least[i + k] for k in SPLIT_LENGTHS if i + k <= n}
            least[i] = min(cost.values())
            pick[i] = max(k for k in cost if cost[k] == least[i])
        at, runs = 0, []
        while at < n:
            runs.append(SPLIT_LENGTHS.index(pick[at]))
            at += pick[at]
        raw = ALL["splitvec"].encode(v)
        assert int.from_bytes(raw[:4], "little") == len(runs) and [x >> 4 for x in raw[4 : 4 + len(runs)]] == runs
        assert len(raw) == 4 + len(runs) + -(-(least[0] - 8 * len(runs)) // 8)


def test_optimal_rule_sizes_from_widths():
    """The sizes of blocks at every width come from the widths of their values alone, and the least is taken, the larger width on ties."""
    code, rng = ALL["blockpatchopt"], np.random.default_rng(3)
    rows = rng.integers(0, 1 << 32, (300, 128)).astype(np.uint64) >> rng.integers(0, 33, (300, 128)).clip(rng.integers(0, 33, (300, 1))).astype(np.uint64)
    width = K.bit_length(rows.reshape(-1)).astype(np.uint8).reshape(rows.shape)
    sizes = np.full((len(rows), 33), 1 << 40)
    for b in range(33):
        at = np.flatnonzero(width.max(axis=1) >= b)
        flat, ends, _ = code._exceptions(rows, width, at, np.full(len(at), b))
        sizes[at, b] = 16 * b + 8 * np.diff(codecs.simple8b_words(flat, ends)[1])
        assert code._sizes(width, at, np.full(len(at), b)).tolist() == sizes[at, b].tolist()
    assert code._best(width).tolist() == (32 - sizes[:, ::-1].argmin(axis=1)).tolist()
