"""Katz backoff language model: Good-Turing discounted counts, exactly normalised backoff weights, scores.

Orders back off one by one down to single words, and those to one class of unseen words. For a context h and a word w
with count c = c(hw) > 0, P(w|h) = d(c) c / c(h); counts above K are reliable and lose nothing. Else P(w|h) = a(h) P(w|h')
with h' the context without its first word; an unseen context leaves it to h' alone. a(h) shares what the discounts left in
h among the words that never followed it:  a(h) = (1 - sum of seen P(w|h)) / (1 - sum of their P(w|h')). Where a
context has no discounted follower, its denominator is c(h) + 1, so that every context keeps some mass.

The corpus is cut into blocks of a million tokens, and everything that grows with it is exchanged between blocks and
buckets of 64-bit hashes, one order after the other:
  1. text -> blocks: distinct word hashes and the token stream as local numbers (written once; texts are read once);
  2. block -> bucket: each distinct n-gram of a block with its training count; the bucket sums, answers every block, and
     names one block the owner of each entry;
  3. owners count, for each context, its followers by their counts and by those of their tails -> bucket of the context,
     which answers with the sums for the contexts that a block needs: what its discounts left and its tails take;
  4. blocks turn these into backoff weights, order by order, and score their texts, each token by recursion.
A block sends an n-gram once, whatever its frequency, and buckets split hashes evenly: no frequent word, n-gram or
context gathers rows. A block has at most one row for a bucket and none for a bucket that it has nothing for, so there
are never more rows than entries. Only the counts of counts, a dozen numbers for an order, reach the driver. save_model()
writes the n-grams and weights as tables by order and part of the hash, which score_with() reads for other texts.
"""

from __future__ import annotations

import gc

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from laneforge.session import written

from .common import crc_part, freed, trim
from .words import mix, pieces, word_hashes, word_spans

#: Tokens of a block, and entries of a bucket, about.
BLOCK, BUCKET = 1_000_000, 2_000_000
#: Effort of the compression of what is exchanged.
LEVEL = 3
#: Words of the longest n-gram; the largest count that is discounted.
ORDER, K = 3, 5
#: Folders of a saved model for each order.
PARTS = 64
END, START = np.uint64(0x5EED0E4D5EED0E4D), np.uint64(0x5EED57A27B5EED57)
_GRAM = np.uint64(0xD6E8FEB86659FD93)
BLOCKS = "block long, ids array<long>, held binary, lens binary, vocab binary, tokens binary, n_vocab long, n_tokens long"
SLICES = "block long, bucket int, hashes binary, counts binary"
STATS = ["total", "types", "ends", *[f"n{r}" for r in range(1, K + 2)]]
#: What buckets tell blocks (counts of n-grams, sums of contexts); block -1 holds figures of the whole bucket.
ANSWERS = "block long, order int, kind int, bucket int, data binary, more binary, whole binary, " + ", ".join(f"{s} long" for s in STATS)
COUNTS, SUMS = 0, 1
MASSES = "block long, order int, bucket int, hashes binary, seen binary, wanted binary"
RESULT = "id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
#: Rows of a model: n-grams with their counts and log10 probabilities; contexts, without a count, with their log10 weights.
MODEL = "order int, hash long, count long, value double"


def planes(a: np.ndarray) -> bytes:
    """The bytes of an integer array, place by place, so that the high places compress away; their number goes first."""
    return squeeze(np.ascontiguousarray(a.astype("<u8").view(np.uint8).reshape(-1, 8).T).tobytes())


def unplanes(raw: bytes) -> np.ndarray:
    flat = pa.decompress(raw[8:], int.from_bytes(raw[:8], "little"), "zstd", asbytes=True)
    return np.ascontiguousarray(np.frombuffer(flat, np.uint8).reshape(8, -1).T).view("<u8").reshape(-1)


def squeeze(raw: bytes) -> bytes:
    return len(raw).to_bytes(8, "little") + pa.Codec("zstd", compression_level=LEVEL).compress(raw, asbytes=True)


def pack_tokens(local: np.ndarray, size: int) -> bytes:
    """A stream of numbers below size: the 255 most frequent as one byte each, the rest after them."""
    top = np.argsort(-np.bincount(local, minlength=size), kind="stable")[:255]
    rank = np.full(size, 255, np.uint8)
    rank[top] = np.arange(len(top))
    code = rank[local]
    parts = [planes(top), squeeze(code.tobytes()), planes(local[code == 255])]
    return b"".join(len(p).to_bytes(8, "little") + p for p in parts)


def unpack_tokens(raw: bytes) -> np.ndarray:
    parts, at = [], 0
    while at < len(raw):
        n = int.from_bytes(raw[at : at + 8], "little")
        parts.append(raw[at + 8 : at + 8 + n])
        at += 8 + n
    top, code = unplanes(parts[0]), np.frombuffer(pa.decompress(parts[1][8:], int.from_bytes(parts[1][:8], "little"), "zstd", asbytes=True), np.uint8)
    out = np.append(top, np.zeros(256 - len(top), np.uint64))[code].astype(np.int64)
    out[code == 255] = unplanes(parts[2])
    return out


def pack_doubles(a: np.ndarray) -> bytes:
    """The different numbers, and for each place which: sums of a few discounts repeat a lot."""
    kinds, which = np.unique(a, return_inverse=True)
    head = planes(kinds.view(np.uint64))
    return len(head).to_bytes(8, "little") + head + planes(which)


def unpack_doubles(raw: bytes) -> np.ndarray:
    end = 8 + int.from_bytes(raw[:8], "little")
    return unplanes(raw[8:end]).view(np.float64)[unplanes(raw[end:]).astype(np.int64)]


def pack_sorted(a: np.ndarray) -> bytes:
    return planes(np.diff(a, prepend=np.uint64(0)))


def unpack_sorted(raw: bytes) -> np.ndarray:
    return np.cumsum(unplanes(raw), dtype=np.uint64)


def cuts(hashes: np.ndarray, buckets: int) -> np.ndarray:
    """Where each bucket's share of sorted hashes begins, and the end."""
    edges = [np.uint64(-(-(b << 64) // buckets)) for b in range(1, buckets)]
    return np.concatenate([[0], np.searchsorted(hashes, np.array(edges, np.uint64)), [len(hashes)]]).astype(np.int64)


def _table(schema_rows: list[dict], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_pylist(schema_rows, schema)


def _arrow(ddl: str) -> pa.Schema:
    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary(), "double": pa.float64(), "boolean": pa.bool_(), "array<long>": pa.list_(pa.int64())}
    return pa.schema([(name, kinds[kind]) for name, kind in (x.split() for x in ddl.split(", "))])


def _blocks(batches):
    schema, part, made = _arrow(BLOCKS), TaskContext.get().partitionId(), 0
    ids, held, lens, tokens, gathered = [], [], [], [], 0

    def flush():
        nonlocal made, ids, held, lens, tokens, gathered
        vocab, local = np.unique(np.concatenate(tokens), return_inverse=True)
        row = {"block": part << 24 | made, "ids": ids, "held": np.concatenate(held).astype(np.uint8).tobytes(), "lens": np.concatenate(lens).astype("<u4").tobytes(), "vocab": pack_sorted(vocab), "tokens": pack_tokens(local, len(vocab)), "n_vocab": len(vocab), "n_tokens": len(local)}
        made, ids, held, lens, tokens, gathered = made + 1, [], [], [], [], 0
        return _table([row], schema)

    for batch in batches:
        out = np.asarray(batch.column(1).fill_null(False)).astype(bool)
        for at, offsets, data in pieces(batch.column(2)):
            starts, ends, n = word_spans(offsets, data)
            stream = np.full(len(starts) + len(n), END)
            stream[np.arange(len(starts)) + np.repeat(np.arange(len(n)), n)] = word_hashes(data, starts, ends)
            ids += batch.column(0).slice(at, len(n)).to_pylist()
            held.append(out[at : at + len(n)])
            lens.append(n + 1)
            tokens.append(stream)
            gathered += len(stream)
            if gathered >= BLOCK:
                yield flush()
    if ids:
        yield flush()


class Block:
    """One block, with its distinct n-grams of each order up to `order` in the order of their hashes.

    By order: hashes of the n-grams; place, the n-gram that ends at each token; and of each n-gram its context (the
    n-gram of one order less before its last word; one past the end: the start of a text) and its tail (without its
    first word).
    """

    def __init__(self, row: dict, order: int):
        self.id, self.ids = row["block"], row["ids"]
        self.held = np.frombuffer(row["held"], np.uint8).astype(bool)
        self.lens = np.frombuffer(row["lens"], "<u4").astype(np.int64)
        vocab, words = unpack_sorted(row["vocab"]), unpack_tokens(row["tokens"])
        self.train = np.repeat(~self.held, self.lens)
        self.hashes, self.place, self.context, self.tail = {1: vocab}, {1: words}, {}, {}
        first, own, ends_here = np.cumsum(self.lens) - self.lens, mix(vocab)[words], vocab[words]
        for k in range(2, order + 1):
            before, hashes = np.empty(len(words), np.int64), np.empty(len(words), np.uint64)
            before[1:], hashes[1:] = self.place[k - 1][:-1], ends_here[:-1]
            before[first], hashes[first] = len(self.hashes[k - 1]), START + np.uint64(k)
            ends_here = mix(hashes * _GRAM + own)
            self.hashes[k], seen_at, self.place[k] = np.unique(ends_here, return_index=True, return_inverse=True)
            self.context[k], self.tail[k] = before[seen_at], self.place[k - 1][seen_at]

    def contexts(self, k: int) -> np.ndarray:
        """Hashes of the contexts of order k, the start of a text last."""
        return np.append(self.hashes[k - 1], START + np.uint64(k))

    def counts(self, k: int) -> np.ndarray:
        """Training counts of the n-grams."""
        return np.bincount(self.place[k][self.train], minlength=len(self.hashes[k]))


def _forward(k: int, buckets: int):
    @freed
    def run(batches):
        schema = _arrow(SLICES)
        for batch in batches:
            for row in batch.to_pylist():
                b = Block(row, k)
                hashes, n = b.hashes[k], b.counts(k)
                at = cuts(hashes, buckets)
                for j in np.flatnonzero(np.diff(at)).tolist():
                    s = slice(at[j], at[j + 1])
                    yield _table([{"block": b.id, "bucket": j, "hashes": pack_sorted(hashes[s]), "counts": planes(n[s])}], schema)

    return run


def _answer(k: int):
    def run(table: pa.Table) -> pa.Table:
        """Sums a bucket and answers each block: four times the total, plus two where the block owns the entry, plus one where no other has it."""
        rows = table.to_pylist()
        hashes = np.concatenate([unpack_sorted(r["hashes"]) for r in rows])
        each = [unplanes(r["counts"]).astype(np.int64) for r in rows]
        sizes, counts = list(map(len, each)), np.concatenate(each)
        kinds, first, place = np.unique(hashes, return_index=True, return_inverse=True)
        total = np.zeros(len(kinds), np.int64)
        np.add.at(total, place, counts)
        answer = total[place] * 4 + (np.bincount(place, minlength=len(kinds)) == 1)[place]
        answer[first] += 2
        same = np.bincount(np.minimum(total, K + 2), minlength=K + 3)
        stats = {"total": int(total.sum()), "types": int((total > 0).sum()), "ends": int(total[kinds == END].sum()) if k == 1 else 0} | {f"n{r}": int(same[r]) for r in range(1, K + 2)}
        out, at = [{"block": -1, "order": k, "kind": COUNTS, "bucket": rows[0]["bucket"], "data": None} | stats], 0
        for r, n in zip(rows, sizes):
            out.append({"block": r["block"], "order": k, "kind": COUNTS, "bucket": r["bucket"], "data": planes(answer[at : at + n])})
            at += n
        return pa.Table.from_pylist(out, _arrow(ANSWERS))

    return run


def discounts(n: list[int]) -> np.ndarray:
    """d(0..K) and 1 beyond, from the counts of counts n[0] = n1 ...: Good-Turing as Katz renormalises it.

    Where that is not between 0 and 1 (too few data), an absolute discount stands in.
    """
    d = np.ones(K + 2)
    n = [float(x) for x in n]
    absolute = n[0] / (n[0] + 2 * n[1]) if n[0] and n[1] else 0.5
    common = (K + 1) * n[K] / n[0] if n[0] else 1.0
    for r in range(1, K + 1):
        good = ((r + 1) * n[r] / (r * n[r - 1]) - common) / (1 - common) if n[r - 1] and common < 1 else 0.0
        d[r] = good if 0 < good < 1 else (r - absolute) / r
    return d


def kept(d: np.ndarray, c: np.ndarray) -> np.ndarray:
    """The discounted counts."""
    return d[np.minimum(c, K + 1)] * c


def corpus_figures(stats: dict, order: int) -> dict:
    """What every block needs of the whole corpus."""
    none = dict.fromkeys(STATS, 0)
    d = {k: discounts([stats.get(k, none)[f"n{r}"] for r in range(1, K + 2)]) for k in range(1, order + 1)}
    words = stats.get(1, none)
    left = sum((r - r * d[1][r]) * words[f"n{r}"] for r in range(1, K + 1))
    bare = 1 if words["total"] and not left else 0
    return {"N": words["total"], "V": words["types"], "texts": words["ends"], "d": d, "bare": bare, "unseen": (left or 1.0) / (words["total"] + bare) if words["total"] else 1.0}


def sums(m: dict, k: int, seen: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """What the discounts left in contexts (0: nothing was discounted), and the discounted counts of their followers' tails without those above K."""
    counts = np.arange(1, K + 1)
    return (counts * (1 - m["d"][k][1 : K + 1])) @ seen[:K], (counts * m["d"][k - 1][1 : K + 1]) @ seen[K : 2 * K]


class Informed:
    """A block with the buckets' answers: counts, and where the sums of contexts have come, weights."""

    def __init__(self, b: Block, m: dict, answers: list[dict], order: int, everything: bool = False, weighted: bool = True):
        self.b, self.m, self.order, self.everything = b, m, order, everything
        self.total, self.owned, self.sole, self.weight, self.bare = {}, {}, {}, {}, {}
        for k in range(1, order + 1):
            got = self._joined(answers, COUNTS, k, unplanes).astype(np.int64)
            if len(got) != len(b.hashes[k]):
                raise ValueError("a block has not got all its counts")
            self.total[k], self.owned[k], self.sole[k] = got >> 2, (got & 2 > 0) & (got > 3), got & 1 > 0
        #: How often each context of an order was followed by a word.
        self.followed = {k: np.append(self.total[k - 1], m["texts"]) for k in range(2, order + 1)}
        self.wanted = self._wanted()
        #: Contexts that no other block has: all that follows them is here, so their sums are too.
        self.apart = {k: np.append(self.sole[k - 1], False) for k in range(2, order + 1)}
        for k in range(2, order + 1 if weighted else 2):
            hashes, turn = b.contexts(k), np.flatnonzero(self.wanted[k] & ~self.apart[k])
            turn = turn[np.argsort(hashes[turn], kind="stable")]
            left, taken = (self._joined(answers, SUMS, k, unpack_doubles, field) for field in ("data", "more"))
            if len(left) != len(turn):
                raise ValueError("a block has not got all its sums")
            taken = taken + self._joined(answers, SUMS, k, unplanes, "whole").astype(np.float64)
            own = np.flatnonzero(self.wanted[k] & self.apart[k])
            if len(own):
                mine = self.seen(k)[:, own].astype(np.float64)
                more = sums(m, k, mine)
                turn, left, taken = np.append(turn, own), np.append(left, more[0]), np.append(taken, more[1] + mine[2 * K])
            count, bare = self.followed[k][turn], left == 0
            if k == 2:
                below = max(m["N"] + m["bare"], 1)
            else:
                tail = self._tails(k)[turn]
                below = np.maximum(self.followed[k - 1][tail] + self.bare[k - 1][tail], 1)
            self.weight[k], self.bare[k] = np.zeros(len(hashes)), np.zeros(len(hashes), np.int64)
            self.weight[k][turn] = np.log10(np.where(bare, 1.0, left) / (count + bare) / np.maximum(1 - taken / below, 1e-300))
            self.bare[k][turn] = bare

    @staticmethod
    def _joined(answers: list[dict], kind: int, k: int, unpack, field: str = "data") -> np.ndarray:
        got = [unpack(r[field]) for r in sorted((r for r in answers if r["kind"] == kind and r["order"] == k), key=lambda r: r["bucket"])]
        return np.concatenate(got) if got else np.zeros(0, np.uint64)

    def _tails(self, k: int) -> np.ndarray:
        """The context of order k - 1 that each context of order k ends with."""
        return np.append(self.b.tail[k - 1], len(self.b.hashes[k - 2]))

    def _wanted(self) -> dict:
        """The contexts whose sums this block needs: they lack a follower, or have one whose count is not discounted, or end a longer one that is needed."""
        out = {}
        for k in range(self.order, 1, -1):
            b, seen = self.b, self.followed[k] > 0
            if self.everything:
                out[k] = seen
                continue
            need = ((self.total[k] == 0) & seen[b.context[k]]) | (self.total[k] > K)
            out[k] = np.zeros(len(seen), bool)
            out[k][b.context[k][need]] = True
            if k < self.order:
                out[k][self._tails(k + 1)[out[k + 1]]] = True
        return out

    def seen(self, k: int) -> np.ndarray:
        """Of each context of order k, among the n-grams that this block owns: followers of counts 1 to K, those whose tails have counts 1 to K, and the other tails' counts."""
        context, mine, n = self.b.context[k], self.owned[k], len(self.followed[k])
        tail = self.total[k - 1][self.b.tail[k]]
        of = lambda pick, what=None: np.bincount(context[pick], None if what is None else what[pick], n).astype("<u8")
        out = np.empty((2 * K + 1, n), "<u8")
        for i, (c, r) in enumerate((c, r) for c in (self.total[k], tail) for r in range(1, K + 1)):
            out[i] = of(mine & (c == r))
        out[2 * K] = of(mine & (tail > K), tail)
        return out

    def direct(self, k: int) -> np.ndarray:
        """Probabilities of the seen n-grams of order k; for single words, of the unseen too."""
        if k == 1:
            return np.where(self.total[1] > 0, kept(self.m["d"][1], self.total[1]) / max(self.m["N"] + self.m["bare"], 1), self.m["unseen"])
        context = self.b.context[k]
        return kept(self.m["d"][k], self.total[k]) / np.maximum(self.followed[k][context] + self.bare[k][context], 1)

    def token_scores(self) -> np.ndarray:
        """log10 P of every token, by recursion from single words up."""
        with np.errstate(divide="ignore"):
            out = np.log10(self.direct(1))[self.b.place[1]]
            for k in range(2, self.order + 1):
                at = self.b.place[k]
                out = np.where((self.total[k] > 0)[at], np.log10(self.direct(k))[at], out + self.weight[k][self.b.context[k][at]])
        return out


def _masses(m: dict, order: int, buckets: dict, everything: bool):
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        rows = []
        for row in left.to_pylist():  # one
            b = Block(row, order)
            own = Informed(b, m, right.to_pylist(), order, everything, weighted=False)
            for k in range(2, order + 1):
                seen, wanted, hashes = own.seen(k), own.wanted[k], b.contexts(k)
                use = np.flatnonzero((wanted | seen.any(axis=0)) & ~own.apart[k])
                use = use[np.argsort(hashes[use], kind="stable")]
                at = cuts(hashes[use], buckets[k - 1])
                for j in np.flatnonzero(np.diff(at)).tolist():
                    s = use[at[j] : at[j + 1]]
                    rows.append({"block": b.id, "order": k, "bucket": j, "hashes": pack_sorted(hashes[s]), "seen": planes(seen[:, s].reshape(-1)), "wanted": np.packbits(wanted[s]).tobytes()})
        return pa.Table.from_pylist(rows, _arrow(MASSES))

    return run


def _sum_up(m: dict):
    def run(table: pa.Table) -> pa.Table:
        """The sums of a bucket's contexts, for the blocks that want them."""
        rows = table.to_pylist()
        k = rows[0]["order"]
        hashes = [unpack_sorted(r["hashes"]) for r in rows]
        kinds, place = np.unique(np.concatenate(hashes), return_inverse=True)
        total, at = np.zeros((2 * K + 1, len(kinds))), 0
        for r, h in zip(rows, hashes):  # a row has a context once, and only one row is unpacked at a time
            total[:, place[at : at + len(h)]] += unplanes(r["seen"]).reshape(2 * K + 1, -1)
            at += len(h)
        left, taken = sums(m, k, total)
        out, at = [], 0
        for r, h in zip(rows, hashes):
            want = place[at : at + len(h)][np.unpackbits(np.frombuffer(r["wanted"], np.uint8))[: len(h)].astype(bool)]
            if len(want):
                out.append({"block": r["block"], "order": k, "kind": SUMS, "bucket": r["bucket"], "data": pack_doubles(left[want]), "more": pack_doubles(taken[want]), "whole": planes(total[2 * K][want])})
            at += len(h)
        return pa.Table.from_pylist(out, _arrow(ANSWERS))

    return run


def _finish(m: dict, order: int):
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return pa.Table.from_pylist([], _arrow(RESULT))
        b = Block(left.to_pylist()[0], order)
        own = Informed(b, m, right.to_pylist(), order)
        texts = np.repeat(np.arange(len(b.lens)), b.lens)
        add = lambda x: np.bincount(texts, x, len(b.lens))
        c = own.total[1][b.place[1]]
        return pa.table({"id": pa.array(b.ids, pa.int64()), "held_out": pa.array(b.held), "n_tokens": b.lens, "n_known": add(c > 0).astype(np.int64), "train_tokens": np.full(len(b.lens), m["N"], np.int64), "base_score": add(np.log10((c + 0.5) / (m["N"] + 0.5 * (m["V"] + 1)))), "score": add(own.token_scores())})

    return run


def _model_rows(m: dict, order: int):
    """What a block owns: its n-grams, the contexts that are n-grams of its own, and with the end of texts the starts."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        parts = [pa.Table.from_pylist([], _arrow(MODEL))]
        for row in left.to_pylist():
            b = Block(row, order)
            own = Informed(b, m, right.to_pylist(), order, everything=True)
            for k in range(1, order + 1):
                o = own.owned[k]
                parts.append(pa.table({"order": np.full(int(o.sum()), k, np.int32), "hash": b.hashes[k][o].view(np.int64), "count": own.total[k][o], "value": np.log10(own.direct(k)[o])}))
            for k in range(2, order + 1):
                o = np.append(own.owned[k - 1], own.owned[1][np.searchsorted(b.hashes[1], END)]) & own.wanted[k]
                parts.append(pa.table({"order": np.full(int(o.sum()), k, np.int32), "hash": b.contexts(k)[o].view(np.int64), "count": pa.nulls(int(o.sum()), pa.int64()), "value": own.weight[k][o]}))
        return pa.concat_tables(parts)

    return run


def _trimmed(run, tables: int = 1):
    """A function over one or two tables that gives memory back after each group."""

    def one(table: pa.Table) -> pa.Table:
        try:
            return run(table)
        finally:
            trim()

    def two(left: pa.Table, right: pa.Table) -> pa.Table:
        try:
            return run(left, right)
        finally:
            trim()

    return one if tables == 1 else two


class Trained:
    """The blocks of a corpus, the buckets' answers for every order, and the figures of the whole corpus."""

    def __init__(self, spark: SparkSession, docs: DataFrame, held, id_col: str, text_col: str, order: int, everything: bool = False):
        if order < 1:
            raise ValueError("order is 1 or more")
        self.spark = spark
        source = docs.select(F.col(id_col).cast("long").alias("id"), held.alias("held"), F.col(text_col).cast("string").alias("text"))
        self.blocks = written(spark, source.mapInArrow(_blocks, BLOCKS), "katz-blocks", "zstd")
        n_blocks, n_vocab, n_tokens = self.blocks.agg(F.count("*"), F.sum("n_vocab"), F.sum("n_tokens")).first()
        least = int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.tasks = max(least, 2 * n_blocks)
        buckets = {k: 1 + (n_vocab if k == 1 else n_tokens) // BUCKET if n_blocks else 1 for k in range(1, order + 1)}
        self.answers, stats = [], {}
        for k in range(1, order + 1):
            sent = self.blocks.mapInArrow(_forward(k, buckets[k]), SLICES).repartition(max(2 * buckets[k], least), "bucket")
            self.answers.append(written(spark, sent.groupBy("bucket").applyInArrow(_trimmed(_answer(k)), ANSWERS), "katz-counts", "zstd"))
            del sent
            stats[k] = self.answers[-1].filter("block = -1").agg(*[F.coalesce(F.sum(s), F.lit(0)).alias(s) for s in STATS]).first().asDict()
            self._drop_shuffles()
        self.figures = corpus_figures(stats, order)
        if order > 1:
            masses = self.informed(_masses(self.figures, order, buckets, everything), MASSES).repartition(max(2 * sum(buckets.values()), least), "order", "bucket")
            self.answers.append(written(spark, masses.groupBy("order", "bucket").applyInArrow(_trimmed(_sum_up(self.figures)), ANSWERS), "katz-sums", "zstd"))
            del masses
            self.answers[-1].isEmpty()
            self._drop_shuffles()

    def _drop_shuffles(self) -> None:
        """Spark drops the shuffle files of steps that nothing refers to when the driver collects its garbage; it refers to a query until the next one ran."""
        for _ in range(2):
            self.spark.range(1).collect()
            gc.collect()
            self.spark.sparkContext._jvm.System.gc()

    def informed(self, run, schema: str) -> DataFrame:
        """Runs over each block with its answers so far."""
        told = None
        for answers in self.answers:
            one = answers.filter("block >= 0").select("block", "order", "kind", "bucket", "data", "more", "whole")
            told = one if told is None else told.unionByName(one)
        spread = lambda df: df.repartition(self.tasks, "block").groupBy("block")
        return spread(self.blocks).cogroup(spread(told)).applyInArrow(_trimmed(run, 2), schema)


def katz_scores(spark: SparkSession, docs: DataFrame, held, id_col: str = "doc_id", text_col: str = "text", order: int = ORDER) -> DataFrame:
    """Scores every whole text with a model of the texts for which `held` (a boolean column) is not true.

    order: the words of the longest n-gram. Tokens are words of A-Z-lower-cased text between white space, then one
    end. A null text is empty and so has one token. Rows may repeat or have null ids: each is scored (and, unless held,
    learnt from) as it stands. No training rows: every word is unseen and probability is one. An empty table gives no
    rows; other columns are not read.
    """
    t = Trained(spark, docs, held, id_col, text_col, order)
    return t.informed(_finish(t.figures, order), RESULT)


def save_model(spark: SparkSession, docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", order: int = ORDER) -> None:
    """Learns from all texts of docs and writes three tables under path, the first two by order and part of the hash.

    ngrams (order, part, hash, count, log10_p), weights (order, part, hash of the context, log10_weight), and figures
    (order of the model, log10 probability of an unseen word).
    """
    t = Trained(spark, docs, F.lit(False), id_col, text_col, order, everything=True)
    rows = written(spark, t.informed(_model_rows(t.figures, order), MODEL).withColumn("part", F.pmod(F.col("hash"), F.lit(PARTS)).cast("int")), "katz-model", "zstd")
    out = lambda df, name: df.repartition("order", "part").sortWithinPartitions("hash").write.partitionBy("order", "part").parquet(f"{path}/{name}")
    out(rows.filter("count IS NOT NULL").withColumnRenamed("value", "log10_p"), "ngrams")
    out(rows.filter("count IS NULL").drop("count").withColumnRenamed("value", "log10_weight"), "weights")
    spark.createDataFrame([(order, float(np.log10(t.figures["unseen"])))], "model_order int, unseen double").coalesce(1).write.parquet(f"{path}/figures")


def _chains(order: int):
    """Each text's tokens as hashes of the n-grams that end there and of their contexts, equal ones counted."""

    @freed
    def run(batches):
        made, part = 0, TaskContext.get().partitionId()
        names = [f"g{k}" for k in range(1, order + 1)] + [f"c{k}" for k in range(2, order + 1)]
        for batch in batches:
            for at, offsets, data in pieces(batch.column(1)):
                starts, ends, n = word_spans(offsets, data)
                lens = n + 1
                stream = np.full(int(lens.sum()), END)
                stream[np.arange(len(starts)) + np.repeat(np.arange(len(n)), n)] = word_hashes(data, starts, ends)
                first, grams, contexts = np.cumsum(lens) - lens, [stream], []
                for k in range(2, order + 1):
                    before = np.concatenate([stream[:1], grams[-1][:-1]])
                    before[first] = START + np.uint64(k)
                    contexts.append(before)
                    grams.append(mix(before * _GRAM + mix(stream)))
                text = np.repeat(np.arange(len(n)), lens)
                _, place, times = np.unique(mix(grams[-1] + mix(text.astype(np.uint64) + np.uint64(1))), return_index=True, return_counts=True)
                ids = batch.column(0).slice(at, len(n)).take(pa.array(text[place]))
                row = (part << 40) + made + text[place]
                made += len(n)
                yield pa.RecordBatch.from_arrays([pa.array(row), ids, pa.array(times.astype(np.int64)), *[pa.array(x[place].view(np.int64)) for x in (*grams, *contexts)]], ["row", "id", "times", *names])

    return run


def score_with(spark: SparkSession, path: str, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_tokens, score of every whole text by a saved model: each token looks its n-grams and contexts up, longest first."""
    order, unseen = spark.read.parquet(f"{path}/figures").first()
    fields = ", ".join(["row long, id long, times long", *[f"g{k} long" for k in range(1, order + 1)], *[f"c{k} long" for k in range(2, order + 1)]])
    source = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    rows = written(spark, source.mapInArrow(_chains(order), fields), "katz-chains", "zstd")
    grams, weights = (spark.read.schema(f"hash long, {value} double, order int, part int").parquet(f"{path}/{name}") for name, value in (("ngrams", "log10_p"), ("weights", "log10_weight")))
    score = None
    for k in range(1, order + 1):
        rows = rows.join(grams.filter(F.col("order") == k).select(F.col("hash").alias(f"g{k}"), F.col("log10_p").alias(f"p{k}")), f"g{k}", "left")
        if k == 1:
            score = F.coalesce("p1", F.lit(unseen))
        else:
            rows = rows.join(weights.filter(F.col("order") == k).select(F.col("hash").alias(f"c{k}"), F.col("log10_weight").alias(f"w{k}")), f"c{k}", "left")
            score = F.coalesce(F.col(f"p{k}"), F.coalesce(f"w{k}", F.lit(0.0)) + score)
    return rows.groupBy("row", "id").agg(F.sum("times").alias("n_tokens"), F.sum(F.col("times") * score).alias("score")).drop("row")


def op5_katz_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return katz_scores(spark, docs, crc_part("doc_id", 5) == 1).withColumnRenamed("id", "doc_id")
