"""The language model against a plain recursive one of tuples and dictionaries."""

import math
import zlib
from collections import Counter, defaultdict
from functools import cache

import pytest
from pyspark.sql import functions as F

from laneforge.llm import katz
from laneforge.llm.common import crc_part

EDGES = [(None, None), (900001, ""), (900002, " \t\n"), (900003, "Zzyzx unseen wörds"), (900003, "Zzyzx unseen wörds"), (900005, "word " * 2000), (900006, "pair bond " * 30), (900007, "alpha beta gamma " * 9 + "alpha beta delta"), (900008, "bond alpha pair gamma"), (900009, "solo duet " * 11)]
UP = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


class Plain:
    def __init__(self, texts, order):
        self.order, self.grams, self.contexts = order, [Counter() for _ in range(order + 1)], [Counter() for _ in range(order + 1)]
        self.followers = [defaultdict(list) for _ in range(order + 1)]
        for text in texts:
            t = self.tokens(text)
            for at, w in enumerate(t):
                for k in range(1, order + 1):
                    h = self.context(t, at, k)
                    self.grams[k][(*h, w)] += 1
                    self.contexts[k][h] += 1
        for k in range(1, order + 1):
            for g in self.grams[k]:
                self.followers[k][g[:-1]].append(g)
        self.total = sum(self.grams[1].values())
        self.d = [None] + [self.good_turing(Counter(self.grams[k].values())) for k in range(1, order + 1)]
        self.weight = cache(self.weight)

    @staticmethod
    def tokens(text):
        return [x for x in "".join(c if c not in "\t\n\x0b\x0c\r" else " " for c in (text or "").translate(UP)).split(" ") if x] + ["</s>"]

    @staticmethod
    def context(t, at, k):
        return tuple((["<s>"] * k + t[:at])[-(k - 1) :]) if k > 1 else ()

    @staticmethod
    def good_turing(n):
        """Discount of a count of 1 to 5; above, none."""
        share = 6 * n[6] / n[1] if n[1] else 1
        out = {}
        for r in range(1, 6):
            d = ((r + 1) * n[r + 1] / (r * n[r]) - share) / (1 - share) if n[r] and share < 1 else 0
            out[r] = d if 0 < d < 1 else (r - (n[1] / (n[1] + 2 * n[2]) if n[1] and n[2] else 0.5)) / r
        return out

    def cut(self, k, c):
        return c * self.d[k].get(c, 1)

    def seen(self, k, g):
        h = g[:-1]
        bare = all(self.grams[k][f] > 5 for f in self.followers[k][h])
        return self.cut(k, self.grams[k][g]) / (self.contexts[k][h] + bare)

    def weight(self, k, h):
        left = 1 - sum(self.seen(k, g) for g in self.followers[k][h])
        return left / (1 - sum(self.p(k - 1, g[1:]) for g in self.followers[k][h])) if k > 1 else left

    def p(self, k, g):
        if self.grams[k][g]:
            return self.seen(k, g)
        if k == 1:
            return self.weight(1, ()) if self.total else 1.0
        return (self.weight(k, g[:-1]) if self.contexts[k][g[:-1]] else 1.0) * self.p(k - 1, g[1:])

    def score(self, text):
        t = self.tokens(text)
        return sum(math.log10(self.p(self.order, (*self.context(t, at, self.order), w))) for at, w in enumerate(t))


def rows_of(spark, sf, n):
    return [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").limit(n).collect()] + EDGES


@pytest.mark.parametrize(("order", "block"), [(1, 1_000_000), (2, 400), (3, 400), (3, 1_000_000), (4, 5000)])
def test_scores(spark, sf, monkeypatch, order, block):
    rows = rows_of(spark, sf, 60)
    held = [zlib.crc32(str("" if i is None else i).encode()) % 5 == 1 for i, _ in rows]
    plain = Plain([t for (_, t), h in zip(rows, held) if not h], order)
    n, v = plain.total, len(plain.grams[1])
    want = Counter()
    for (i, text), h in zip(rows, held):
        t = plain.tokens(text)
        base = sum(math.log10((plain.grams[1][w,] + 0.5) / (n + 0.5 * (v + 1))) for w in t)
        want[i, h, len(t), sum(plain.grams[1][w,] > 0 for w in t), n, round(base, 5), round(plain.score(text), 5)] += 1
    monkeypatch.setattr(katz, "BLOCK", block)
    frame = spark.createDataFrame(rows, "doc_id long, text string").withColumn("id", F.lit("clash")).repartition(3)
    got = katz.katz_scores(spark, frame, crc_part("doc_id", 5) == 1, order=order).collect()
    assert Counter((r["id"], r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 5), round(r["score"], 5)) for r in got) == want


def test_plain_model_is_normalised(spark, sf):
    plain = Plain([t for _, t in rows_of(spark, sf, 40)], 3)
    words = [g[0] for g in plain.grams[1]]
    assert plain.followers[2]["solo",] == [("solo", "duet")] and plain.grams[2]["solo", "duet"] > 5
    for h in [("solo",), ("pair",), ("<s>",), *list(plain.followers[2])[:15]]:
        assert sum(plain.p(2, (*h, w)) for w in [*words, "never seen"]) == pytest.approx(1)
    for h in [("duet", "solo"), ("bond", "pair"), ("<s>", "<s>"), *list(plain.followers[3])[:15]]:
        assert sum(plain.p(3, (*h, w)) for w in [*words, "never seen"]) == pytest.approx(1)


def test_saved_model(spark, sf, tmp_path):
    rows = rows_of(spark, sf, 50)
    plain = Plain([t for _, t in rows[10:]], 3)
    katz.save_model(spark, spark.createDataFrame(rows[10:], "doc_id long, text string"), str(tmp_path / "model"))
    grams = spark.read.parquet(str(tmp_path / "model" / "ngrams"))
    assert {r["order"]: r["count"] for r in grams.groupBy("order").count().collect()} == {k: len(plain.grams[k]) for k in (1, 2, 3)}
    assert {f.name for f in (tmp_path / "model" / "weights").iterdir() if f.is_dir()} == {"order=2", "order=3"}
    got = Counter((r["id"], r["n_tokens"], round(r["score"], 5)) for r in katz.score_with(spark, str(tmp_path / "model"), spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == Counter((i, len(plain.tokens(t)), round(plain.score(t), 5)) for i, t in rows)


def test_without_training(spark):
    frame = spark.createDataFrame([(1, "a b"), (2, None)], "doc_id long, text string")
    got = {r["id"]: (r["n_tokens"], r["n_known"], r["train_tokens"], r["base_score"], r["score"]) for r in katz.katz_scores(spark, frame, F.lit(True)).collect()}
    assert got == {1: (3, 0, 0, 0.0, 0.0), 2: (1, 0, 0, 0.0, 0.0)}
    assert katz.katz_scores(spark, frame.limit(0), F.lit(False)).count() == 0
