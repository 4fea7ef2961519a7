"""Near copies by word shingles against the similarity of all pairs."""

from collections import Counter, defaultdict

import random

import pytest
from pyspark.sql import functions as F

from laneforge.llm import exact_dedup, shingles, simhash


def plain_near(rows, words=5, similarity=0.8):
    """The least id of each row's group."""
    sets, shared, at = [], Counter(), defaultdict(list)
    for i, (_, text) in enumerate(rows):
        w = (text or "").encode().lower().split()
        sets.append({tuple(w[k : k + words]) for k in range(max(1, len(w) - words + 1))} if w else {None})
        for s in sets[-1]:
            shared.update((j, i) for j in at[s])
            at[s].append(i)
    parent = list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for (i, j), both in shared.items():
        if both >= similarity * (len(sets[i]) + len(sets[j]) - both) - 1e-9:
            parent[find(j)] = find(i)
    least = {}
    for i, (key, _) in enumerate(rows):
        least[find(i)] = min(least.get(find(i), key), key)
    return [least[find(i)] for i in range(len(rows))]


def test_near_copies_of_documents(spark):
    frame = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    rows = [tuple(r) for r in frame.collect()]
    want = {key for (key, _), least in zip(rows, plain_near(rows)) if key == least}
    assert {r["doc_id"] for r in simhash.drop_near_copies(spark, frame).collect()} == want
    assert len(want) < len(rows)


def test_ordinary_near_copies_go(spark):
    """Copies with changed words: 5-word similarity above 0.8 goes (11 by way of 3), below stays; short texts too."""
    base = [f"w{i}" for i in range(200)]
    change = lambda *at: " ".join("new" if i in at else w for i, w in enumerate(base))
    rows = [(1, change()), (2, change(50)), (3, change(20, 60, 120)), (4, change(*range(0, 200, 12))), (11, change(20, 60, 90, 120, 150, 170)), (5, "a b"), (6, "A  b"), (7, "a b c"), (8, None), (9, " \n"), (10, change(3).upper())]
    frame = spark.createDataFrame(rows, "doc_id long, text string").withColumn("row", F.lit("clash"))
    kept = simhash.drop_near_copies(spark, frame)
    assert kept.columns == frame.columns
    want = [key for (key, _), least in zip(rows, plain_near(rows)) if key == least]
    assert sorted(r["doc_id"] for r in kept.collect()) == want == [1, 4, 5, 7, 8]
    assert simhash.drop_near_copies(spark, frame.limit(0)).count() == 0


def test_fingerprints_link_too(spark):
    """Texts two bits apart or fewer are one group though their sets of runs differ, and bring the groups of the sets together."""
    hot = "again " * 400
    rows = [(1, hot + "one two three four five six seven eight nine ten"), (2, hot + "a b c d e f g h i j k l m n"), (3, "all else"), (4, "All  else"), (0, hot + "a b c d e f g h i j k l m n".upper())]
    assert {bin(simhash.fingerprint(rows[0][1]) ^ simhash.fingerprint(rows[k][1])).count("1") <= 2 for k in (1, 4)} == {True}
    assert [key for (key, _), least in zip(rows, plain_near(rows)) if key == least] == [1, 3, 0]
    assert sorted(r["doc_id"] for r in simhash.drop_near_copies(spark, spark.createDataFrame(rows, "doc_id long, text string")).collect()) == [0, 3]


@pytest.mark.parametrize("chunk", [3, 256])
def test_borderline_groups(spark, monkeypatch, chunk):
    """Many variants of one text, about as similar as the limit: those that no other is near enough to stay."""
    monkeypatch.setattr(shingles, "CHUNK", chunk)
    rng, base = random.Random(3), [f"w{i}" for i in range(150)]
    rows = []
    for k in range(70):
        words = list(base)
        for at in rng.sample(range(150), rng.choice([1, 2, 3, 5, 9])):
            words[at] = f"x{k}{at}"
        rows.append((k, " ".join(words)))
    want = [key for (key, _), least in zip(rows, plain_near(rows)) if key == least]
    assert 5 < len(want) < 60
    assert sorted(r["doc_id"] for r in simhash.drop_near_copies(spark, spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()) == want


def test_rows_are_told_apart(spark):
    """Rows that share an id but not the text, null ids, and rows that repeat."""
    a, b = "a text of some words that is here twice", "quite another text with words of its own in it"
    rows = [(1, a), (5, a), (5, b), (None, a), (5, b), (None, None), (None, ""), (2, None)]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(tuple(r) for r in simhash.drop_near_copies(spark, frame).filter("text <> ''").collect()) == [(1, a), (5, b)]
    assert simhash.drop_near_copies(spark, frame).count() == 3
    for keep, first in (("min", 1), ("max", 5)):
        kept = exact_dedup.drop_exact_copies(spark, frame, keep=keep).collect()
        assert sorted((r["doc_id"], r["text"]) for r in kept if r["text"]) == sorted([(first, a), (5, b)])
        assert len(kept) == 3 and [r["doc_id"] for r in kept if not r["text"]] == [2]
