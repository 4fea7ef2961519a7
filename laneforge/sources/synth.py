"""Synthetic sorted sets: uniform and clustered."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F


#: Digest bins that the uniform sets are cut by; values that a task of the clustered sets makes at most.
BINS, PART = 4096, 1 << 18


def gen_uniform(spark: SparkSession, n_arrays: int, n: int, hi: int = 1 << 29, seed: int = 1) -> DataFrame:
    """(list_key, x): n distinct uniform integers in [0, hi) for each of n_arrays lists, made by the JVM.

    Numbers are drawn in excess, made distinct, and the n of smallest digest stay, so the set is uniform. Digests fall
    into bins: a list's bins stay or go whole, but for the one that holds the n-th, and only that is ranked.
    """
    extra = n + 10 * int(n**0.5) + int(1.3 * n * n / hi) + 16
    drawn = spark.range(n_arrays * extra).select((F.col("id") % n_arrays).cast("string").alias("list_key"), F.pmod(F.xxhash64(F.lit(seed), "id"), F.lit(hi)).alias("x")).distinct()
    drawn = drawn.withColumn("digest", F.xxhash64(F.lit(seed + 1), "x")).withColumn("bin", F.pmod("digest", F.lit(BINS)))
    bins = drawn.groupBy("list_key", "bin").agg(F.count("*").alias("c"))
    bins = bins.withColumn("before", F.sum("c").over(W.partitionBy("list_key").orderBy("bin")) - F.col("c")).filter(F.col("before") < n)
    rows = drawn.join(bins, ["list_key", "bin"])
    whole = rows.filter(F.col("before") + F.col("c") <= n).select("list_key", "x")
    cut = rows.filter(F.col("before") + F.col("c") > n)
    rank = F.row_number().over(W.partitionBy("list_key").orderBy("digest", "x"))
    return whole.unionByName(cut.withColumn("r", rank).filter(F.col("before") + F.col("r") <= n).select("list_key", "x"))


def clustered(rng: np.random.Generator, n: int, lo: int, hi: int) -> np.ndarray:
    """n sorted distinct integers in [lo, hi): a random cut with half of the values on either side, again and again.

    With probability 1/2 one side, chosen at random, is filled uniformly; a part of at most ten values always is.
    """
    out, work = [], [(n, lo, hi)]
    while work:
        n, lo, hi = work.pop()
        if n == 0:
            continue
        if n <= 10 or hi - lo == n:
            out.append(lo + _distinct(rng, n, hi - lo))
            continue
        left = n // 2
        cut = int(rng.integers(lo + left, hi - (n - left) + 1))
        parts = [(left, lo, cut), (n - left, cut, hi)]
        if rng.random() < 0.5:
            k, a, b = parts.pop(int(rng.integers(2)))
            out.append(a + _distinct(rng, k, b - a))
        work += parts
    return np.sort(np.concatenate(out)) if out else np.zeros(0, np.int64)


def _distinct(rng: np.random.Generator, n: int, span: int) -> np.ndarray:
    if 3 * n >= span:
        return rng.permutation(span)[:n].astype(np.int64)
    got = np.unique(rng.integers(0, span, n + n // 4 + 4))
    while len(got) < n:
        got = np.unique(np.concatenate([got, rng.integers(0, span, n)]))
    return rng.permutation(got)[:n].astype(np.int64)


def clustered_parts(rng: np.random.Generator, n: int, lo: int, hi: int, part: int = PART) -> list[tuple[int, int, int, bool]]:
    """The top of the recursion of clustered(): parts (n, lo, hi, whether filled uniformly) of at most `part` values, unless dense.

    A uniform fill is cut in the middle of its range, with as many values on either side as chance puts there.
    """
    out, work = [], [(n, lo, hi, False)]
    while work:
        n, lo, hi, flat = work.pop()
        if n <= part or hi - lo == n and flat:
            out.append((n, lo, hi, flat))
        elif flat or hi - lo == n:
            middle = (lo + hi) // 2
            left = int(rng.hypergeometric(middle - lo, hi - middle, n))
            work += [(left, lo, middle, True), (n - left, middle, hi, True)]
        else:
            left = n // 2
            cut = int(rng.integers(lo + left, hi - (n - left) + 1))
            parts = [(left, lo, cut, False), (n - left, cut, hi, False)]
            if rng.random() < 0.5:
                k, a, b, _ = parts.pop(int(rng.integers(2)))
                work.append((k, a, b, True))
            work += parts
    return [p for p in out if p[0]]


def gen_clustered(spark: SparkSession, n_arrays: int, n: int, hi: int = 1 << 29, seed: int = 1) -> DataFrame:
    """(list_key, x) of n_arrays clustered sets, seeded by the list. The top of each recursion is drawn first; its parts are then made by tasks of their own."""

    def plan(batches):
        for batch in batches:
            for k in batch.column(0).to_pylist():
                parts = clustered_parts(np.random.default_rng([seed, k]), n, 0, hi)
                yield pa.RecordBatch.from_arrays([pa.array([k] * len(parts), pa.int64()), pa.array(np.arange(len(parts))), *[pa.array(c) for c in zip(*parts)]], ["k", "part", "n", "lo", "hi", "flat"])

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                rng = np.random.default_rng([seed, r["k"], 1 + r["part"]])
                if r["flat"]:
                    x = r["lo"] + (_distinct(rng, r["n"], r["hi"] - r["lo"]) if r["n"] < r["hi"] - r["lo"] else np.arange(r["n"]))
                else:
                    x = clustered(rng, r["n"], r["lo"], r["hi"])
                yield pa.RecordBatch.from_arrays([pa.array([str(r["k"])] * len(x)), pa.array(x)], ["list_key", "x"])

    parts = spark.range(n_arrays).mapInArrow(plan, "k long, part long, n long, lo long, hi long, flat boolean")
    return parts.repartition("k", "part").mapInArrow(run, "list_key string, x long")
