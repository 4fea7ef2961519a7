"""Approximate nearest neighbours by largest inner product: an inverted multi-index.

The two halves of a vector are quantised separately with k centroids each; a pair of centroids is a cell. A query
walks the cells in order of its summed distance to their two centroids, taken from a heap, until the cells hold
enough vectors, and reranks these exactly. Distance here is the negative inner product, which sums over the halves too.
How many vectors are enough is measured: a bounded number of probes is searched exactly over all rows, and the share of
the vectors is the least that would have found the asked part of their neighbours.

Cells and queries meet in blocks: small cells share one, a cell of many vectors is cut into several, and the queries of
a block are dealt into teams, so no task holds more than one block and one team. Equal vectors of a block count once, with their smallest ids, as a query
can't return more of them. Each block returns a query's best only.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from laneforge.session import written

#: Rows that the centroids are fitted on at most; all rows are indexed.
SAMPLE = 20_000
#: Rows of that sample which the share is measured on at most.
PROBES = 128
#: Centroids of a half at most; so there are at most this squared cells, whatever the table holds.
CENTROIDS = 512
#: Vectors and queries that a task compares at most, and queries at a time.
VECTORS, QUERIES, AT_ONCE = 4096, 8192, 512
BROADCAST_BLOCKS = 100_000


def usable(col: Column, dim: int | None = None) -> Column:
    """Whether a vector takes part: not null, not zero, all components finite, and of dim components where given."""
    good = F.forall(col, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(col, lambda x: x != 0)
    return F.coalesce(col.isNotNull() & good & (F.lit(True) if dim is None else F.size(col) == dim), F.lit(False))


def fit(sample: np.ndarray, k: int, rounds: int = 12, seed: int = 7) -> np.ndarray:
    """k centroids of the rows, by Lloyd's algorithm; fewer where there are fewer different rows."""
    rows = np.unique(sample, axis=0)
    rng = np.random.default_rng(seed)
    centres = rows[rng.permutation(len(rows))[:k]].copy()
    for _ in range(rounds):
        own = nearest(rows, centres)
        total = np.zeros_like(centres)
        np.add.at(total, own, rows)
        n = np.bincount(own, minlength=len(centres))
        centres = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], centres)
    return centres


def nearest(rows: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return ((centres**2).sum(axis=1) - 2 * rows @ centres.T).argmin(axis=1)


def traverse(q: np.ndarray, first: np.ndarray, second: np.ndarray, sizes: dict[int, int], enough: int) -> list[int]:
    """Non-empty cells in order of summed distance until they hold `enough` vectors."""
    half, k = first.shape[1], len(second)
    a, b = -(first @ q[:half]), -(second @ q[half:])
    oa, ob = np.argsort(a, kind="stable"), np.argsort(b, kind="stable")
    a, b = a[oa], b[ob]
    heap, seen, cells, held = [(a[0] + b[0], 0, 0)], {(0, 0)}, [], 0
    while heap and held < enough:
        _, i, j = heapq.heappop(heap)
        cell = int(oa[i]) * k + int(ob[j])
        if n := sizes.get(cell, 0):
            cells.append(cell)
            held += n
        for x, y in ((i + 1, j), (i, j + 1)):
            if x < len(a) and y < len(b) and (x, y) not in seen:
                seen.add((x, y))
                heapq.heappush(heap, (a[x] + b[y], x, y))
    return cells


def needed_share(probes: np.ndarray, found: list[list[int]], first: np.ndarray, second: np.ndarray, sizes: dict[int, int], recall: float) -> float:
    """The least share of the vectors in the cells that the probes walk first that holds the part `recall` of their neighbours.

    found: the cells of each probe's true neighbours. All cells of a probe are put in order here; there is a bounded
    number of probes and of cells.
    """
    half, cells = first.shape[1], np.array(sorted(sizes))
    held, need = np.array([sizes[c] for c in cells.tolist()], float), []
    for q, own in zip(probes, found):
        order = np.argsort(-((first @ q[:half])[cells // len(second)] + (second @ q[half:])[cells % len(second)]), kind="stable")
        upto = np.empty(len(cells))
        upto[order] = np.cumsum(held[order])
        need += (upto[np.searchsorted(cells, own)] / held.sum()).tolist()
    need.sort()
    return need[min(len(need) - 1, int(np.ceil(recall * len(need))) - 1)] if need else 1.0


def _near_probes(probes: np.ndarray, own: np.ndarray, k: int):
    """Of a partition's rows (id, v, cell) the k nearest of each probe: rows (probe, id, cell, score)."""

    def run(frames):
        best = pd.DataFrame({"probe": [], "id": [], "cell": [], "score": []})
        for f in frames:
            if not len(f):
                continue
            score, ids = probes @ np.stack(f["v"].to_numpy()).astype(float).T, f["id"].to_numpy()
            score[own[:, None] == ids[None, :]] = -np.inf
            m = min(k, score.shape[1])
            at = np.argpartition(-score, m - 1, axis=1)[:, :m]
            rows = pd.DataFrame({"probe": np.repeat(np.arange(len(probes)), m), "id": ids[at].reshape(-1), "cell": f["cell"].to_numpy()[at].reshape(-1), "score": np.take_along_axis(score, at, axis=1).reshape(-1)})
            best = pd.concat([best, rows[np.isfinite(rows["score"])]]).sort_values("score", ascending=False, kind="stable").groupby("probe").head(k)
        yield best.astype({"probe": "int32", "id": "int64", "cell": "int32", "score": "float64"})

    return run


def best_of_block(vectors: np.ndarray, ids: np.ndarray, cells: np.ndarray, queries: np.ndarray, own: np.ndarray, walked: list, k: int):
    """For each query its k best among the block's vectors in cells that it walked, itself excluded: (query place, id, exact score)."""
    order = np.argsort(ids, kind="stable")
    vectors, ids, cells = vectors[order], ids[order], cells[order]
    _, first, place = np.unique(vectors.view(np.dtype((np.void, vectors.dtype.itemsize * vectors.shape[1]))).reshape(-1), return_index=True, return_inverse=True)
    kinds = vectors[first]
    names, cell_of = np.unique(cells[first], return_inverse=True)
    turn = np.argsort(place, kind="stable")
    start = np.searchsorted(place[turn], np.arange(len(kinds)))
    stop = np.append(start[1:], len(ids))
    open_to = np.zeros((len(queries), len(names) + 1), bool)
    for i, wanted in enumerate(walked):
        at = np.searchsorted(names, wanted)
        open_to[i, np.where(np.append(names, -1)[at] == wanted, at, len(names))] = True
    rough = np.where(open_to[:, cell_of], queries @ kinds.T, -np.inf)
    m = min(k + 1, len(kinds))
    least = np.partition(rough, -m, axis=1)[:, -m]
    slack = 1e-9 * (1 + np.abs(np.where(np.isfinite(rough), rough, 0)).max(axis=1))
    at, kind = np.nonzero((rough >= (least - slack)[:, None]) & np.isfinite(rough))
    exact = (queries[at] * kinds[kind]).sum(axis=1)
    out, edge = [], np.searchsorted(at, np.arange(len(queries) + 1)).tolist()
    for i in range(len(queries)):
        got = []
        for j in range(edge[i], edge[i + 1]):
            c = kind[j]
            got += [(-exact[j], v) for v in ids[turn[start[c] : min(stop[c], start[c] + k + 1)]].tolist() if v != own[i]]
        out += [(i, v, -s) for s, v in sorted(got)[:k]]
    return out


def lay_out(sizes: dict[int, int], most: int = VECTORS) -> dict[int, list[int]]:
    """Blocks of each cell: neighbouring small cells share a block, a large cell has several of its own."""
    blocks, now, held = {}, 0, 0
    for cell in sorted(sizes):
        n = sizes[cell]
        if held and held + n > most:
            now, held = now + 1, 0
        parts = 1 + (n - 1) // most
        blocks[cell] = list(range(now, now + parts))
        now, held = (now + parts, 0) if parts > 1 else (now, held + n)
    return blocks


def search(spark: SparkSession, base: DataFrame, queries: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", k: int = 20, cells_per_half: int | None = None, recall: float = 0.94, share: float | None = None) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found of each query among the rows of base other than its own id.

    A query walks cells until they hold `share` of all vectors; where that is None, the share that finds the part
    `recall` of the neighbours of up to PROBES rows of the table. Vectors that are null, zero, of another length than
    most, or hold null or non-finite components take no part, and neither do null ids. Equal scores go to the smaller
    id; rows that repeat an id and vector count once. No rows where base or queries have none; other columns are not read.
    """
    schema = "query_id long, rank int, vec_id long, score double"
    rows = base.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("v")).filter(usable(F.col("v")) & F.col("id").isNotNull())
    lengths = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").limit(1).collect()
    if not lengths:
        return spark.createDataFrame([], schema)
    dim, total = lengths[0]["d"], lengths[0]["count"]
    rows = rows.filter(F.size("v") == dim)
    taken = rows.orderBy(F.xxhash64("id"), "id").limit(SAMPLE).collect()
    sample = np.array([r["v"] for r in taken], float)
    half = max(1, dim // 2)
    size = min(cells_per_half or int(np.clip(np.sqrt(total / 12), 4, CENTROIDS)), CENTROIDS)
    first, second = fit(sample[:, :half], size), fit(sample[:, half:] if dim > 1 else np.zeros((len(sample), 1)), size)
    wide = len(second)

    @F.pandas_udf("int")
    def cell_of(v: pd.Series) -> pd.Series:
        x = np.array(v.tolist(), float)
        y = x[:, half:] if dim > 1 else np.zeros((len(x), 1))
        return pd.Series((nearest(x[:, :half], first) * wide + nearest(y, second)).astype(np.int32))

    index = written(spark, rows.withColumn("cell", cell_of("v")), "imi-index")
    sizes = {r["cell"]: r["count"] for r in index.groupBy("cell").count().collect()}  # at most cells_per_half squared rows
    blocks = lay_out(sizes)
    if share is None:
        probes, own = sample[:PROBES], np.array([r["id"] for r in taken[:PROBES]])
        ranked = index.select("id", "v", "cell").mapInPandas(_near_probes(probes, own, k), "probe int, id long, cell int, score double")
        ranked = ranked.withColumn("r", F.row_number().over(W.partitionBy("probe").orderBy(F.desc("score"), "id"))).filter(F.col("r") <= k)
        met = ranked.groupBy("probe").agg(F.collect_list("cell").alias("cells")).collect()  # k cells of each probe
        wide_probes = probes if dim > 1 else np.concatenate([probes, np.zeros((len(probes), 1))], axis=1)
        share = needed_share(wide_probes[[r["probe"] for r in met]], [r["cells"] for r in met], first, second, sizes, recall)
    enough = max(k + 1, int(np.ceil(share * total)))
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))

    @F.pandas_udf("array<struct<b: int, cells: array<int>>>")
    def walk(v: pd.Series) -> pd.Series:
        out = []
        for q in v:
            met: dict[int, list[int]] = {}
            for cell in traverse(np.asarray(q if dim > 1 else [*q, 0.0], float), first, second, sizes, enough):
                for b in blocks[cell]:
                    met.setdefault(b, []).append(cell)
            out.append([{"b": b, "cells": c} for b, c in met.items()])
        return pd.Series(out)

    asked = queries.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("v")).filter(usable(F.col("v"), dim) & F.col("id").isNotNull()).distinct().repartition(tasks, "id")
    asked = written(spark, asked.withColumn("met", walk("v")), "imi-queries")
    visited = asked.select("id", "v", F.explode("met").alias("met")).select("id", "v", "met.b", "met.cells")
    visits = {r["b"]: r["count"] for r in visited.groupBy("b").count().collect()}  # a row for each block at most
    # One row a cell, and there are CENTROIDS squared of them at most.
    parts = spark.createDataFrame([(c, b[0], len(b)) for c, b in blocks.items()], "cell int, at int, n int")
    teams = spark.createDataFrame([(b, 1 + n // QUERIES) for b, n in visits.items()], "b int, qb int")
    teams = F.broadcast(teams) if len(visits) <= BROADCAST_BLOCKS else teams
    deal = lambda n: F.pmod(F.xxhash64("id"), F.col(n)).cast("int")
    left = index.join(F.broadcast(parts), "cell").withColumn("b", F.col("at") + deal("n")).join(teams, "b")
    left = left.withColumn("c", F.explode(F.sequence(F.lit(0), F.col("qb") - 1))).select("b", "c", "id", "v", "cell")
    right = visited.join(teams, "b").withColumn("c", deal("qb")).select("b", "c", "id", "v", "cells")

    def pair(vectors: pd.DataFrame, wanted: pd.DataFrame) -> pd.DataFrame:
        if not len(vectors) or not len(wanted):
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []})
        stack = lambda f: np.ascontiguousarray(np.stack(f["v"].to_numpy()), float)
        own, have, asks, walked = wanted["id"].to_numpy(), stack(vectors), stack(wanted), list(wanted["cells"])
        found = []
        for at in range(0, len(own), AT_ONCE):
            s = slice(at, at + AT_ONCE)
            found += [(int(own[at + i]), v, x) for i, v, x in best_of_block(have, vectors["id"].to_numpy(), vectors["cell"].to_numpy(), asks[s], own[s], walked[s], k)]
        return pd.DataFrame(found, columns=["query_id", "vec_id", "score"])

    found = left.groupBy("b", "c").cogroup(right.groupBy("b", "c")).applyInPandas(pair, "query_id long, vec_id long, score double")
    best = W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.distinct().withColumn("rank", F.row_number().over(best).cast("int")).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op8_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    table = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return search(spark, table, table.filter("vec_id % 20 = 0"))
