"""Positions, chunks, deltas and their inverse, as DataFrames.

No list is ever ranked in one task. Ids fall into bins of 2^16; each bin counts its ids, a running sum over a list's
few bins gives every bin its first position, and a window within the bin does the rest. A chunk has at most 2^16 ids,
so every later window is over a chunk.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from laneforge.functions.layout import CHUNK

CHUNK_KEY = ["list_key", "chunk_no"]


def positions(postings: DataFrame, mode: str = "rank", chunk: int = CHUNK) -> DataFrame:
    """Distinct (list_key, x) -> list_key, x, pos, n, chunk_no, i, len.

    mode `rank`: chunks of exactly `chunk` ids, the last may be shorter; pos counts through the list, n is its length.
    mode `range`: a chunk is the ids of one range of `chunk` numbers, so nothing counts through the list: pos and n are
    those of the chunk. i and len are the place in the chunk and its length in both.
    """
    binned = postings.select("list_key", "x", F.expr(f"x div {chunk}").alias("bin"))
    inside = W.partitionBy("list_key", "bin")
    if mode == "range":
        out = binned.withColumn("i", F.row_number().over(inside.orderBy("x")).cast("long") - 1).withColumn("len", F.count("*").over(inside))
        return out.select("list_key", "x", F.col("i").alias("pos"), F.col("len").alias("n"), F.col("bin").alias("chunk_no"), "i", "len")
    counts = binned.groupBy("list_key", "bin").agg(F.count("*").alias("c"))
    by_list = W.partitionBy("list_key")
    counts = counts.select("list_key", "bin", (F.sum("c").over(by_list.orderBy("bin")) - F.col("c")).alias("before"), F.sum("c").over(by_list).alias("n"))
    ranked = binned.withColumn("r", F.row_number().over(inside.orderBy("x")).cast("long") - 1).join(counts, ["list_key", "bin"])
    pos = F.col("before") + F.col("r")
    return (
        ranked.select("list_key", "x", pos.alias("pos"), "n")
        .withColumn("chunk_no", F.expr(f"pos div {chunk}"))
        .withColumn("i", F.expr(f"pos % {chunk}"))
        .withColumn("len", F.least(F.lit(chunk), F.col("n") - F.col("chunk_no") * chunk))
    )


def delta_strided(placed: DataFrame, stride: int = 1, out: str | None = None, value: str = "x") -> DataFrame:
    """Adds the difference to the value `stride` places before in the chunk; the first `stride` values stay."""
    w = W.partitionBy(*CHUNK_KEY).orderBy("i")
    return placed.withColumn(out or f"d{stride}", F.col(value) - F.coalesce(F.lag(value, stride).over(w), F.lit(0)))


def undelta_strided(deltas: DataFrame, stride: int = 1, delta: str | None = None, out: str = "x") -> DataFrame:
    """Running sums, `stride` of them interleaved, within each chunk."""
    w = W.partitionBy(*CHUNK_KEY, F.col("i") % stride).orderBy("i").rowsBetween(W.unboundedPreceding, 0)
    return deltas.withColumn(out, F.sum(delta or f"d{stride}").over(w))


def residual_linear(placed: DataFrame) -> DataFrame:
    """Instead of differences: the distance of each id to the line through its chunk by least squares, zig-zag coded."""
    from laneforge.functions.exprs import zigzag

    fit = placed.groupBy(*CHUNK_KEY).agg(F.coalesce(F.regr_slope("x", "i"), F.lit(0.0)).alias("slope"), F.coalesce(F.regr_intercept("x", "i"), F.min("x").cast("double")).alias("start"))
    return placed.join(fit, CHUNK_KEY).withColumn("residual", zigzag((F.col("x") - F.floor(F.col("start") + F.col("slope") * F.col("i"))).cast("long")))


def from_residual_linear(rows: DataFrame, out: str = "x") -> DataFrame:
    """The ids again, from the residuals and the line (slope, start) that residual_linear() leaves beside them."""
    from laneforge.functions.exprs import unzigzag

    return rows.withColumn(out, (F.floor(F.col("start") + F.col("slope") * F.col("i")) + unzigzag(F.col("residual"))).cast("long"))


def prepared(postings: DataFrame, mode: str = "rank") -> DataFrame:
    """Positions with both kinds of deltas."""
    return delta_strided(delta_strided(positions(postings, mode), 1), 4)


def delta_column(mode: str) -> Column:
    return {"d1": F.col("d1"), "s4": F.col("d4"), "none": F.col("x")}[mode]
