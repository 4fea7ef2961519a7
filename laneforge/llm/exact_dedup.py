"""Exact deduplication by a tree-merge of sorted digest runs.

Every text becomes a pair of independent digests and a length. A row's run is a hash of its id, so a run is the
same whichever task reads the row. Within a run equal keys fold into one entry (sorted aggregation: Spark sorts
each run by key and merges). In each round groups of `fan_in` runs exchange their entries by key and merge them
multiway; an entry keeps the best id seen and the number of rows. After the last round there is one run, spread over
the cluster by key. The verdicts then go back down the same tree: at every step a key meets at most `fan_in`
entries, so a text that a third of all rows share never gathers in one task.

Entries fold only if SHA-256, BLAKE2b and the length all agree: that second, independent digest verifies the first.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from laneforge.session import written

from .common import freed, kept_rows, row_key

KEY = ["sha", "check", "n_bytes"]
DIGEST_SCHEMA = "id long, sha binary, check binary, n_bytes long"


@freed
def _digests(batches):
    for batch in batches:
        sha, check, size = [], [], []
        for text in batch.column(1):
            raw = (text.as_py() or "").encode("utf-8", "surrogatepass").lower()
            sha.append(hashlib.sha256(raw).digest())
            check.append(hashlib.blake2b(raw, digest_size=16).digest())
            size.append(len(raw))
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(sha, pa.binary()), pa.array(check, pa.binary()), pa.array(size, pa.int64()), *batch.columns[2:]],
            ["id", "sha", "check", "n_bytes", *batch.schema.names[2:]],
        )


def text_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", row_col: str | None = None) -> DataFrame:
    """id, both digests and the length of every whole A-Z-lower-cased text; null counts as empty. With row_col that binary column as row."""
    more = [F.col(row_col).alias("row")] if row_col else []
    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"), *more).mapInArrow(_digests, DIGEST_SCHEMA + (", row binary" if row_col else ""))


def exact_groups(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", fan_in: int = 8, rounds: int = 2, row_col: str | None = None) -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256 (hex), and with row_col that binary column as row.

    keep: whether the smallest or the largest id of equal texts stays. Null and empty texts are equal. A row with
    a null id counts in its group; it stays only where the group has no other id. Rows that repeat an id and text are
    each returned, with the same verdict. Texts of any length are read whole. An empty table gives no rows; other columns are not read.
    """
    if keep not in ("min", "max"):
        raise ValueError("keep is 'min' or 'max'")
    best = F.min if keep == "min" else F.max
    rows = written(spark, text_digests(docs, id_col, text_col, row_col), "digests")
    rows = rows.withColumn("run", F.pmod(F.xxhash64("id"), F.lit(fan_in**rounds)).cast("int"))
    # An aggregate over a struct is a sorted one: each side is a sorted run, each exchange a multiway merge.
    levels = [rows.groupBy("run", *KEY).agg(best(F.struct("id")).alias("best"), F.count("*").alias("n"))]
    if keep == "min":  # a null would sort first
        levels = [rows.groupBy("run", *KEY).agg(F.min(F.struct(F.col("id").isNull().alias("none"), "id")).alias("best"), F.count("*").alias("n"))]
    for _ in range(rounds):
        levels.append(levels[-1].withColumn("run", F.expr(f"run div {fan_in}").cast("int")).groupBy("run", *KEY).agg(best("best").alias("best"), F.sum("n").alias("n")))
    top = levels[-1].filter("n > 1").select(F.col("run").alias("up"), *KEY, F.col("best.id").alias("keep_id"), F.col("n").alias("group_size"))
    for level in reversed(levels[:-1]):
        entries = level.select("run", F.expr(f"run div {fan_in}").cast("int").alias("up"), *KEY)
        top = entries.join(top, ["up", *KEY]).drop("up").withColumnRenamed("run", "up")
    found = rows.join(top.withColumnRenamed("up", "run"), ["run", *KEY], "left")
    keep_id = F.when(F.col("group_size").isNull(), F.col("id")).otherwise(F.col("keep_id"))
    return found.select(
        "id",
        keep_id.alias("keep_id"),
        F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"),
        keep_id.eqNullSafe(F.col("id")).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
        *(["row"] if row_col else []),
    )


def drop_exact_copies(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min") -> DataFrame:
    """One row of each group of equal texts, with all its columns.

    It is a row of the group's smallest (keep="max": largest) id; a row with a null id only where the group has no
    other. Of several rows with that id one stays: the one whose text sorts first by its hash, then any. Rows that share
    an id but not the text are in groups of their own. An empty table gives no rows.
    """
    key = row_key(id_col, F.col(text_col))
    found = exact_groups(spark, docs.withColumn("_row", key), id_col, text_col, keep, row_col="_row")
    best = found.groupBy("text_sha256").agg(F.min(F.when(F.col("kept"), F.col("row"))).alias("best"))
    verdict = found.join(best, "text_sha256").groupBy("row").agg(F.first(F.col("row") != F.col("best")).alias("gone"), F.count("*").alias("n"))
    verdict = written(spark, verdict.filter("gone OR n > 1"), "digest-verdicts")
    return kept_rows(docs, key, verdict.filter("gone").select("row"), verdict.filter("NOT gone").select("row"))


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return exact_groups(spark, docs, keep="max").withColumnRenamed("id", "doc_id")


ORACLE = """
WITH t AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS s FROM documents)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, sha256(s) AS text_sha256
FROM t WINDOW w AS (PARTITION BY s)
"""
