"""SimHash near-duplicates: fingerprints, pigeonring candidate search, Hamming check, components.

The 64 bits are a ring of segments. If two fingerprints differ in at most `limit` bits, some chain of consecutive
segments, wherever it starts, never exceeds its proportional budget: after j of m segments at most j * limit / m
differences, rounded down. Its first segments have a budget below one, so they are equal: these are a bucket key, one for
each start. For two bits and five segments a key has two neighbouring segments, 25 or 26 bits, and there are five
keys where equal segments in any places would need ten. What a bucket yields is pruned by the rest of the chain from the
same start (at most one difference up to the fourth segment) before the full Hamming check.

A bucket of more than `bucket_limit` fingerprints is not paired up. Its members go another exact way: two
fingerprints differ in at most two bits exactly if they share a neighbour at distance at most one, so each member is
linked to the smallest member that shares each of its 65 neighbours. That is linear in the members and finds
the same components; no link is lost.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from laneforge.session import written

from . import shingles
from .common import freed, kept_rows, row_key

#: Segments of the ring, and the most bits that linked fingerprints differ in.
SEGMENTS, LIMIT = 5, 2
PIECE = 1 << 16


def fingerprint(text: str | None, words: int = 3, seed: int = 42) -> int:
    """The 64-bit fingerprint of one text, as an unsigned number."""
    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not parts:
        return 0
    joined = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1)
    if len(parts) <= words:
        spans = [(0, len(joined))]
    else:
        starts = np.concatenate([[0], ends[:-words]]).tolist()
        spans = list(zip(starts, (ends[words - 1 :] - 1).tolist()))
    digest, total = xxhash.xxh64_intdigest, np.zeros(64, np.int64)
    for at in range(0, len(spans), PIECE):
        hashes = np.array([digest(joined[a:b], seed) for a, b in spans[at : at + PIECE]], dtype=">u8")
        total += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * total > len(spans)).tobytes(), "big")


def _fingerprints(words: int, seed: int):
    @freed
    def run(batches):
        for batch in batches:
            found = np.array([fingerprint(x.as_py(), words, seed) for x in batch.column(1)], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.int64())], ["id", "fp"])

    return run


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, seed: int = 42) -> DataFrame:
    """id and fp (the 64 bits as a signed long) of every whole text."""
    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_fingerprints(words, seed), "id long, fp long")


def _segment(fp: Column, i: int) -> Column:
    edges = [64 * k // SEGMENTS for k in range(SEGMENTS + 1)]
    low, high = edges[i % SEGMENTS], edges[i % SEGMENTS + 1]
    return F.shiftrightunsigned(fp, 64 - high).bitwiseAND(F.lit((1 << (high - low)) - 1))


#: The differences that a chain may have gathered after each of its segments.
BUDGETS = [j * LIMIT // SEGMENTS for j in range(1, SEGMENTS + 1)]


def _keys(fp: Column) -> Column:
    """For each start: the start and the segments from there that a chain in budget has equal, in one number."""
    out = []
    for start in range(SEGMENTS):
        key = F.lit(start).cast("long")
        for j in range(BUDGETS.count(0)):
            key = F.shiftleft(key, -(-64 // SEGMENTS)).bitwiseOR(_segment(fp, start + j))
        out.append(key)
    return F.array(*out)


def _chain(x: Column, start: Column) -> Column:
    """Whether the chain of the differences x from `start` keeps its budget at every segment but the last, which is the Hamming check."""
    out = F.lit(False)
    for i in range(SEGMENTS):
        total, ok = F.lit(0), F.lit(True)
        for j in range(SEGMENTS - 1):
            total = total + F.bit_count(_segment(x, i + j))
            if BUDGETS[j]:  # the key holds the others
                ok = ok & (total <= BUDGETS[j])
        out = F.when(start == i, ok).otherwise(out)
    return out


def near_links(spark: SparkSession, fps: DataFrame, bucket_limit: int = 512) -> DataFrame:
    """Edges (u < v) between distinct fingerprints that give the components of `at most two bits apart`."""
    keyed = fps.select("fp", F.posexplode(_keys(F.col("fp"))).alias("start", "key"))
    sizes = keyed.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1")
    crowded = written(spark, keyed.join(sizes, "key"), "simhash-buckets")
    small = crowded.filter(F.col("n") <= bucket_limit)
    left, right = small.select("key", "start", F.col("fp").alias("u")), small.select("key", F.col("fp").alias("v"))
    x = F.col("u").bitwiseXOR(F.col("v"))
    pairs = left.join(right, "key").filter(F.col("u") < F.col("v")).filter(_chain(x, F.col("start"))).filter(F.bit_count(x) <= LIMIT).select("u", "v")
    full = crowded.filter(F.col("n") > bucket_limit).select("fp").distinct()
    around = full.select("fp", F.explode(F.concat(F.array("fp"), F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.col("fp").bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), i))))).alias("at"))
    least = around.groupBy("at").agg(F.min("fp").alias("u"), F.count("*").alias("n")).filter("n > 1").drop("n")
    stars = around.join(least, "at").filter("fp <> u").select("u", F.col("fp").alias("v"))
    return pairs.unionByName(stars).distinct()


def components(spark: SparkSession, edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """node, root for every node of the edges (u, v) that is not its component's least: alternating large-star and small-star steps, each written out.

    Each step joins edges with the least neighbour of each node, so no neighbour list is ever gathered.
    """
    now, before = written(spark, edges.filter("u <> v").select("u", "v"), "cc"), None
    for _ in range(most_rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v")
        down = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        low = down.groupBy("u").agg(F.min("v").alias("m"))
        small = down.join(low, "u").select(F.col("v").alias("w"), "u", "m")
        step = small.select(F.col("w").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v"))).filter("u <> v").distinct()
        seen = Observation()
        now = written(spark, step.observe(seen, F.count("*").alias("n"), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 30))).alias("a"), F.sum(F.pmod(F.xxhash64("v", "u"), F.lit(1 << 30))).alias("b")), "cc")
        if seen.get == before:
            return now.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("root"))
        before = seen.get
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")


def near_groups(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, bucket_limit: int = 512) -> DataFrame:
    """One row per document: id, fp, component_id (the least id that links of at most two bits reach).

    A null or wordless text has fingerprint 0 and links like any other. Equal texts have equal fingerprints; a
    fingerprint takes part once, however many rows share it. Rows with a null id count for links but never name a
    component unless it has no other id. Texts of any length are read whole. An empty table gives no rows; other columns are not read.
    """
    rows = written(spark, fingerprints(docs, id_col, text_col, words), "fingerprints")
    fps = written(spark, rows.groupBy("fp").agg(F.min("id").alias("least_id")), "fps")
    nodes = _rooted(spark, fps, bucket_limit)
    least = nodes.groupBy("root").agg(F.min("least_id").alias("component_id"))
    named = nodes.join(least, "root").select("fp", "component_id")
    return rows.join(named, "fp").select("id", "fp", "component_id")


def _rooted(spark: SparkSession, fps: DataFrame, bucket_limit: int = 512) -> DataFrame:
    """Rows of distinct fingerprints (fp, ...) with the least fingerprint of their component as root."""
    roots = components(spark, near_links(spark, fps.select("fp"), bucket_limit))
    return fps.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = shingles.WORDS, similarity: float = shingles.SIMILARITY) -> DataFrame:
    """One document of each group of near copies stays, the one with the least id; all columns are returned.

    Two kinds of links make the groups. Fingerprints of three-word runs link at two bits or fewer, as in op7. That means
    near identity, so texts that share so much of their sets of runs of `words` words are linked too, found by bands of minima
    and decided by the sets: a 64-bit fingerprint wide enough for these leaves segments too short to search by.
    Wordless texts have the same empty set, so one of them stays, and so does one of the rows that repeat an id and
    its text. Rows that share an id but not the text are told apart; null ids come last. An empty table gives no rows.
    """
    key = row_key(id_col, F.col(text_col))
    texts = docs.select(key.alias("row"), F.col(text_col).cast("string").alias("text"))
    groups = written(spark, shingles.similar_groups(spark, texts, words, similarity), "shingle-groups")
    groups = groups.groupBy("row").agg(F.min("keep").alias("keep"), F.count("*").alias("n"))
    prints = texts.mapInArrow(_fingerprints(3, 42), "id binary, fp long").select(F.col("id").alias("row"), "fp").distinct()
    met = written(spark, prints.join(groups.select("row", "keep"), "row").select("fp", "keep").distinct(), "simhash-groups")
    parts = _rooted(spark, met.select("fp").distinct()).join(met, "fp").select("root", "keep").distinct()
    first = parts.groupBy("root").agg(F.min("keep").alias("first"))
    links = parts.join(first, "root").filter("keep <> first").select(F.col("keep").alias("u"), F.col("first").alias("v")).distinct()
    over = components(spark, links).select(F.col("node").alias("keep"), F.col("root").alias("least"))
    rows = groups.join(over, "keep", "left").select("row", F.coalesce("least", "keep").alias("keep"), "n")
    rows = written(spark, rows.filter("keep <> row OR n > 1"), "near-verdicts")
    return kept_rows(docs, key, rows.filter("keep <> row").select("row"), rows.filter("keep = row").select("row"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return near_groups(spark, docs).select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
