"""Set operations and look-ups on lists in compressed form.

An encoded row keeps its chunk's least and greatest id, so a look-up first decides on those two numbers which payloads
to decode at all. The filter goes below the decoding step, as Spark moves none through it, and reaches the Parquet
footers of a written table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from laneforge.plans.pipeline import decode_chunks, to_postings


def prune(encoded: DataFrame, lo: int | None = None, hi: int | None = None) -> DataFrame:
    """Chunks that may hold ids in [lo, hi]."""
    if lo is not None:
        encoded = encoded.filter(F.col("x_max") >= lo)
    return encoded if hi is None else encoded.filter(F.col("x_min") <= hi)


def range_lookup(encoded: DataFrame, lo: int, hi: int) -> DataFrame:
    """(list_key, x) with x in [lo, hi]; only overlapping chunks are decoded."""
    return to_postings(decode_chunks(prune(encoded, lo, hi))).filter(F.col("x").between(lo, hi))


def list_stats(encoded: DataFrame) -> DataFrame:
    """n, least and greatest id of every list, from the chunks' columns alone."""
    return encoded.groupBy("list_key").agg(F.sum("n").cast("long").alias("n"), F.min("x_min").alias("x_min"), F.max("x_max").alias("x_max"))


def value_at(encoded: DataFrame, asked: DataFrame, chunk: int) -> DataFrame:
    """The ids at places (list_key, pos): one chunk is decoded for each, and the rest of the list is not."""
    want = asked.select("list_key", "pos", F.expr(f"pos div {chunk}").alias("chunk_no"))
    rows = encoded.join(want.select("list_key", "chunk_no").distinct(), ["list_key", "chunk_no"], "left_semi")
    return decode_chunks(rows).join(want, ["list_key", "chunk_no"]).select("list_key", "pos", F.element_at("values", (F.col("pos") % chunk + 1).cast("int")).alias("x"))


def _meeting(own: DataFrame, other: DataFrame) -> DataFrame:
    """The chunks of `own` that overlap a chunk of `other` in ids, for chunks of one pair of lists or of many (column `pair`).

    Both sides go to buckets of ids as wide as a chunk is on average, so the join is on equal keys. The chunks of a
    list are disjoint, so together they touch at most as many buckets as there are, and one more each.
    """
    least, most, n = own.select("x_min", "x_max").unionByName(other.select("x_min", "x_max")).agg(F.min("x_min"), F.max("x_max"), F.count("*")).first()
    width = max(1, ((most or 0) - (least or 0) + 1) // max(n, 1))
    spread = lambda d: d.withColumn("bucket", F.explode(F.sequence(F.expr(f"x_min div {width}"), F.expr(f"x_max div {width}"))))
    left = spread(own.select("list_key", "chunk_no", "x_min", "x_max"))
    right = spread(other.select("x_min", "x_max")).select("bucket", F.col("x_min").alias("lo"), F.col("x_max").alias("hi"))
    hit = left.join(right, "bucket").filter((F.col("lo") <= F.col("x_max")) & (F.col("x_min") <= F.col("hi"))).select("list_key", "chunk_no").distinct()
    return own.join(hit, ["list_key", "chunk_no"], "left_semi")


def intersect(encoded: DataFrame, a: str, b: str, strategy: str = "skip") -> DataFrame:
    """Ids of both lists. `merge` decodes both; `skip` decodes the chunks of b that overlap a chunk of a, and the reverse."""
    left, right = encoded.filter(F.col("list_key") == a), encoded.filter(F.col("list_key") == b)
    if strategy == "skip":
        left, right = _meeting(left, right), _meeting(right, left)
    elif strategy != "merge":
        raise ValueError("strategy is 'skip' or 'merge'")
    return to_postings(decode_chunks(left)).select("x").join(to_postings(decode_chunks(right)).select("x"), "x", "left_semi")


def overlapping_chunks(encoded: DataFrame, a: str, b: str) -> DataFrame:
    """decoded, total: chunks of both lists that `skip` decodes, and all of them."""
    left, right = encoded.filter(F.col("list_key") == a), encoded.filter(F.col("list_key") == b)
    hit = _meeting(left, right).unionByName(_meeting(right, left))
    return hit.agg(F.count("*").alias("decoded")).crossJoin(encoded.filter(F.col("list_key").isin(a, b)).agg(F.count("*").alias("total")))


def conjunctive(encoded: DataFrame, terms: DataFrame, width: int = 1 << 16) -> DataFrame:
    """(session, x): ids that the lists of all matched terms of a session share. terms: session, term, distinct.

    A session starts from its shortest list, known from the chunks' columns, and only its ids are looked up in the
    other lists. Of these only chunks are decoded that may hold such an id: chunks and ids meet by buckets of `width`
    ids on equal keys. What is emitted is the shortest list times the terms, not all lists of all terms.
    """
    lists = list_stats(encoded).select("list_key", "n")
    met = terms.select("session", F.col("term").alias("list_key")).join(lists, "list_key")
    start = met.groupBy("session").agg(F.min(F.struct("n", "list_key")).alias("s"), F.count("*").alias("need")).select("session", "need", F.col("s.list_key").alias("first"))
    firsts = encoded.join(start.select(F.col("first").alias("list_key")).distinct(), "list_key", "left_semi")
    ids = to_postings(decode_chunks(firsts)).withColumnRenamed("list_key", "first").join(start, "first").select("session", "need", "first", "x")
    asked = ids.filter("need > 1").join(met.select("session", "list_key"), "session").filter("list_key <> first").select("session", "need", "list_key", "x")
    wanted = asked.select("list_key", F.expr(f"x div {width}").alias("bucket")).distinct()
    chunks = encoded.withColumn("bucket", F.explode(F.sequence(F.expr(f"x_min div {width}"), F.expr(f"x_max div {width}"))))
    needed = chunks.select("list_key", "chunk_no", "bucket").join(wanted, ["list_key", "bucket"], "left_semi").select("list_key", "chunk_no").distinct()
    others = to_postings(decode_chunks(encoded.join(needed, ["list_key", "chunk_no"], "left_semi")))
    hits = asked.join(others, ["list_key", "x"], "left_semi").groupBy("session", "x").agg((F.count("*") + 1).alias("have"), F.first("need").alias("need"))
    return ids.filter("need = 1").select("session", "x").unionByName(hits.filter("have = need").select("session", "x"))


def union_lists(encoded: DataFrame, keys: list[str]) -> DataFrame:
    return to_postings(decode_chunks(encoded.filter(F.col("list_key").isin(keys)))).select("x").distinct()


def difference(encoded: DataFrame, a: str, b: str) -> DataFrame:
    """Ids of a that b lacks; chunks of b that overlap no chunk of a are not decoded."""
    left, right = encoded.filter(F.col("list_key") == a), encoded.filter(F.col("list_key") == b)
    return to_postings(decode_chunks(left)).select("x").join(to_postings(decode_chunks(_meeting(right, left))).select("x"), "x", "left_anti")


def value_at_cost(encoded: DataFrame, asked: DataFrame, chunk: int) -> DataFrame:
    """list_key, pos, decoded, total: the integers that value_at() decodes for a place, and those of its list."""
    want = asked.select("list_key", "pos", F.expr(f"pos div {chunk}").alias("chunk_no"))
    own = want.join(encoded.select("list_key", "chunk_no", F.col("n").cast("long").alias("decoded")), ["list_key", "chunk_no"])
    return own.join(list_stats(encoded).select("list_key", F.col("n").alias("total")), "list_key").select("list_key", "pos", "decoded", "total")


def floor_lookup(encoded: DataFrame, probes: DataFrame) -> DataFrame:
    """As-of: for each probe (list_key, at) the greatest id <= at of its list, or null. One chunk is decoded for each probe.

    The chunk is the last whose least id is not beyond the probe; it is found on the chunks' columns.
    """
    heads = encoded.select("list_key", "chunk_no", "x_min")
    near = probes.join(heads, "list_key").filter("x_min <= at").groupBy("list_key", "at").agg(F.max_by("chunk_no", "x_min").alias("chunk_no"))
    rows = decode_chunks(encoded.join(near.select("list_key", "chunk_no").distinct(), ["list_key", "chunk_no"], "left_semi"))
    found = rows.join(near, ["list_key", "chunk_no"]).select("list_key", "at", F.array_max(F.filter("values", lambda v: v <= F.col("at"))).alias("x"))
    return probes.join(found, ["list_key", "at"], "left").select("list_key", "at", "x")
