"""Exact encoded sizes of every list, by formula: bytes without encoding a single value.

Each function takes rows (list_key, chunk_no, i, len, v) and gives list_key, n, n_bytes. Sizes equal the lengths of the
byte plane's payloads.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from laneforge.functions.exprs import bit_length, byte_len, vbyte_len
from laneforge.functions.layout import BLOCK, META

from .blocks import tail, width_choice, widths

CHUNK_KEY = ["list_key", "chunk_no"]


def _chunks(rows: DataFrame) -> DataFrame:
    return rows.groupBy(*CHUNK_KEY).agg(F.count("*").alias("n"))


def _up(value: Column, to: int) -> Column:
    return F.ceil(value / to).cast("long")


def _pad(value: Column, to: int) -> Column:
    return _up(value, to) * to


def _per_list(chunks: DataFrame, size: Column) -> DataFrame:
    return chunks.withColumn("bytes", size).groupBy("list_key").agg(F.sum("n").alias("n"), F.sum("bytes").cast("long").alias("n_bytes"))


def _with_tail(rows: DataFrame, block: int) -> DataFrame:
    """Chunks with nb, the number of their whole blocks, and tail, the bytes of the rest."""
    rest = tail(rows, block).groupBy(*CHUNK_KEY).agg(F.sum(vbyte_len(F.col("v"))).alias("tail"))
    return _chunks(rows).join(rest, CHUNK_KEY, "left").withColumns({"tail": F.coalesce("tail", F.lit(0)), "nb": F.expr(f"n div {block}")})


def binary_packing(rows: DataFrame, block: int) -> DataFrame:
    meta = META.get(block, 16)
    body = widths(rows, block).groupBy(*CHUNK_KEY).agg(F.sum(4 * _up(F.col("m") * block, 32)).alias("body"))
    chunks = _with_tail(rows, block).join(body, CHUNK_KEY, "left")
    return _per_list(chunks, _up(F.col("nb"), meta) * meta + F.coalesce("body", F.lit(0)) + F.col("tail"))


def _patched_pages(rows: DataFrame) -> DataFrame:
    """Of chunks with whole blocks: low, notes, and the high parts of the scalar and of the vertical layout, in bytes.

    All exceptions of a block have m - b bits, so the blocks' choices are enough and no value is looked at again.
    """
    chosen = width_choice(rows.filter(F.col("len") >= BLOCK))
    notes = 2 + F.when(F.col("m") > F.col("b"), 1 + F.col("c")).otherwise(0)
    sets = chosen.groupBy(*CHUNK_KEY, (F.col("m") - F.col("b")).alias("bucket")).agg(F.sum(16 * F.col("b")).alias("low"), F.sum(notes).alias("notes"), F.sum("c").alias("k"))
    high = lambda align, unit: F.sum(F.when(F.col("bucket") > 0, align + _up(F.col("k"), unit) * F.col("bucket") * (unit // 8)).otherwise(0)).alias(f"high{unit}")
    return sets.groupBy(*CHUNK_KEY).agg(F.sum("low").alias("low"), F.sum("notes").alias("notes"), high(4, 32), high(16, 128))


def _page_bytes(vertical: bool) -> Column:
    align, unit = (16, 128) if vertical else (4, 32)
    return F.coalesce(F.lit(align) + F.col("low") + _pad(4 + _pad(F.col("notes"), 4) + 4, align) + F.col(f"high{unit}"), F.lit(0))


def page_patched(rows: DataFrame, vertical: bool) -> DataFrame:
    chunks = _with_tail(rows, BLOCK).join(_patched_pages(rows), CHUNK_KEY, "left")
    return _per_list(chunks, _page_bytes(vertical) + F.col("tail"))


def _byte_groups(lengths: Column) -> Column:
    """Groups of eight bytes that values of these lengths fill in turn, none astride."""
    start = F.struct(F.lit(1).cast("long").alias("groups"), F.lit(0).alias("used"))
    fits = lambda a, x: a["used"] + x <= 8
    step = lambda a, x: F.struct((a["groups"] + F.when(fits(a, x), 0).otherwise(1)).cast("long").alias("groups"), F.when(fits(a, x), a["used"] + x).otherwise(x).cast("int").alias("used"))
    return F.aggregate(lengths, start, step, lambda a: a["groups"])


def byte_groups(rows: DataFrame) -> DataFrame:
    """A chunk's lengths are gathered in order, one small number each."""
    placed = F.array_sort(F.collect_list((F.col("i") * 8 + byte_len(F.col("v"))).cast("int")))
    chunks = rows.groupBy(*CHUNK_KEY).agg(F.count("*").alias("n"), placed.alias("placed"))
    return _per_list(chunks, 9 * _byte_groups(F.transform("placed", lambda x: x % 8)))


#: The codes that report() prices.
REPORT = ["vpack128", "pack32", "vpatch", "bucketpatch", "vbyte", "groupvarint", "bytegroup8", "raw32"]


def report(rows: DataFrame) -> DataFrame:
    """list_key, codec, n, n_bytes for all codes of REPORT from one layout of the rows.

    Rows move once, to their chunk. Everything then is counted there: sums over values, ORs of blocks of 32 that make
    those of 128, and one choice of width a block for both patched codes.
    """
    laid = rows.repartition(*CHUNK_KEY)
    whole = lambda block: F.col("i") >= F.expr(f"len div {block}") * block
    vb, by = vbyte_len(F.col("v")), byte_len(F.col("v"))
    chunks = laid.groupBy(*CHUNK_KEY).agg(
        F.count("*").alias("n"), F.sum(vb).alias("vbyte"), F.sum(by).alias("bytes"), F.array_sort(F.collect_list((F.col("i") * 8 + by).cast("int"))).alias("placed"),
        *[F.sum(F.when(whole(b), vb).otherwise(0)).alias(f"tail{b}") for b in (32, 128)],
    )
    small = laid.filter(~whole(32)).groupBy(*CHUNK_KEY, F.expr("i div 32").alias("b")).agg(F.bit_or("v").alias("o"))
    large = small.groupBy(*CHUNK_KEY, F.expr("b div 4").alias("b")).agg(F.sum(4 * bit_length(F.col("o"))).alias("body32"), F.bit_or("o").alias("o"), F.count("*").alias("parts"))
    body = large.groupBy(*CHUNK_KEY).agg(F.sum("body32").alias("body32"), F.sum(F.when(F.col("parts") == 4, 16 * bit_length(F.col("o"))).otherwise(0)).alias("body128"))
    priced = chunks.join(body, CHUNK_KEY, "left").join(_patched_pages(laid), CHUNK_KEY, "left")
    packed = lambda b, meta: _up(F.expr(f"n div {b}"), meta) * meta + F.coalesce(f"body{b}", F.lit(0)) + F.col(f"tail{b}")
    size = {
        "vpack128": packed(128, 16), "pack32": packed(32, 4), "vpatch": _page_bytes(True) + F.col("tail128"), "bucketpatch": _page_bytes(False) + F.col("tail128"), "vbyte": F.col("vbyte"),
        "groupvarint": F.col("bytes") + _up(F.col("n"), 4), "bytegroup8": 9 * _byte_groups(F.transform("placed", lambda x: x % 8)), "raw32": 4 * F.col("n"),
    }
    lists = priced.groupBy("list_key").agg(F.sum("n").alias("n"), *[F.sum(size[c]).cast("long").alias(c) for c in REPORT])
    return lists.select("list_key", "n", F.explode(F.array(*[F.struct(F.lit(c).alias("codec"), F.col(c).alias("n_bytes")) for c in REPORT])).alias("s")).select("list_key", "n", "s.n_bytes", "s.codec")


def summed(rows: DataFrame, per_value: Column, bits: bool = False, fixed: Column | None = None) -> DataFrame:
    """Codes whose size is a sum over values: bytes, or bits that round up to bytes for each chunk."""
    chunks = rows.groupBy(*CHUNK_KEY).agg(F.count("*").alias("n"), F.sum(per_value).alias("total"))
    size = _up(F.col("total"), 8) if bits else F.col("total")
    return _per_list(chunks, size + fixed if fixed is not None else size)


def tiny_groups(rows: DataFrame) -> DataFrame:
    groups = rows.groupBy(*CHUNK_KEY, F.expr("i div 4").alias("g")).agg(F.count("*").alias("n"), F.bit_or("v").alias("o"))
    chunks = groups.groupBy(*CHUNK_KEY).agg(F.sum("n").alias("n"), F.count("*").alias("groups"), F.sum(4 * bit_length(F.col("o"))).alias("bits"))
    return _per_list(chunks, F.col("groups") + _up(F.col("bits"), 8))


def rice(rows: DataFrame) -> DataFrame:
    means = rows.groupBy(*CHUNK_KEY).agg(F.expr("sum(v) div count(*)").alias("mean")).withColumn("k", F.greatest(F.lit(0), bit_length(F.col("mean")) - 1))
    one = F.call_function("shiftrightunsigned", F.col("v"), F.col("k")) + 1 + F.col("k")
    return summed(rows.join(means, CHUNK_KEY), one, bits=True, fixed=F.lit(1))


def _gamma(v: Column) -> Column:
    return 2 * bit_length(v + 1) - 1


def _delta(v: Column) -> Column:
    n = bit_length(v + 1)
    return 2 * bit_length(n.cast("long")) - 1 + n - 1


FORMULAS = {
    "vpack128": lambda r: binary_packing(r, 128),
    "horizpack": lambda r: binary_packing(r, 128),
    "vpack256": lambda r: binary_packing(r, 256),
    "vpack512": lambda r: binary_packing(r, 512),
    "pack32": lambda r: binary_packing(r, 32),
    "pack16": lambda r: binary_packing(r, 16),
    "pack8": lambda r: binary_packing(r, 8),
    "bucketpatch": lambda r: page_patched(r, False),
    "vpatch": lambda r: page_patched(r, True),
    "vbyte": lambda r: summed(r, vbyte_len(F.col("v"))),
    "groupvarint": lambda r: summed(r, byte_len(F.col("v")), fixed=_up(F.col("n"), 4)),
    "bytegroup8": byte_groups,
    "tinygroup4": tiny_groups,
    "elias_gamma": lambda r: summed(r, _gamma(F.col("v")), bits=True),
    "elias_delta": lambda r: summed(r, _delta(F.col("v")), bits=True),
    "golomb_rice": rice,
    "raw32": lambda r: summed(r, F.lit(4)),
}


def encoded_size(rows: DataFrame, codec: str) -> DataFrame:
    """list_key, n, n_bytes under a codec that has a formula."""
    return FORMULAS[codec](rows)
