"""Blocks as DataFrames: widths, histograms, choice of width, exceptions, packed words and back.

Input rows: list_key, chunk_no, i, len and the value v. Only whole blocks take part; the rest of a chunk is a tail.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from laneforge.functions.exprs import bit_length, high_bits, low_bits, word_index, word_shift
from laneforge.functions.layout import BLOCK, LOCATION_BITS

BLOCK_KEY = ["list_key", "chunk_no", "block_no"]


def in_blocks(rows: DataFrame, block: int = BLOCK) -> DataFrame:
    """Rows of whole blocks, with block_no and the place j in the block."""
    return rows.filter(F.col("i") < F.expr(f"len div {block}") * block).withColumn("block_no", F.expr(f"i div {block}")).withColumn("j", F.expr(f"i % {block}"))


def widths(rows: DataFrame, block: int = BLOCK) -> DataFrame:
    """m of each block from the OR of its values: one logarithm a block."""
    return in_blocks(rows, block).groupBy(*BLOCK_KEY).agg(F.bit_or("v").alias("o")).select(*BLOCK_KEY, bit_length(F.col("o")).alias("m"))


def widths_by_max(rows: DataFrame, block: int = BLOCK) -> DataFrame:
    """The same from the largest of all the logarithms."""
    return in_blocks(rows, block).groupBy(*BLOCK_KEY).agg(F.max(bit_length(F.col("v"))).alias("m"))


def histogram(rows: DataFrame, block: int = BLOCK) -> DataFrame:
    """How many values of each width a block has."""
    return in_blocks(rows, block).groupBy(*BLOCK_KEY, bit_length(F.col("v")).alias("w")).agg(F.count("*").alias("cnt"))


def width_choice(rows: DataFrame, block: int = BLOCK) -> DataFrame:
    """b, m, c and cost of each block: the width of least cost, the larger on ties.

    One pass counts the 33 widths of a block side by side; every candidate is then priced from the counts, not
    from the data.
    """
    counted = in_blocks(rows, block).withColumn("w", bit_length(F.col("v"))).groupBy(*BLOCK_KEY).agg(F.max("w").alias("m"), F.array(*[F.count_if(F.col("w") == k) for k in range(33)]).alias("cnt"))
    above = lambda b: F.aggregate(F.slice("cnt", b + 2, F.lit(33)), F.lit(0).cast("long"), lambda s, x: s + x)
    price = lambda b: F.struct((F.lit(block) * b + above(b) * (LOCATION_BITS + F.col("m") - b)).alias("cost"), (-b).alias("less"), above(b).alias("c"))
    best = F.array_min(F.transform(F.sequence(F.lit(0), F.col("m")), price))
    return counted.withColumn("best", best).select(*BLOCK_KEY, (-F.col("best.less")).cast("int").alias("b"), "m", F.col("best.c").alias("c"), F.col("best.cost").cast("long").alias("cost"))


def exceptions(rows: DataFrame, block: int = BLOCK) -> DataFrame:
    """Values beyond their block's b: place, high part, and the bucket (m - b) that it goes to."""
    chosen = width_choice(rows, block)
    joined = in_blocks(rows, block).join(chosen.filter("c > 0"), BLOCK_KEY)
    return joined.filter(bit_length(F.col("v")) > F.col("b")).select(*BLOCK_KEY, F.col("j").alias("loc"), high_bits(F.col("v"), F.col("b")).alias("high"), (F.col("m") - F.col("b")).alias("bucket"))


def packed_words(rows: DataFrame, block: int, lanes: int = 1) -> DataFrame:
    """Words of each block at its width m: scalar layout, or vertical with that many lanes."""
    with_width = in_blocks(rows, block).join(widths(rows, block).filter("m > 0"), BLOCK_KEY)
    word, shift = word_index(F.col("j"), F.col("m"), lanes), word_shift(F.col("j"), F.col("m"), lanes)
    low = F.call_function("shiftleft", F.col("v"), F.col("shift")).bitwiseAND(F.lit((1 << 32) - 1))
    both = with_width.select(*BLOCK_KEY, "v", "m", word.alias("word_no"), shift.alias("shift")).withColumn(
        "part",
        F.explode(
            F.filter(
                F.array(
                    F.struct(F.col("word_no").alias("n"), low.alias("bits")),
                    F.when(F.col("shift") + F.col("m") > 32, F.struct((F.col("word_no") + lanes).alias("n"), F.call_function("shiftrightunsigned", F.col("v"), 32 - F.col("shift")).alias("bits"))),
                ),
                lambda p: p.isNotNull(),
            )
        ),
    )
    return both.groupBy(*BLOCK_KEY, F.col("part.n").alias("word_no")).agg(F.bit_or("part.bits").alias("word"))


def unpacked_words(words: DataFrame, width: DataFrame, block: int, lanes: int = 1) -> DataFrame:
    """Values of every block from its words and width: list_key, chunk_no, block_no, j, v. Blocks of width 0 hold zeros."""
    held = words.groupBy(*BLOCK_KEY).agg(F.map_from_entries(F.collect_list(F.struct("word_no", "word"))).alias("words"))  # at most `block` words
    rows = width.join(held, BLOCK_KEY, "left").withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(block - 1))))
    word, shift = word_index(F.col("j"), F.col("m"), lanes), word_shift(F.col("j"), F.col("m"), lanes)
    rows = rows.withColumn("wi", word).withColumn("s", shift)
    get = lambda at: F.coalesce(F.try_element_at("words", at), F.lit(0).cast("long"))
    first = F.call_function("shiftrightunsigned", get(F.col("wi")), F.col("s"))
    rest = F.when(F.col("s") + F.col("m") > 32, F.call_function("shiftleft", get(F.col("wi") + lanes), 32 - F.col("s"))).otherwise(F.lit(0).cast("long"))
    return rows.select(*BLOCK_KEY, F.col("j").cast("long").alias("j"), F.when(F.col("m") == 0, F.lit(0).cast("long")).otherwise(low_bits(first.bitwiseOR(rest), F.col("m"))).alias("v"))


def tail(rows: DataFrame, block: int) -> DataFrame:
    return rows.filter(F.col("i") >= F.expr(f"len div {block}") * block)


def block_count(block: int) -> Column:
    return F.expr(f"len div {block}")
