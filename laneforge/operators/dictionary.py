"""Dictionary coding: values of a column to small integers, the most frequent first."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from laneforge.session import written

#: Dictionaries of up to so many values are broadcast to the rows; larger ones join by a shuffle.
BROADCAST_VALUES = 500_000


def dictionary(df: DataFrame, column: str) -> DataFrame:
    """value, cnt, code: codes count from 0 by falling frequency, ties by value. Nulls have no code.

    Values are ranked in two steps, so no task sees them all: ranges of (count, value) are sorted apart, and every range
    begins where the sizes of those before it end.
    """
    spark = df.sparkSession
    counts = df.filter(F.col(column).isNotNull()).groupBy(F.col(column).cast("string").alias("value")).agg(F.count("*").alias("cnt"))
    ranged = counts.repartitionByRange(int(spark.conf.get("spark.sql.shuffle.partitions")), F.desc("cnt"), F.asc("value")).withColumn("part", F.spark_partition_id())
    ranged = written(spark, ranged, "dictionary")  # a row keeps the number of its range
    sizes = ranged.groupBy("part").agg(F.count("*").alias("size"))
    starts = sizes.select("part", (F.sum("size").over(W.partitionBy().orderBy("part")) - F.col("size")).alias("start"))  # one row a range
    place = F.row_number().over(W.partitionBy("part").orderBy(F.desc("cnt"), "value")).cast("long") - 1
    return ranged.withColumn("place", place).join(F.broadcast(starts), "part").select("value", "cnt", (F.col("start") + F.col("place")).alias("code"))


def coded(df: DataFrame, column: str, codes: DataFrame) -> DataFrame:
    """df with `code` in place of nothing: null where the value has no code."""
    side = codes.select(F.col("value").alias(column + "_value"), "code")
    if codes.count() <= BROADCAST_VALUES:
        side = F.broadcast(side)
    return df.join(side, F.col(column).cast("string") == F.col(column + "_value"), "left").drop(column + "_value")
