"""Posting lists (list_key, x) from the given tables: words to document ids, column values to row keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from laneforge.functions.layout import LIMIT
from laneforge.functions.words import BEYOND
from laneforge.session import load

#: Whatever is neither a letter nor a number divides words.
WORD_BREAK = r"[^\p{L}\p{N}]+"
TAG = "<[^>]*>"


def words_of(text: Column) -> Column:
    return F.filter(F.array_distinct(F.split(F.lower(text), WORD_BREAK)), lambda w: w != "")


def postings_from_text(df: DataFrame, id_col: str, text: Column, unique: bool = True) -> DataFrame:
    """One row per word and document. Words are made distinct within a document before the shuffle; without `unique`, rows repeat where ids do."""
    rows = df.select(F.explode(words_of(text)).alias("list_key"), F.col(id_col).cast("long").alias("x")).filter("x IS NOT NULL")
    return rows.distinct() if unique else rows


def words_by_id(spark: SparkSession, sf_dir: str, source: str) -> DataFrame:
    """words, text, x for every text of `documents` or `pages`, and its id; ids may repeat.

    Texts of Latin-1 characters go as they are, with words null, to functions.words; others as their distinct words.
    """
    table, key, text = {"documents": ("documents", "doc_id", F.col("text")), "pages": ("pages", "page_id", F.regexp_replace("html", TAG, " "))}[source]
    return split_or_whole(load(spark, sf_dir, table).select(text.alias("text"), F.col(key).cast("long").alias("x")))


def split_or_whole(rows: DataFrame) -> DataFrame:
    """words, text, x from rows (text, x): either the distinct words or the text, the other null."""
    beyond = F.col("text").rlike(BEYOND)
    return rows.select(F.when(beyond, words_of(F.col("text"))).alias("words"), F.when(~beyond, F.col("text")).alias("text"), "x")


def postings_from_html(df: DataFrame, id_col: str, html: str, unique: bool = True) -> DataFrame:
    return postings_from_text(df, id_col, F.regexp_replace(html, TAG, " "), unique)


def postings_from_column(df: DataFrame, key: Column, value: Column) -> DataFrame:
    """One row per value of a column and row key that has it."""
    return df.select(key.cast("string").alias("list_key"), value.cast("long").alias("x")).filter("list_key IS NOT NULL AND x IS NOT NULL").distinct()


def _seconds() -> Column:
    return F.expr("timestampdiff(SECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)")


_COLUMNS = {
    "lineitem_supp": ("lineitem", "l_suppkey", "l_orderkey"),
    "lineitem_part": ("lineitem", "l_partkey", "l_orderkey"),
    "lineitem_line": ("lineitem", "l_linenumber", "l_orderkey"),
    "events_type": ("events", "event_type", "event_id"),
    "orders_cust": ("orders", "o_custkey", "o_orderkey"),
}
NAMES = ["documents", "pages", *_COLUMNS, "events_user"]


def postings(spark: SparkSession, sf_dir: str, source: str, unique: bool = True) -> DataFrame:
    """The distinct postings of a source by name. Without `unique` those of texts may repeat, for a reader that counts them once."""
    if source == "documents":
        return postings_from_text(load(spark, sf_dir, "documents"), "doc_id", F.col("text"), unique)
    if source == "pages":
        return postings_from_html(load(spark, sf_dir, "pages"), "page_id", "html", unique)
    if source == "events_user":
        return postings_from_column(load(spark, sf_dir, "events"), F.col("user_id"), _seconds())
    table, key, value = _COLUMNS[source]
    return postings_from_column(load(spark, sf_dir, table), F.col(key), F.col(value))


def rejected(df: DataFrame) -> DataFrame:
    """How many postings the methods can't take: null, negative, or beyond 32 bits."""
    x = F.col("x")
    return df.agg(F.count_if(x.isNull()).alias("nulls"), F.count_if(x < 0).alias("negative"), F.count_if(x >= LIMIT).alias("too_large"))


def oracle(source: str) -> str:
    """The same postings in SQL."""
    if source in ("documents", "pages"):
        text = "text" if source == "documents" else "regexp_replace(html, '<[^>]*>', ' ', 'g')"
        key = "doc_id" if source == "documents" else "page_id"
        return f"SELECT DISTINCT list_key, x FROM (SELECT unnest(string_split_regex(lower({text}), '[^\\p{{L}}\\p{{N}}]+')) AS list_key, {key} AS x FROM {source}) WHERE list_key <> ''"
    if source == "events_daily":
        return "SELECT DISTINCT event_type || '/' || strftime(ts, '%Y-%m-%d') AS list_key, event_id AS x FROM events"
    if source == "events_user":
        return "SELECT DISTINCT CAST(user_id AS VARCHAR) AS list_key, date_diff('second', TIMESTAMP '2024-01-01', ts) AS x FROM events"
    table, key, value = _COLUMNS[source]
    return f"SELECT DISTINCT CAST({key} AS VARCHAR) AS list_key, CAST({value} AS BIGINT) AS x FROM {table}"
