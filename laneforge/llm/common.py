"""Pieces that the operators share."""

from __future__ import annotations

import ctypes

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def lower_ascii(col: Column) -> Column:
    """A-Z lower-cased and nothing else; for short strings (long texts use bytes.lower(), which does the same)."""
    return F.translate(col, UPPER, UPPER.lower())


def crc_part(id_col: str, parts: int) -> Column:
    """crc32 of the id as text, modulo parts; a null id counts as the empty string."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % parts


def row_key(id_col: str, text_col: str):
    """What tells a document's row: its id (nulls last), and its text for rows that repeat an id. Order as bytes is order of ids."""
    key = F.concat(F.when(F.col(id_col).isNull(), F.lit(b"\x01")).otherwise(F.lit(b"\x00")), F.unhex(F.lpad(F.hex(F.coalesce(F.col(id_col).cast("long"), F.lit(0)).bitwiseXOR(F.lit(-(1 << 63)))), 16, "0")), F.unhex(F.lpad(F.hex(F.xxhash64(F.coalesce(text_col, F.lit("")))), 16, "0")))
    return key


def kept_rows(docs: DataFrame, key: Column, gone: DataFrame, repeated: DataFrame) -> DataFrame:
    """The rows of docs whose key is not in `gone`, and of those whose key is in `repeated` one for each key.

    Both are small tables with a column `row` (and no key is in both); a key that many rows share combines before it is shuffled.
    """
    rows = docs.select(key.alias("row"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("rest"))
    if repeated.isEmpty():
        return rows.join(gone, "row", "left_anti").select("rest.*")
    once = rows.join(gone.unionByName(repeated), "row", "left_anti").select("rest")
    first = rows.join(repeated, "row", "left_semi").groupBy("row").agg(F.first("rest").alias("rest")).select("rest")
    return once.unionByName(first).select("rest.*")


def trim() -> None:
    """Gives memory that this worker no longer uses back to the machine."""
    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library keeps its own house
        pass


def freed(run):
    """A function over Arrow batches that gives memory back when its task ends: the worker stays for other tasks, idle or not."""

    def task(batches):
        try:
            yield from run(batches)
        finally:
            trim()

    return task
