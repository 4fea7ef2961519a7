"""Line deduplication: repeated passages, and content-defined chunks.

A line's hash is rolled over a window of lines, so what a document says before or after a passage changes nothing.

Passages: the rolling hash of two lines is taken at every line, and the boundaries of what goes are where it stops to
repeat. A window that occurs earlier (least document, then place) takes both its lines away; windows overlap, so runs of
repeated lines go from their first line to their last. A line that goes has an earlier equal one: of every line a copy
stays. Windows of blank lines, and those that overlap their own first occurrence, take nothing away.

Chunks: where the rolling hash falls on a fixed residue a chunk ends. A chunk of several lines that occurs again is
removed. Passages that hold no whole chunk stay, so the query and the pipeline use passages.

Either first meet by hash only, a few bytes each. Texts move once, and only those of repeated hashes: they are
grouped by their own bytes, so a removal always rests on equal bytes. Both groupings combine before they shuffle, and a
verdict goes back to the rows of one document, so a chunk that every document has gathers nowhere.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from laneforge.session import written

from .common import freed, row_key

MASK, WIDE = (1 << 64) - 1, (1 << 128) - 1
BASE = 0x9E3779B97F4A7C15F39CC0605CEDC835
#: Lines of the rolling window, one cut in so many places, least and most lines of a chunk.
WINDOW, DIVISOR, LEAST, MOST = 2, 3, 2, 64


def cut_lines(lines: list[bytes], window: int = WINDOW, divisor: int = DIVISOR, least: int = LEAST, most: int = MOST) -> list[tuple[int, int]]:
    """Chunks [first, end) of lines."""
    hashes = [xxhash.xxh64_intdigest(x, 17) for x in lines]
    base = 0x9E3779B97F4A7C15
    out_factor, rolled, out, first = pow(base, window, 1 << 64), 0, [], 0
    for i, h in enumerate(hashes):
        rolled = (rolled * base + h - (hashes[i - window] * out_factor if i >= window else 0)) & MASK
        n = i + 1 - first
        if n >= least and ((rolled >> 20) % divisor == 0 or n >= most):
            out.append((first, i + 1))
            first = i + 1
    if first < len(lines):
        if out and len(lines) - first < least:
            out[-1] = (out[-1][0], len(lines))
        else:
            out.append((first, len(lines)))
    return out


def _chunks(text: str | None) -> list[tuple[int, bytes]]:
    """Lines and bytes of every chunk of a text."""
    if not text:
        return []
    lines = text.encode("utf-8", "surrogatepass").split(b"\n")
    return [(b - a, b"\n".join(lines[a:b])) for a, b in cut_lines(lines)]


def _windows(text: str | None, least: int = LEAST) -> list[tuple[int, bytes]]:
    """Lines and bytes of every run of `least` lines of a text."""
    if not text:
        return []
    lines = text.encode("utf-8", "surrogatepass").split(b"\n")
    return [(least, b"\n".join(lines[i : i + least])) for i in range(len(lines) - least + 1)]


def _chunk_keys(text: str | None) -> list[tuple[int, bytes]]:
    """Place and digest of every chunk of several lines."""
    return [(k, hashlib.blake2b(chunk, digest_size=16).digest()) for k, (n, chunk) in enumerate(_chunks(text)) if n > 1]


def _window_keys(text: str | None, least: int = LEAST) -> list[tuple[int, bytes]]:
    """Place and rolling hash, over the hashes of its lines, of every run of `least` lines that are not all blank."""
    if not text:
        return []
    lines = text.encode("utf-8", "surrogatepass").split(b"\n")
    hashes, blank = [xxhash.xxh3_128_intdigest(x) for x in lines], [not x.strip() for x in lines]
    leaves, rolled, out = pow(BASE, least, 1 << 128), 0, []
    for i, h in enumerate(hashes):
        rolled = (rolled * BASE + h - (hashes[i - least] * leaves if i >= least else 0)) & WIDE
        first = i + 1 - least
        if first >= 0 and not all(blank[first : i + 1]):
            out.append((first, rolled.to_bytes(16, "little")))
    return out


def _list_chunks(keys):
    @freed
    def run(batches):
        for batch in batches:
            ids, place, digest = [], [], []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                for k, key in keys(text.as_py()):
                    ids.append(doc)
                    place.append(k)
                    digest.append(key)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.binary()), pa.array(place, pa.int32()), pa.array(digest, pa.binary())], ["row", "place", "digest"])

    return run


def _repeated_texts(units):
    @freed
    def run(batches):
        for batch in batches:
            ids, place, texts = [], [], []
            for doc, text, places in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist()):
                chunks = units(text.as_py())
                for k in places:
                    ids.append(doc)
                    place.append(k)
                    texts.append(chunks[k][1])
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.binary()), pa.array(place, pa.int32()), pa.array(texts, pa.binary())], ["row", "place", "chunk"])

    return run


def repeated_chunks(spark: SparkSession, docs: DataFrame, units=_chunks, keys=_chunk_keys, apart: int = 1) -> DataFrame:
    """row, gone: the places of the chunks to remove, for rows (row, text) that have any; in one row places of equal ones are `apart` at least."""
    listed = docs.select("row", "text").mapInArrow(_list_chunks(keys), "row binary, place int, digest binary")
    listed = written(spark, listed, "line-chunks")
    often = listed.groupBy("digest").agg(F.count("*").alias("n")).filter("n > 1").select("digest")
    asked = listed.join(often, "digest").groupBy("row").agg(F.array_sort(F.collect_set("place")).alias("places"))
    texts = docs.select("row", "text").join(asked, "row").select("row", "text", "places").mapInArrow(_repeated_texts(units), "row binary, place int, chunk binary")
    texts = written(spark, texts.withColumn("size", F.length("chunk")), "line-repeats")
    first = texts.groupBy("chunk").agg(F.min(F.struct("row", "place")).alias("first"), F.count("*").alias("n")).filter("n > 1")
    later = texts.join(first, "chunk").filter((F.struct("row", "place") > F.col("first")) & ((F.col("row") != F.col("first.row")) | (F.col("place") >= F.col("first.place") + apart)))
    return later.groupBy("row").agg(F.array_sort(F.collect_set("place")).alias("gone"))


def _without_chunks(text: str, gone: set[int]) -> tuple[str, int, int]:
    chunks = _chunks(text)
    return b"\n".join(c for k, (_, c) in enumerate(chunks) if k not in gone).decode("utf-8", "surrogatepass") if gone else text, len(chunks), len(gone)


def _without_passages(text: str | None, gone: set[int]) -> tuple[str | None, int, int]:
    """The text left, and how many runs of lines stay or go, and go."""
    if not text or not gone:
        return text, int(bool(text)), 0
    lines = text.encode("utf-8", "surrogatepass").split(b"\n")
    away = np.zeros(len(lines) + 2, bool)
    for k in gone:
        away[k + 1 : k + 1 + LEAST] = True
    removed = int((away[1:] & ~away[:-1]).sum())
    stays = int((~away[1:-1] & np.concatenate([[True], away[1:-2]])).sum())
    return b"\n".join(x for x, a in zip(lines, away[1:-1]) if not a).decode("utf-8", "surrogatepass"), removed + stays, removed


def _without(leave):
    @freed
    def run(batches):
        for batch in batches:
            texts = [leave(text.as_py(), set(gone or ())) for text, gone in zip(batch.column("text"), batch.column("gone").to_pylist())]
            left, chunks_n, gone_n = zip(*texts) if texts else ((), (), ())
            at = batch.schema.get_field_index("text")
            batch = batch.set_column(at, "text", pa.array(left, pa.string()))
            batch = batch.drop_columns(["gone"])
            for name, values in (("n_chunks", chunks_n), ("n_removed", gone_n)):
                batch = batch.append_column(name, pa.array(values, pa.int32()))
            yield batch

    return run


#: What is compared, by which keys it meets, how far equal ones are apart in one text, and what is left of a text.
CHUNKS, PASSAGES = (_chunks, _chunk_keys, 1, _without_chunks), (_windows, _window_keys, LEAST, _without_passages)


def _deduplicated(spark: SparkSession, docs: DataFrame, id_col: str, text_col: str, way=CHUNKS) -> DataFrame:
    """text without what is repeated, rest (a struct of all columns), n_chunks, n_removed."""
    units, keys, apart, leave = way
    rows = docs.select(row_key(id_col, text_col).alias("row"), F.col(text_col).cast("string").alias("text"), F.struct(*[F.col(c) for c in docs.columns if c != text_col], F.lit(0).alias("_none")).alias("rest"))
    removed = repeated_chunks(spark, rows, units, keys, apart)
    schema = T.StructType([*rows.schema.fields, T.StructField("n_chunks", T.IntegerType()), T.StructField("n_removed", T.IntegerType())])
    return rows.join(removed, "row", "left").mapInArrow(_without(leave), schema)


def _columns(docs: DataFrame, text_col: str, but: tuple[str, ...] = ()) -> list:
    return [F.col("text").alias(c) if c == text_col else F.col("rest")[c].alias(c) for c in docs.columns if c not in but]


def drop_repeated_chunks(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All columns of docs, the text without its repeated chunks, and n_chunks, n_removed.

    Null texts stay null; empty texts and texts of one line stay as they are. Rows with a null id come last in the order
    of first occurrences. Rows that repeat an id and a text are one document. Columns of docs named n_chunks or
    n_removed give way; other names never clash. An empty table gives no rows.
    """
    return _deduplicated(spark, docs, id_col, text_col).select(*_columns(docs, text_col, ("n_chunks", "n_removed")), "n_chunks", "n_removed")


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """As drop_repeated_chunks, but every passage of two or more lines that occurs earlier goes, whatever stands around it.

    n_removed counts the runs of lines that go, n_chunks those that go and those that stay between them.
    """
    return _deduplicated(spark, docs, id_col, text_col, PASSAGES).select(*_columns(docs, text_col, ("n_chunks", "n_removed")), "n_chunks", "n_removed")


def line_stage(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The documents without repeated passages, with their own columns; those of which nothing is left go.

    Null, empty and one-line texts stay as they are; texts of any length are read whole. Rows that repeat an id and a text
    are one document, and keep or lose the same lines. An empty table gives no rows; names of other columns never clash.
    """
    return _deduplicated(spark, docs, "doc_id", "text", PASSAGES).filter("n_removed = 0 OR length(text) > 0").select(*_columns(docs, "text"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = drop_repeated_passages(spark, docs)
    return out.select("doc_id", "n_chunks", "n_removed", F.length(F.coalesce("text", F.lit(""))).cast("long").alias("n_chars_left"), F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("text_sha256"))


ORACLE = r"""
WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS k FROM documents WHERE text <> ''),
w AS (SELECT doc_id, k, line || chr(10) || after AS c FROM (SELECT *, lead(line) OVER (PARTITION BY doc_id ORDER BY k) AS after FROM l) WHERE after IS NOT NULL AND regexp_matches(line || after, '[^ \t\n\r\x0b\x0c]')),
f AS (SELECT doc_id, k, first_value(doc_id) OVER o AS first_doc, first_value(k) OVER o AS first_k FROM w WINDOW o AS (PARTITION BY c ORDER BY doc_id, k)),
g AS (SELECT doc_id, k FROM f WHERE doc_id <> first_doc OR k >= first_k + 2),
gg AS (SELECT doc_id, k FROM g UNION SELECT doc_id, k + 1 FROM g),
b AS (SELECT l.doc_id, l.k, line, gg.k IS NOT NULL AS gone FROM l LEFT JOIN gg ON gg.doc_id = l.doc_id AND gg.k = l.k),
r AS (SELECT *, coalesce(lag(gone) OVER (PARTITION BY doc_id ORDER BY k), NOT gone) <> gone AS fresh FROM b),
t AS (SELECT doc_id, count(*) FILTER (gone AND fresh) AS removed, count(*) FILTER (fresh) AS runs, string_agg(line, chr(10) ORDER BY k) FILTER (NOT gone) AS rest FROM r GROUP BY doc_id),
o AS (SELECT d.doc_id, coalesce(removed, 0) AS removed, coalesce(runs, 0) AS runs, coalesce(CASE WHEN removed > 0 THEN rest ELSE text END, '') AS rest FROM documents d LEFT JOIN t USING (doc_id))
SELECT doc_id, CAST(runs AS INTEGER) AS n_chunks, CAST(removed AS INTEGER) AS n_removed, length(rest) AS n_chars_left, sha256(rest) AS text_sha256 FROM o
"""
