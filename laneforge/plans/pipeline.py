"""The byte plane: chunks of a list to payloads and back, in Arrow batches.

A batch of chunk rows is one flat buffer of integers with offsets. Deltas are taken over the whole buffer at once, and so
are binary packing and the patched codes, where blocks of one width are packed together whichever chunk they are of.
The other codes take the chunks one by one.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from laneforge.functions import kernels as K
from laneforge.functions.codecs import ALL, BinaryPacking, unpack_many
from laneforge.functions.layout import CHUNK, LIMIT
from laneforge.functions.words import words as words_of_texts
from laneforge.session import written

STRIDES = {"d1": 1, "s4": 4, "none": 0}
ENCODED = "list_key string, chunk_no long, codec string, delta_mode string, n int, x_min long, x_max long, n_bytes long, payload binary"
CHUNKS = "list_key string, chunk_no long, n int, x_min long, x_max long, values array<long>"


def build_chunks(postings: DataFrame, mode: str = "rank", chunk: int = CHUNK) -> DataFrame:
    """Chunk rows (CHUNKS) of sorted ids; a list's ids that repeat count once. A group is one bin or chunk, so it holds at most `chunk` ids.

    Ids meet in bins of ranges of `chunk` numbers, as arrays. For chunks of ranks (see positions()) a running sum over the
    sizes of a list's bins gives each its first position, and the arrays, written in between, are cut where chunks begin:
    no row for an id is shuffled a second time.
    """
    bins = postings.groupBy("list_key", F.expr(f"x div {chunk}").alias("bin")).agg(F.array_sort(F.collect_set("x")).alias("values"))
    if mode == "range":
        rows = bins.withColumnRenamed("bin", "chunk_no")
    else:
        bins = written(postings.sparkSession, bins, "bins")
        size = F.size("values").cast("long")
        starts = bins.select("list_key", "bin", (F.sum(size).over(W.partitionBy("list_key").orderBy("bin")) - size).alias("before"))
        placed = bins.join(starts, ["list_key", "bin"]).withColumn("chunk_no", F.explode(F.sequence(F.expr(f"before div {chunk}"), F.expr(f"(before + size(values) - 1) div {chunk}"))))
        skipped = F.greatest(F.col("chunk_no") * chunk - F.col("before"), F.lit(0))
        part = F.slice("values", (skipped + 1).cast("int"), (F.least((F.col("chunk_no") + 1) * chunk - F.col("before"), size) - skipped).cast("int"))
        rows = placed.select("list_key", "chunk_no", part.alias("part")).groupBy("list_key", "chunk_no").agg(F.array_sort(F.flatten(F.collect_list("part"))).alias("values"))
    return rows.select("list_key", "chunk_no", F.size("values").alias("n"), F.col("values")[0].alias("x_min"), F.element_at("values", -1).alias("x_max"), "values")


def build_text_chunks(rows: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """Chunks of ranks, as build_chunks() makes them, from rows (words array<string>, x): x is in the list of every word of its row.
    Rows may have a `text` besides, whose words count too.

    A batch of rows turns into lists at once, so no row for a word and an id is made or aggregated. Lists of which all parts
    together have at most `chunk` ids are one chunk, whose parts meet in one shuffle; the few longer ones take bins.
    """
    spark = rows.sparkSession
    rows = rows.select("x", *[c for c in ("words", "text") if c in rows.columns]).filter("x IS NOT NULL")
    parts = written(spark, rows.mapInArrow(_inverted, "list_key string, n int, first boolean, values array<long>"), "parts")
    # A longer list has a part of more than its share of `chunk` ids, so that only lists of such parts are added up, where there are fewer parts of a list than that.
    share = chunk // max(1, parts.filter("first").count())
    parts, sums = parts.drop("first"), parts.select("list_key", "n")
    if share:
        sums = sums.join(written(spark, sums.filter(F.col("n") > share).select("list_key").distinct(), "large"), "list_key", "left_semi")
    # Written, so that its size is known: at most one list for every `chunk` ids.
    longer = written(spark, sums.groupBy("list_key").agg(F.sum("n").alias("n")).filter(F.col("n") > chunk).select("list_key"), "longer")
    short = parts.join(longer, "list_key", "left_anti").select("list_key", "values").repartition("list_key").sortWithinPartitions("list_key").mapInArrow(_merged, CHUNKS)
    return short.unionByName(build_chunks(parts.join(longer, "list_key", "left_semi").select("list_key", F.explode("values").alias("x")), chunk=chunk))


def _inverted(batches):
    """Every word of a batch with the ids of its rows, each once but for rows of one id that are apart; `first` is set in one row of a batch."""
    for batch in batches:
        words = batch.column("words")
        found, each = [words.flatten()], [pc.fill_null(pc.list_value_length(words), 0).to_numpy(zero_copy_only=False)]
        if "text" in batch.schema.names:
            own, count = words_of_texts(batch.column("text"))
            found, each = found + own, [*each, count]
        ids = batch.column("x").to_numpy(zero_copy_only=False)
        coded = pa.chunked_array(found, pa.string()).dictionary_encode()  # one dictionary for all pieces
        if not len(coded):
            continue
        keys = coded.chunk(0).dictionary
        codes = np.concatenate([c.indices.to_numpy(zero_copy_only=False) for c in coded.chunks])
        order = _by_code(codes, len(keys))
        codes, values = codes[order], np.concatenate([np.repeat(ids, n) for n in each])[order]
        fresh = np.concatenate([[True], (codes[1:] != codes[:-1]) | (values[1:] != values[:-1])])
        n, values = np.bincount(codes[fresh], minlength=len(keys)), values[fresh]
        offsets = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
        yield pa.RecordBatch.from_arrays([keys, pa.array(n.astype(np.int32)), pa.array(np.arange(len(keys)) == 0), pa.ListArray.from_arrays(pa.array(offsets), pa.array(values))], ["list_key", "n", "first", "values"])


def _by_code(codes: np.ndarray, many: int) -> np.ndarray:
    """The stable order of numbers below `many`: sorted by their low 16 bits, and by the rest."""
    order = np.argsort(codes.astype(np.uint16), kind="stable")
    if many > 1 << 16:
        order = order[np.argsort((codes >> 16).astype(np.uint16)[order], kind="stable")]
    return order


def _merged(batches):
    """Parts of lists in the order of their keys -> lists of one chunk. The last list of a batch waits for the next one."""
    held = None
    for batch in batches:
        if not batch.num_rows:
            continue
        held = pa.Table.from_batches([batch]) if held is None else pa.concat_tables([held, pa.Table.from_batches([batch])])
        keys = held.column("list_key").combine_chunks()
        firsts = np.flatnonzero(pc.not_equal(keys[1:], keys[:-1]).to_numpy(zero_copy_only=False)) + 1
        if len(firsts):
            yield _one_chunk_lists(held.slice(0, firsts[-1]), np.concatenate([[0], firsts[:-1]]))
            held = held.slice(firsts[-1])
    if held is not None:
        yield _one_chunk_lists(held, np.zeros(1, np.int64))


def _one_chunk_lists(parts: pa.Table, firsts: np.ndarray) -> pa.RecordBatch:
    """One row for the parts from each of `firsts` to the next: their ids, sorted, those that repeat once."""
    x, offsets = flat(parts.column("values"))
    of_part = np.zeros(parts.num_rows, np.int64)
    of_part[firsts[1:]] = 1
    of = np.repeat(np.cumsum(of_part), np.diff(offsets))
    if ((of[1:] == of[:-1]) & (x[1:] < x[:-1])).any():
        x = x[np.lexsort((x, of))]
    fresh = np.concatenate([[True], (of[1:] != of[:-1]) | (x[1:] != x[:-1])])
    x, n = x[fresh], np.bincount(of[fresh])
    ends = np.cumsum(n)
    keys = parts.column("list_key").combine_chunks().take(pa.array(firsts))
    values = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]).astype(np.int32)), pa.array(x))
    return pa.RecordBatch.from_arrays([keys, pa.array(np.zeros(len(n), np.int64)), pa.array(n.astype(np.int32)), pa.array(x[ends - n]), pa.array(x[ends - 1]), values], ["list_key", "chunk_no", "n", "x_min", "x_max", "values"])


def flat(column) -> tuple[np.ndarray, np.ndarray]:
    """Values and offsets of a list column."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    offsets = column.offsets.to_numpy().astype(np.int64)
    values = column.values.to_numpy(zero_copy_only=False).astype(np.int64)[offsets[0] : offsets[-1]] if len(column) else np.zeros(0, np.int64)
    return values, offsets - offsets[0] if len(offsets) else np.zeros(1, np.int64)


def batch_deltas(x: np.ndarray, offsets: np.ndarray, stride: int, check: bool = True) -> np.ndarray:
    """Differences within each chunk of a flat buffer; the first `stride` values of a chunk stay."""
    if len(x) and (x.min() < 0 or x.max() >= LIMIT):
        bad = int(((x < 0) | (x >= LIMIT)).sum())
        raise ValueError(f"{bad} values are not unsigned 32-bit integers")
    if not stride:
        return x.astype(np.uint64)
    d = x.copy()
    d[stride:] -= x[:-stride] if len(x) > stride else x[:0]
    for k in range(stride):
        at = offsets[:-1] + k
        at = at[at < offsets[1:]]
        d[at] = x[at]
    if check and len(d) and d.min() < 0:
        raise ValueError(f"{int((d < 0).sum())} values are smaller than those before them: differential coding takes sorted lists")
    return d.astype(np.uint64)


def batch_undeltas(d: np.ndarray, offsets: np.ndarray, stride: int) -> np.ndarray:
    """Prefix sums within each chunk: one running sum per lane over the buffer, less what came before the chunk."""
    return K.undelta_many(d, offsets, stride) if stride else d.astype(np.int64)


def encode_batch(d: np.ndarray, offsets: np.ndarray, codec: str) -> list[bytes]:
    """Payloads of the chunks of a flat buffer of deltas."""
    return ALL[codec].encode_many(d, offsets)


def decode_fused(payloads: list[bytes], n: np.ndarray, codec: str, stride: int) -> np.ndarray:
    """Values instead of deltas, in one pass: blocks are summed up as they are unpacked, then get what came before them.

    For binary packing with differences; other codes decode in two passes.
    """
    c = ALL[codec]
    if isinstance(c, BinaryPacking) and stride and c.block % stride == 0:
        return unpack_many(c, payloads, np.asarray(n), stride).astype(np.int64)
    return batch_undeltas(decode_batch(payloads, n, codec), np.concatenate([[0], np.cumsum(n)]), stride)


def decode_batch(payloads: list[bytes], n: np.ndarray, codec: str) -> np.ndarray:
    """The flat buffer of deltas of these payloads."""
    return ALL[codec].decode_many(payloads, n)


def encode_chunks(chunks: DataFrame, codec: str, delta: str = "d1") -> DataFrame:
    """Chunk rows -> encoded rows (ENCODED). With delta `none` the lists may be unsorted."""
    stride = STRIDES[delta]
    if codec not in ALL:
        raise ValueError(f"no such code: {codec}")

    def run(batches):
        for batch in batches:
            x, offsets = flat(batch.column("values"))
            payloads = encode_batch(batch_deltas(x, offsets, stride), offsets, codec)
            k = batch.num_rows
            yield pa.RecordBatch.from_arrays(
                [batch.column("list_key"), batch.column("chunk_no"), pa.array([codec] * k), pa.array([delta] * k), batch.column("n"), batch.column("x_min"), batch.column("x_max"), pa.array(list(map(len, payloads)), pa.int64()), pa.array(payloads, pa.binary())],
                ["list_key", "chunk_no", "codec", "delta_mode", "n", "x_min", "x_max", "n_bytes", "payload"],
            )

    return chunks.select("list_key", "chunk_no", "n", "x_min", "x_max", "values").mapInArrow(run, ENCODED)


def decode_chunks(encoded: DataFrame, fused: bool = False) -> DataFrame:
    """Encoded rows, of any mixture of codes, -> chunk rows: differences first and then their sums, or, `fused`, both in one pass where a code can."""

    def run(batches):
        for batch in batches:
            n = batch.column("n").to_numpy(zero_copy_only=False).astype(np.int64)
            offsets = np.concatenate([[0], np.cumsum(n)])
            kinds = list(zip(batch.column("codec").to_pylist(), batch.column("delta_mode").to_pylist()))
            payloads = batch.column("payload").to_pylist()
            x = np.zeros(int(offsets[-1]), np.int64)
            for codec, delta in dict.fromkeys(kinds):
                rows = np.array([k == (codec, delta) for k in kinds])
                own = np.concatenate([[0], np.cumsum(n[rows])])
                mine = [p for p, r in zip(payloads, rows) if r]
                x[np.repeat(rows, n)] = decode_fused(mine, n[rows], codec, STRIDES[delta]) if fused else batch_undeltas(decode_batch(mine, n[rows], codec), own, STRIDES[delta])
            values = pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(x))
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in ("list_key", "chunk_no", "n", "x_min", "x_max")] + [values], ["list_key", "chunk_no", "n", "x_min", "x_max", "values"])

    return encoded.select("list_key", "chunk_no", "codec", "delta_mode", "n", "x_min", "x_max", "payload").mapInArrow(run, CHUNKS)


def to_postings(chunks: DataFrame) -> DataFrame:
    return chunks.select("list_key", F.explode("values").alias("x"))


def timed(x: np.ndarray, offsets: np.ndarray, codec: str, delta: str, runs: int = 1, fused: bool = False) -> tuple[int, int, int, int]:
    """Bytes, and the best of `runs` kernel times (ns) of coding, of decoding, and of the prefix sums within it. Checks the result."""
    stride, best, n = STRIDES[delta], [1 << 62] * 3, np.diff(offsets)
    for _ in range(runs):
        t = [time.perf_counter_ns()]
        payloads = encode_batch(batch_deltas(x, offsets, stride), offsets, codec)
        t.append(time.perf_counter_ns())
        if fused:
            back = decode_fused(payloads, n, codec, stride)
            t += [time.perf_counter_ns()] * 2
        else:
            d = decode_batch(payloads, n, codec)
            t.append(time.perf_counter_ns())
            back = batch_undeltas(d, offsets, stride)
            t.append(time.perf_counter_ns())
        best = [min(a, b) for a, b in zip(best, (t[1] - t[0], t[3] - t[1], t[3] - t[2]))]
    if not np.array_equal(back, x):
        raise ValueError(f"{codec}/{delta} did not decode to its input")
    return sum(map(len, payloads)), *best


def payload_bytes(chunks: DataFrame, codes: list[tuple[str, str]]) -> DataFrame:
    """list_key, codec, delta_mode, n_bytes of every list under every code, in one pass over the chunks."""

    def run(batches):
        for batch in batches:
            x, offsets = flat(batch.column("values"))
            for delta in dict.fromkeys(m for _, m in codes):
                d = batch_deltas(x, offsets, STRIDES[delta])
                for codec in (c for c, m in codes if m == delta):
                    size = list(map(len, encode_batch(d, offsets, codec)))
                    yield pa.RecordBatch.from_arrays([batch.column("list_key"), pa.array([codec] * len(size)), pa.array([delta] * len(size)), pa.array(size, pa.int64())], ["list_key", "codec", "delta_mode", "n_bytes"])

    found = chunks.select("list_key", "values").mapInArrow(run, "list_key string, codec string, delta_mode string, n_bytes long")
    return found.groupBy("list_key", "codec", "delta_mode").agg(F.sum("n_bytes").alias("n_bytes"))


TIMES = ("n_ints", "n_bytes", "coding_ns", "decoding_ns", "prefix_ns")


def measure(chunks: DataFrame, codec: str, delta: str = "d1", runs: int = 1, fused: bool = False) -> DataFrame:
    """One row per batch: integers, bytes, and the best of `runs` kernel times (ns) for coding, decoding and the prefix sums alone.

    Times include the differential coding. Every batch is checked to decode to what it was.
    """

    def run(batches):
        for batch in batches:
            x, offsets = flat(batch.column("values"))
            got = timed(x, offsets, codec, delta, runs, fused)
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64()) for k in (len(x), *got)], list(TIMES))

    return chunks.select("values").mapInArrow(run, ", ".join(f"{c} long" for c in TIMES))


def measured(chunks: DataFrame, codec: str, delta: str = "d1", runs: int = 1, fused: bool = False) -> DataFrame:
    """codec, delta_mode, n_ints, bits_per_int, ratio, coding_mis, decoding_mis, delta_share."""
    total = measure(chunks, codec, delta, runs, fused).agg(*[F.sum(c).alias(c) for c in TIMES])
    return total.select(
        F.lit(codec).alias("codec"),
        F.lit(delta).alias("delta_mode"),
        "n_ints",
        (8 * F.col("n_bytes") / F.col("n_ints")).alias("bits_per_int"),
        (4 * F.col("n_ints") / F.col("n_bytes")).alias("ratio"),
        (1000 * F.col("n_ints") / F.col("coding_ns")).alias("coding_mis"),
        (1000 * F.col("n_ints") / F.col("decoding_ns")).alias("decoding_mis"),
        (F.col("prefix_ns") / F.col("decoding_ns")).alias("delta_share"),
    )


def _tasks(chunks: DataFrame, most: int = 1 << 21, least: int = 1 << 18) -> int:
    """How many tasks code the chunks: `most` integers for each, fewer where cores would wait, but not below `least`."""
    ints = chunks.agg(F.sum("n").alias("n")).first()["n"] or 0
    return max(1, ints // most, min(4 * chunks.sparkSession.sparkContext.defaultParallelism, ints // least))


def measure_classes(chunks: DataFrame, codes: list[tuple[str, str]], runs: int = 1) -> DataFrame:
    """codec, delta_mode, K, n_ints, n_bytes, coding_ns, decoding_ns, summed over the lists of each class of length.

    All codes are timed in one pass over the chunks. Each task has its share of every class and takes them in order, so
    that a batch holds few of them and the few long lists, which hold most of the integers, are not one task's.
    """
    from .measures import length_class

    # A list is as long as its chunk, but for the few that have several. Written, so that their number is known.
    several = chunks.filter("chunk_no > 0").select("list_key").distinct()
    lists = written(chunks.sparkSession, chunks.join(several, "list_key", "left_semi").groupBy("list_key").agg(F.sum("n").cast("long").alias("list_n")), "several")
    laid = chunks.join(lists, "list_key", "left").select(length_class(F.coalesce("list_n", F.col("n").cast("long"))).alias("K"), F.xxhash64("list_key", "chunk_no").alias("part"), "values")
    laid = laid.repartition(_tasks(chunks), "part").sortWithinPartitions("K")

    def run(batches):
        for batch in batches:
            classes = batch.column("K").to_numpy()
            x, offsets = flat(batch.column("values"))
            for k in np.unique(classes).tolist():
                a, b = np.searchsorted(classes, [k, k + 1])
                own, edges = x[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
                rows = [(c, m, k, len(own), *timed(own, edges, c, m, runs)[:3]) for c, m in codes]
                yield pa.RecordBatch.from_arrays([pa.array(column) for column in zip(*rows)], names).cast(schema)

    names = ["codec", "delta_mode", "K", "n_ints", "n_bytes", "coding_ns", "decoding_ns"]
    schema = pa.schema([("codec", pa.string()), ("delta_mode", pa.string()), ("K", pa.int32()), *[(c, pa.int64()) for c in names[3:]]])
    found = laid.select("K", "values").mapInArrow(run, "codec string, delta_mode string, K int, n_ints long, n_bytes long, coding_ns long, decoding_ns long")
    return found.groupBy("codec", "delta_mode", "K").agg(*[F.sum(c).alias(c) for c in names[3:]])
