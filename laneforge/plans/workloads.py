"""The experiment workloads: packing speeds, web postings, the table of all codes, the frontier, intervals."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from laneforge.functions import kernels as K
from laneforge.sources.postings import WORD_BREAK

from . import measures, pipeline

#: Words too frequent to index, in the languages of the given tables.
STOP_WORDS = "a an and are as at be by for from has he in is it its of on that the to was were will with de la le les et des un une en du que der die das und ist von el los las y".split()
#: Endings that are dropped from words that keep at least three letters, the longest first.
ENDINGS = ["ations", "ation", "ingly", "ments", "ment", "ings", "edly", "ing", "ies", "ed", "es", "ly", "s"]


def stem(word: Column) -> Column:
    """The word without the first of the endings that it has."""
    out = word
    for ending in reversed(ENDINGS):
        out = F.when(word.endswith(ending) & (F.length(word) >= len(ending) + 3), F.substr(word, F.lit(1), F.length(word) - len(ending))).otherwise(out)
    return out


def web_postings(pages: DataFrame, top: int, id_col: str = "page_id", html: str = "html") -> DataFrame:
    """(list_key, x) of the `top` most frequent stems of tag-free pages, stop words left out; ties by stem."""
    words = F.filter(F.split(F.lower(F.regexp_replace(html, "<[^>]*>", " ")), WORD_BREAK), lambda w: (w != "") & ~w.isin(STOP_WORDS))
    rows = pages.select(F.explode(F.array_distinct(F.transform(words, stem))).alias("list_key"), F.col(id_col).cast("long").alias("x")).distinct()
    frequent = rows.groupBy("list_key").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "list_key").limit(top)
    return rows.join(frequent.select("list_key"), "list_key", "left_semi")


def arrays_of(batches, n: int):
    """The first columns of a task's batches as arrays of n 32-bit integers, the last one shorter."""
    held, have = [], 0
    for batch in batches:
        x = batch.column(0).to_numpy(zero_copy_only=False).astype(np.uint32)
        while have + len(x) >= n:
            yield np.concatenate([*held, x[: n - have]])
            x, held, have = x[n - have :], [], 0
        held, have = [*held, x], have + len(x)
    if have:
        yield np.concatenate(held)


def packing_speeds(rows: DataFrame, value: Column, n: int = 1 << 16, runs: int = 3) -> DataFrame:
    """b, variant, n_ints, pack_mis, unpack_mis for widths 1 to 32 over the values of all rows in arrays of 256 KB, each checked.

    An array is packed at width b as the low b bits of its values. A task's last array is filled up to whole blocks with zeros, which do not count.
    """

    def run(batches):
        for x in arrays_of(batches, n):
            filled = np.concatenate([x, np.zeros(-len(x) % 128, np.uint32)])
            for b in range(1, 33):
                v = filled & np.uint32((1 << b) - 1)
                for name, width, pack, unpack in (
                    ("scalar", 32, K.pack_scalar, K.unpack_scalar),
                    ("scalar_masked", 32, lambda x, b: K.pack_scalar(x, b, mask=True), K.unpack_scalar),
                    ("vertical", 128, K.pack_vertical, lambda w, b, k: K.unpack_vertical(w, b)),
                    ("vertical_masked", 128, lambda x, b: K.pack_vertical(x, b, mask=True), lambda w, b, k: K.unpack_vertical(w, b)),
                    ("horizontal", 128, K.pack_scalar, K.unpack_horizontal),
                ):
                    blocks, best = v.reshape(-1, width), [1 << 62, 1 << 62]
                    for _ in range(runs):
                        t0 = time.perf_counter_ns()
                        words = pack(blocks, b)
                        t1 = time.perf_counter_ns()
                        back = unpack(words, b, width)
                        best = [min(best[0], t1 - t0), min(best[1], time.perf_counter_ns() - t1)]
                    if not np.array_equal(back, blocks):
                        raise ValueError(f"{name} packing at {b} bits is not exact")
                    yield pa.RecordBatch.from_pydict({"b": pa.array([b], pa.int32()), "variant": [name], "n_ints": [len(x)], "pack_ns": [best[0]], "unpack_ns": [best[1]]})

    found = rows.select(value.cast("long").alias("x")).filter("x IS NOT NULL").mapInArrow(run, "b int, variant string, n_ints long, pack_ns long, unpack_ns long")
    mis = lambda ns: 1000 * F.sum("n_ints") / F.sum(ns)
    return found.groupBy("b", "variant").agg(F.sum("n_ints").alias("n_ints"), mis("pack_ns").alias("pack_mis"), mis("unpack_ns").alias("unpack_mis"))


def copy_speed(rows: DataFrame, value: Column, n: int = 1 << 22, runs: int = 5) -> DataFrame:
    """n_ints, copy_mis: all values of a column of 32-bit integers, and how many millions of them a second a plain copy moves, n at once: the ceiling of any decoder here."""

    def run(batches):
        for a in arrays_of(batches, n):
            b, best = np.empty_like(a), 1 << 62
            for _ in range(runs):
                t = time.perf_counter_ns()
                np.copyto(b, a)
                best = min(best, time.perf_counter_ns() - t)
            yield pa.RecordBatch.from_pydict({"n_ints": [len(a)], "ns": [best]})

    found = rows.select(value.cast("long").alias("x")).filter("x IS NOT NULL").mapInArrow(run, "n_ints long, ns long")
    return found.agg(F.sum("n_ints").alias("n_ints"), (1000 * F.sum("n_ints") / F.sum("ns")).alias("copy_mis"))


def cycles(mis: Column, mhz: Column) -> Column:
    """Processor cycles an integer, from millions of integers and of cycles a second."""
    return mhz / mis


def clock(spark: SparkSession) -> DataFrame:
    """mhz: the clock that a worker's machine states, null where it states none."""

    def run(batches):
        for _ in batches:
            found = None
            try:
                with open("/proc/cpuinfo") as f:
                    found = max((float(line.split(":")[1]) for line in f if line.startswith("cpu MHz")), default=None)
            except OSError:
                pass
            yield pa.RecordBatch.from_pydict({"mhz": pa.array([found], pa.float64())})

    return spark.range(1, numPartitions=1).mapInArrow(run, "mhz double")


def buffer_memory(chunks: DataFrame, codes: list[tuple[str, str]]) -> DataFrame:
    """codec, delta_mode, pages, coding_kb, decoding_kb: the most that any one of the chunks takes at once besides itself and its payload."""

    def run(batches):
        import tracemalloc

        for batch in batches:
            for i in range(batch.num_rows):
                x, offsets = pipeline.flat(batch.column("values").slice(i, 1))
                for codec, delta in codes:
                    stride, most = pipeline.STRIDES[delta], []
                    payloads = pipeline.encode_batch(pipeline.batch_deltas(x, offsets, stride), offsets, codec)
                    for step in (
                        lambda: pipeline.encode_batch(pipeline.batch_deltas(x, offsets, stride), offsets, codec),  # noqa: B023
                        lambda: pipeline.batch_undeltas(pipeline.decode_batch(payloads, np.diff(offsets), codec), offsets, stride),  # noqa: B023
                    ):
                        tracemalloc.start()
                        step()
                        most.append(tracemalloc.get_traced_memory()[1] / 1024)
                        tracemalloc.stop()
                    yield pa.RecordBatch.from_pydict({"codec": [codec], "delta_mode": [delta], "coding_kb": [most[0]], "decoding_kb": [most[1]]})

    found = chunks.select("values").mapInArrow(run, "codec string, delta_mode string, coding_kb double, decoding_kb double")
    return found.groupBy("codec", "delta_mode").agg(F.count("*").alias("pages"), F.max("coding_kb").alias("coding_kb"), F.max("decoding_kb").alias("decoding_kb"))


#: Arrays, integers of each, and their range, of the published synthetic sets.
REGIMES = {"short": (1 << 10, 1 << 15, 1 << 29), "long": (1, 1 << 25, 1 << 29)}


def synthetic(spark: SparkSession, kind: str, regime: str, scale: int = 1) -> DataFrame:
    """Chunks of a synthetic set. scale divides the number of short arrays, or the length and the range of the long one, so gaps stay."""
    from laneforge.sources import synth

    arrays, n, hi = REGIMES[regime]
    if regime == "short":
        arrays = max(1, arrays // scale)
    else:
        n, hi = n // scale, hi // scale
    make = {"uniform": synth.gen_uniform, "clustered": synth.gen_clustered}[kind]
    return pipeline.build_chunks(make(spark, arrays, n, hi))


def all_codes(chunks: DataFrame, codes: list[tuple[str, str]], runs: int = 1) -> DataFrame:
    """codec, delta_mode, bits_per_int, ratio, coding_mis, decoding_mis, delta_share for each code. Cache the chunks first."""
    out = None
    for codec, delta in codes:
        one = pipeline.measured(chunks, codec, delta, runs)
        out = one if out is None else out.unionByName(one)
    return out


def frontier(table: DataFrame, bits: str = "bits_per_int", coding: str = "coding_mis", decoding: str = "decoding_mis") -> DataFrame:
    """The codes of a table that none beats in both bits and decoding speed, and how many times slower than the fastest of all each codes."""
    named = table.withColumn("code", F.concat_ws("/", "codec", "delta_mode"))
    fastest = named.agg(F.max(coding).alias("fastest"))
    best = measures.pareto(named, bits, decoding, "code").crossJoin(F.broadcast(fastest))
    return best.select("code", bits, decoding, coding, (F.col("fastest") / F.col(coding)).alias("lag"))


def in_intervals(rows: DataFrame, intervals: DataFrame, width: int) -> DataFrame:
    """Interval join: rows (x, ...) with intervals (name, lo, hi), lo <= x <= hi, by equal buckets of `width` numbers.

    An interval goes to every bucket that it touches, so choose a width near the usual length of an interval.
    """
    spread = intervals.withColumn("bucket", F.explode(F.sequence(F.expr(f"lo div {width}"), F.expr(f"hi div {width}"))))
    return rows.withColumn("bucket", F.expr(f"x div {width}")).join(spread, "bucket").filter("x BETWEEN lo AND hi").drop("bucket")
