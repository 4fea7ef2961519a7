"""Streams of (key, id) to encoded lists."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from laneforge.plans.pipeline import build_chunks, decode_chunks, encode_chunks, to_postings
from laneforge.session import shared_root

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """The events of a folder of Parquet files as they come, or of one file; ts becomes a timestamp that watermarks accept."""
    reader, path = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger), spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    if path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(path).isFile():
        reader, folder = reader.option("pathGlobFilter", path.getName()), path.getParent().toString()  # a stream watches folders
    return reader.parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def daily_counts(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events of each type and day: n, first and last id; rows later than the watermark are dropped."""
    windowed = (events.withWatermark("ts", late) if events.isStreaming else events).groupBy(F.window("ts", "1 day"), "event_type")
    out = windowed.agg(F.count("*").alias("n"), F.min("event_id").alias("x_min"), F.max("event_id").alias("x_max"))
    return out.select(F.col("event_type").alias("list_key"), F.date_format(F.col("window.start"), "yyyy-MM-dd").alias("day"), "n", "x_min", "x_max")


def sliding_counts(events: DataFrame, late: str = "1 hour") -> DataFrame:
    windowed = (events.withWatermark("ts", late) if events.isStreaming else events).groupBy(F.window("ts", "1 day", "6 hours"), "event_type")
    return windowed.agg(F.count("*").alias("n")).select(F.col("event_type").alias("list_key"), F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Sessions of each user: start, n, first and last id."""
    windowed = (events.withWatermark("ts", late) if events.isStreaming else events).groupBy(F.session_window("ts", gap), "user_id")
    out = windowed.agg(F.count("*").alias("n"), F.min("event_id").alias("x_min"), F.max("event_id").alias("x_max"))
    return out.select("user_id", F.col("session_window.start").alias("start"), "n", "x_min", "x_max")


def distinct_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def append_encoded(events: DataFrame, path: str, checkpoint: str, codec: str = "vpack128", key: str = "event_type"):
    """Each micro-batch becomes encoded chunks, appended at path; returns the query. Run compact() now and then."""

    def sink(batch: DataFrame, epoch: int) -> None:
        rows = batch.select(F.col(key).cast("string").alias("list_key"), F.col("event_id").alias("x")).filter("list_key IS NOT NULL AND x IS NOT NULL").distinct()
        encode_chunks(build_chunks(rows), codec).withColumn("epoch", F.lit(epoch)).write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return events.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def compact(encoded: DataFrame, codec: str = "vpack128", delta: str = "d1") -> DataFrame:
    """Small chunks of many batches, whose ranges may overlap, to full chunks of distinct ids."""
    return encode_chunks(build_chunks(to_postings(decode_chunks(encoded)).distinct()), codec, delta)


def with_names(events: DataFrame, dimension: DataFrame, on: str) -> DataFrame:
    """Stream-static join: events with the columns of a dimension table that is read anew for every batch; events without a match stay."""
    return events.join(dimension, on, "left")


def daily_lists(events: DataFrame, codec: str = "vpack128") -> DataFrame:
    """Encoded lists (one row per chunk) of the event ids of each type and day; list_key is `type/day`."""
    rows = events.select(F.concat_ws("/", "event_type", F.date_format("ts", "yyyy-MM-dd")).alias("list_key"), F.col("event_id").alias("x"))
    return encode_chunks(build_chunks(rows.filter("list_key IS NOT NULL AND x IS NOT NULL").distinct()), codec)


def drained(spark: SparkSession, stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there now and gives what it emitted, from a table in the shared folder.

    mode `append`: rows as they become final; `complete`: the whole result after the last batch.
    """
    path = f"{shared_root(spark)}/laneforge/{name}-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{path}/checkpoint").outputMode(mode).trigger(availableNow=True)
    if mode == "append":
        writer = writer.format("parquet").option("path", f"{path}/out")
    else:
        writer = writer.foreachBatch(lambda batch, epoch: batch.write.mode("overwrite").parquet(f"{path}/out"))
    writer.start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/out")


STATE = T.StructType([T.StructField("x", T.LongType())])
MARKS = T.StructType([T.StructField(n, T.LongType()) for n in ("top", "chunks", "held", "last")])
SEALED = "list_key string, chunk_no long, n int, x_min long, x_max long, values array<long>, side boolean"


def seal_blocks(keyed: DataFrame, limit: int = 2048, idle_ms: int = 60_000) -> DataFrame:
    """Stateful builder: (list_key, x) -> a chunk whenever a list has gathered `limit` ids, and what is left once a list got none for idle_ms.

    State is a list of fewer than `limit` ids for each key, and four numbers: the greatest id sealed, chunks so far, ids
    held and the greatest of them. Ids that come in order are appended to the list, which is only rewritten when a chunk
    is sealed or an id comes out of order. An id that comes after a greater one was sealed goes to a side chunk of its
    own batch, so the order within a chunk always holds. Timers fire in a later batch of the running stream. Needs the
    RocksDB state store.
    """
    from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

    class Builder(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.handle = handle
            self.buffer = handle.getListState("buffer", STATE)
            self.marks = handle.getValueState("marks", MARKS)

        def _chunk(self, key, number, values, side):
            return {"list_key": key[0], "chunk_no": number, "n": len(values), "x_min": values[0], "x_max": values[-1], "values": values, "side": side}

        def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
            top, chunks, n, last = self.marks.get() if self.marks.exists() else (-1, 0, 0, -1)
            got = sorted({int(x) for f in rows for x in f["x"]})
            late, fresh, out = [x for x in got if x <= top], [x for x in got if x > top], []
            if late:
                out.append(self._chunk(key, chunks, late, True))
                chunks += 1
            if fresh and fresh[0] > last and n + len(fresh) < limit:
                self.buffer.appendList([(x,) for x in fresh])
                n, last = n + len(fresh), fresh[-1]
            elif fresh:
                held = sorted({r[0] for r in self.buffer.get()} | set(fresh))
                while len(held) >= limit:
                    out.append(self._chunk(key, chunks, held[:limit], False))
                    chunks, top, held = chunks + 1, held[limit - 1], held[limit:]
                if held:
                    self.buffer.put([(x,) for x in held])
                else:
                    self.buffer.clear()
                n, last = len(held), held[-1] if held else -1
            self.marks.update((top, chunks, n, last))
            for t in list(self.handle.listTimers()):
                self.handle.deleteTimer(t)
            if n:
                self.handle.registerTimer(timerValues.getCurrentProcessingTimeInMs() + idle_ms)
            if out:
                yield pd.DataFrame(out)

        def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
            top, chunks, n, last = self.marks.get()
            if n:
                held = sorted(r[0] for r in self.buffer.get())
                self.buffer.clear()
                self.marks.update((last, chunks + 1, 0, -1))
                yield pd.DataFrame([self._chunk(key, chunks, held, False)])

        def close(self) -> None:
            pass

    return keyed.groupBy("list_key").transformWithStateInPandas(statefulProcessor=Builder(), outputStructType=SEALED, outputMode="Append", timeMode="ProcessingTime")
