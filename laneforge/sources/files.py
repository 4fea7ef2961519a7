"""Lists in files: other formats in, encoded tables out and in, a data source with pushed filters."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

from laneforge.plans.measures import length_class

LONG_FORM = "list_key string, x long"
LIST_FORM = "list_key string, values array<long>"


def read_lists(spark: SparkSession, path: str, format: str, arrays: bool = False) -> DataFrame:
    """(list_key, x) from csv, json, parquet, orc, or text lines `key<TAB>id id id`. arrays: a column `values` holds each list."""
    if format == "text":
        parts = F.split("value", "\t")
        return spark.read.text(path).select(parts[0].alias("list_key"), F.explode(F.split(parts[1], " ").cast("array<long>")).alias("x"))
    df = spark.read.format(format).schema(LIST_FORM if arrays else LONG_FORM).load(path)
    return df.select("list_key", F.explode("values").alias("x")) if arrays else df


def read_u32_lists(spark: SparkSession, path: str) -> DataFrame:
    """(list_key, x) from binary files of lists, each a little-endian 32-bit length and so many 32-bit integers. Keys are file name and number."""

    def run(batches):
        for batch in batches:
            for name, raw in zip(batch.column(0).to_pylist(), batch.column(1)):
                data, at, k = np.frombuffer(raw.as_py(), "<u4"), 0, 0
                while at < len(data):
                    n = int(data[at])
                    x = data[at + 1 : at + 1 + n].astype(np.int64)
                    if len(x) < n:
                        raise ValueError(f"{name} ends within a list")
                    yield pa.RecordBatch.from_arrays([pa.array([f"{name}#{k}"] * n, pa.string()), pa.array(x)], ["list_key", "x"])
                    at, k = at + 1 + n, k + 1

    files = spark.read.format("binaryFile").load(path).select(F.element_at(F.split("path", "/"), -1).alias("name"), "content")
    return files.mapInArrow(run, LONG_FORM)


def write_encoded(encoded: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Parquet, a folder for each length class of chunks, rows sorted by list and least id, so footers prune both."""
    rows = encoded.withColumn("K", length_class(F.col("n").cast("long")))
    rows.repartition("K", "list_key").sortWithinPartitions("K", "list_key", "x_min").write.mode(mode).partitionBy("K").parquet(path)


def read_encoded(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


class _File(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


class _Reader(DataSourceReader):
    """Reads files of an encoded table, decoding only the chunks that the pushed filters leave."""

    def __init__(self, files: list[str]):
        self.files, self.keys, self.lo, self.hi = files, None, 0, 1 << 62

    def pushFilters(self, filters):
        for f in filters:
            column = f.attribute[0] if getattr(f, "attribute", None) else None
            if isinstance(f, EqualTo) and column == "list_key":
                self.keys = {f.value}
            elif column == "x" and isinstance(f, (GreaterThan, GreaterThanOrEqual)):
                self.lo = max(self.lo, f.value)
            elif column == "x" and isinstance(f, (LessThan, LessThanOrEqual)):
                self.hi = min(self.hi, f.value)
            yield f  # Spark applies each filter to the rows again

    def partitions(self):
        return [_File(f) for f in self.files]

    def read(self, partition):
        import pyarrow.parquet as pq

        from laneforge.plans.pipeline import STRIDES, batch_undeltas, decode_batch

        where = [("x_max", ">=", self.lo), ("x_min", "<=", self.hi)] + ([("list_key", "in", self.keys)] if self.keys else [])
        table = pq.read_table(partition.path, filters=where, partitioning=None)
        for r in table.to_pylist():
            n = np.array([r["n"]])
            x = batch_undeltas(decode_batch([r["payload"]], n, r["codec"]), np.array([0, r["n"]]), STRIDES[r["delta_mode"]])
            yield pa.RecordBatch.from_arrays([pa.array([r["list_key"]] * len(x)), pa.array(x)], ["list_key", "x"])


class EncodedLists(DataSource):
    """spark.read.format("encoded_lists").option("files", "a.parquet,b.parquet").load() -> (list_key, x).

    Filters on list_key and x are pushed where spark.sql.python.filterPushdown.enabled is set. The files are opened by the
    executors themselves, so they must lie in a file system that all of them mount.
    """

    @classmethod
    def name(cls) -> str:
        return "encoded_lists"

    def schema(self) -> str:
        return LONG_FORM

    def reader(self, schema) -> DataSourceReader:
        return _Reader([f for f in self.options["files"].split(",") if f])
