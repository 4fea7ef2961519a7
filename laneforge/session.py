"""Session helpers: sessions for tests and the bench, table loading, tables written to the shared scratch folder."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LOCAL_ROOTS: dict[str, str] = {}


def local_session(cpus: int = 8, partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A local session for tests and the bench; queries never call this, they use the session they are given."""
    return (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.driver.memory", memory)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def workers_find_package(spark: SparkSession) -> None:
    """Python workers on this machine look for the package where the driver found it; on a cluster it is installed or shipped with --py-files."""
    top = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    known = spark.sparkContext.environment.get("PYTHONPATH", "")
    if top not in known.split(os.pathsep):
        spark.sparkContext.environment["PYTHONPATH"] = os.pathsep.join(x for x in (top, known) if x)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The given table, read by Spark only: the folder may be in a store that nothing else reaches."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a temporary one where it is unset (local mode, tests)."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    key = spark.sparkContext.applicationId
    if key not in _LOCAL_ROOTS:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        _LOCAL_ROOTS[key] = tempfile.mkdtemp(prefix="laneforge-")
        atexit.register(shutil.rmtree, _LOCAL_ROOTS[key], ignore_errors=True)
    return _LOCAL_ROOTS[key]


def written(spark: SparkSession, df: DataFrame, label: str, compression: str = "snappy", keep: bool = False) -> DataFrame:
    """The rows of df, written as Parquet in the shared folder and read back.

    This cuts the lineage: an executor lost later costs a read, not the work before. The folder goes at the end of a
    scratch() block that it was written in, unless kept, or else when the driver's file system closes.
    """
    path = f"{shared_root(spark)}/laneforge/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", compression).parquet(path)
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    _files(spark, target).deleteOnExit(target)
    if _OPEN and not keep:
        _OPEN[-1].append(path)
    return spark.read.schema(df.schema).parquet(path)


#: Paths written in the scratch() blocks that are open.
_OPEN: list[list[str]] = []


def _files(spark: SparkSession, path):
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


@contextmanager
def scratch(spark: SparkSession):
    """Tables that written() makes in this block go at its end; write what is still needed with keep=True."""
    _OPEN.append([])
    try:
        yield
    finally:
        for path in _OPEN.pop():
            target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            _files(spark, target).delete(target, True)
