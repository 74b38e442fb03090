"""The shared folder for tables that cut a lineage; they go when the session's program ends."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

_folders: dict[str, SparkSession] = {}


def scratch_dir(spark: SparkSession) -> str:
    """The folder that the session names in spark.checkpoint.dir, else one in its warehouse; a temporary one only where master is local."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if spark.sparkContext.master.split("[")[0] == "local":
        own = next((x for x, of in _folders.items() if x.startswith("file://") and of is spark), None)
        return own or _remembered(f"file://{tempfile.mkdtemp(prefix='gridchain-')}", spark)
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/")


def _remembered(folder: str, spark: SparkSession) -> str:
    if not _folders:
        atexit.register(_clean)
    _folders[folder] = spark
    return folder


def _clean() -> None:
    for folder, spark in _folders.items():
        with contextlib.suppress(Exception):  # the session may be gone
            delete(spark, folder)


def delete(spark: SparkSession, path: str) -> None:
    """Delete a folder in any file system that the session reaches."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def scratch_path(spark: SparkSession, tag: str) -> str:
    """A new path in this program's part of the shared folder."""
    top = scratch_dir(spark)
    own = next((x for x, of in _folders.items() if of is spark and x.startswith(f"{top}/gridchain-")), None)
    own = own or _remembered(f"{top}/gridchain-{uuid.uuid4().hex}", spark)
    return f"{own}/{tag}-{uuid.uuid4().hex}"


#: While it is set, Spark deletes a statement's shuffle files as soon as the statement has ended.
SHUFFLES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextlib.contextmanager
def without_shuffles(spark: SparkSession) -> Iterator[None]:
    """No shuffle files stay of what runs inside; each map task leaves three files, however few its rows."""
    before = spark.conf.get(SHUFFLES, None)
    spark.conf.set(SHUFFLES, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(SHUFFLES)
        else:
            spark.conf.set(SHUFFLES, before)


def stored(df: DataFrame, tag: str, codec: str = "zstd") -> DataFrame:
    """df written once to the shared folder and read back: a job of its own, without lineage, that survives lost executors."""
    path = scratch_path(df.sparkSession, tag)
    with without_shuffles(df.sparkSession):
        df.write.option("compression", codec).parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._gridchain_path = path
    return out
