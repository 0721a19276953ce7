"""Session helpers: the shared folder, written intermediate tables, released shuffles."""

from __future__ import annotations

import gc
import os
import tempfile
import time
import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir`` of the session.

    Where the setting is missing (tests, a laptop) a temporary folder is used.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        sc = spark.sparkContext
        known = sc._jsc.sc().getCheckpointDir()
        if known.isDefined():
            return known.get()
        folder = "file://" + os.path.join(tempfile.gettempdir(), f"glyphfold-{uuid.uuid4().hex}")
        sc.setCheckpointDir(folder)
    return folder


#: Tables of one process lie in one folder of their own.
RUN = uuid.uuid4().hex


def run_dir(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/glyphfold/{RUN}"


def clear(spark: SparkSession) -> None:
    """Delete all tables that ``settle`` wrote in this process; no DataFrame made before can be read any more."""
    remove(spark, run_dir(spark))


def remove(spark: SparkSession, folder: str) -> None:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


#: Rows above which a settled table is never sent to the driver and the executors as a whole.
BROADCAST_ROWS = 200_000
#: Bytes of files below which a settled table is not counted.
COUNTED_BYTES = 1 << 18
#: Bytes of files above which shuffles of a settled table are worth a pause to be dropped.
PAUSE_BYTES = 1 << 24


def settle(df: DataFrame, name: str = "t") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back.

    Cuts lineage: what comes later survives lost executors without repeating
    the work, and plans of loops stay short. Spark judges by the bytes of the
    files whether a table is broadcast; columns of few values are held in a
    fraction of what their rows need in memory, so tables of many rows are
    marked to be joined by sorting.
    """
    spark = df.sparkSession
    path = f"{run_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    if stored_bytes(spark, path) > COUNTED_BYTES and out.count() > BROADCAST_ROWS:
        out = out.hint("merge")
    out._settled_at = path
    return out


def few(df: DataFrame) -> DataFrame:
    """A settled table of few rows, marked to be sent to the executors as a whole: what it is joined with is then not shuffled."""
    return F.broadcast(df) if hasattr(df, "_settled_at") and df.count() <= BROADCAST_ROWS else df


def gathered(df: DataFrame) -> pd.DataFrame:
    """All rows on the driver, sent as columns: no object is made for each row."""
    return df.toArrow().to_pandas()


def large(df: DataFrame) -> bool:
    """Whether a settled table has more than ``PAUSE_BYTES``."""
    return stored_bytes(df.sparkSession, df._settled_at) > PAUSE_BYTES


def stored_bytes(spark: SparkSession, folder: str) -> int:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(path).getLength()


def whole_row(df: DataFrame):
    """All columns of ``df`` as one column ``row``: what is added beside it can't clash with their names."""
    return F.struct(*(F.col(f"`{c}`") for c in df.columns)).alias("row")


def discard(*tables: DataFrame) -> None:
    """Delete tables that ``settle`` wrote, once nothing reads them any more; others are left."""
    for df in tables:
        if hasattr(df, "_settled_at"):
            remove(df.sparkSession, df._settled_at)


def release(spark: SparkSession) -> None:
    """Let the driver drop shuffle files that no live DataFrame needs any more.

    References of Python objects reach the JVM with a delay, so it is asked twice.
    """
    for _ in range(2):
        gc.collect()
        time.sleep(0.2)
        spark.sparkContext._jvm.System.gc()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
