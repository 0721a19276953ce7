"""Edges from event streams: windows, per-user successors, and folding into a table."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from glyphfold.session import shared_dir
from glyphfold.sources.graphs import key_id

EDGE = "src long, dst long, ts timestamp"


def read_events(spark: SparkSession, path: str) -> DataFrame:
    """A file stream over Parquet events: a folder that grows, or one file of it."""
    schema = spark.read.parquet(path).schema
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    reader = spark.readStream.schema(schema)
    if at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(at).isFile():
        return reader.option("pathGlobFilter", at.getName()).parquet(at.getParent().toString())
    return reader.parquet(path)


def _timed(events: DataFrame) -> DataFrame:
    """Watermarks need timestamps with a zone."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def successors(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """(src, dst, ts): each user's state (type and hour) to the next; late events are dropped.

    The last state of every user is kept; rows of one batch are put in time order first.
    """
    key = key_id(F.concat_ws("@", "event_type", F.hour("ts").cast("string")))
    rows = _timed(events).withWatermark("ts", watermark).select("user_id", "ts", "event_id", key.alias("state"))

    def step(user: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        df = pd.concat(list(parts)).sort_values(["ts", "event_id"])
        states, times = df["state"].tolist(), df["ts"].tolist()
        if state.exists:
            states.insert(0, state.get[0])
        else:
            times = times[1:]
        state.update((states[-1],))
        yield pd.DataFrame({"src": states[:-1], "dst": states[1:], "ts": times}).astype({"src": "int64", "dst": "int64"})

    return rows.groupBy("user_id").applyInPandasWithState(step, EDGE, "last long", "append", GroupStateTimeout.NoTimeout)


def window_counts(events: DataFrame, length: str = "1 day", slide: str | None = None, watermark: str = "1 day") -> DataFrame:
    """Events by type and tumbling or sliding window."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return _timed(events).withWatermark("ts", watermark).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str = "6 hours", watermark: str = "1 day") -> DataFrame:
    """Sessions of each user: start, end and number of events."""
    s = F.session_window("ts", gap)
    return _timed(events).withWatermark("ts", watermark).groupBy(s.alias("s"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n")


def run_to_table(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there now into a Parquet table of the shared folder."""
    import uuid

    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/glyphfold/stream-{name}-{uuid.uuid4().hex}"

    def put(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/data/batch={n}")  # a repeated batch replaces itself

    q = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/data").select(*stream.columns)


def fold_edges(edges: DataFrame) -> DataFrame:
    """Multiplicities of the edges seen so far."""
    return edges.groupBy("src", "dst").agg(F.count("*").alias("m"))


def dirty_nodes(before: DataFrame, now: DataFrame) -> DataFrame:
    """Nodes whose neighbourhood changed between two edge tables: their clusters are summarised anew."""
    diff = before.exceptAll(now).union(now.exceptAll(before))
    return diff.select(F.col("src").alias("id")).union(diff.select("dst")).distinct()
