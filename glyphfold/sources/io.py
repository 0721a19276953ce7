"""Edge lists from files, and graphs kept as tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from glyphfold.sources.graphs import PropertyGraph, from_edges, key_id

FORMATS = ("csv", "tsv", "json", "parquet", "orc", "text")


def read_edge_list(spark: SparkSession, path: str, fmt: str = "csv", src: str = "src", dst: str = "dst", m: str | None = None, header: bool = False, directed: bool = True) -> PropertyGraph:
    """A graph from an edge list; keys that aren't whole numbers are hashed to longs.

    Text lines are split at white space, lines starting with # or % are comments.
    """
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        df = spark.read.text(path).where(~F.col("value").rlike(r"^\s*([#%]|$)")).select(F.get(parts, 0).alias("src"), F.get(parts, 1).alias("dst"), F.get(parts, 2).alias("m"))
        src, dst, m = "src", "dst", "m"
    elif fmt in ("csv", "tsv"):
        df = spark.read.csv(path, sep="," if fmt == "csv" else "\t", header=header, comment="#")
        if not header:
            names = df.columns
            src, dst, m = names[0], names[1], names[2] if len(names) > 2 else None
    elif fmt in FORMATS:
        df = spark.read.format(fmt).load(path)
    else:
        raise ValueError(f"unknown format {fmt}")
    weight = F.coalesce(F.col(m).cast("long"), F.lit(1).cast("long")) if m else F.lit(1).cast("long")
    return from_edges(df.select(_key(df, src).alias("src"), _key(df, dst).alias("dst"), weight.alias("m")), directed=directed)


def _key(df: DataFrame, name: str):
    c = F.col(name)
    if isinstance(df.schema[name].dataType, (T.LongType, T.IntegerType, T.ShortType)):
        return c.cast("long")
    return F.when(c.rlike(r"^\d{1,18}$"), c.try_cast("long")).otherwise(key_id(c.cast("string")))


def save_graph(g: PropertyGraph, name: str, buckets: int = 16) -> None:
    """Nodes and edges as tables bucketed by their join keys, for repeated use without a shuffle."""
    g.nodes.write.mode("overwrite").bucketBy(buckets, "id").sortBy("id").saveAsTable(f"{name}_nodes")
    g.edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(f"{name}_edges")


def load_graph(spark: SparkSession, name: str, directed: bool = True) -> PropertyGraph:
    return PropertyGraph(spark.table(f"{name}_nodes"), spark.table(f"{name}_edges"), directed, name)
