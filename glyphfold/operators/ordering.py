"""Numbering of rows in a total order, without a single task that sees them all."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from glyphfold.session import settle


def numbered(df: DataFrame, keys: list, column: str = "rank", start: int = 0, name: str = "numbered") -> DataFrame:
    """``df`` with the place of each row by ``keys`` in ``column``.

    A range shuffle sorts; a row's place is that in its partition plus the counts of the
    partitions before. The driver holds one count a partition. Ties are numbered in any
    order, so keys should tell rows apart.
    """
    spark = df.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    placed = settle(df.repartitionByRange(parts, *keys).sortWithinPartitions(*keys).withColumn("_at", F.monotonically_increasing_id()), name)
    counts = sorted((int(p), int(n)) for p, n in placed.groupBy(F.shiftright("_at", 33)).count().collect())
    before, rows = start, []
    for part, n in counts:
        rows.append((part, before))
        before += n
    if not rows:
        return placed.withColumn("_at", F.lit(start).cast("long")).withColumnRenamed("_at", column)
    offsets = spark.createDataFrame(rows, "_part int, _before long")
    place = F.col("_before") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    return placed.withColumn("_part", F.shiftright("_at", 33).cast("int")).join(F.broadcast(offsets), "_part").withColumn(column, place).drop("_part", "_before", "_at")


def node_draw(x: Column, seed: int):
    """A repeatable draw per node id, below 2**31 - 1, in arithmetic that any SQL has."""
    p = F.lit((1 << 31) - 1)
    return F.pmod(F.pmod(F.pmod(x, p) * 48_271 + seed * 69_621, p) * 40_692, p)
