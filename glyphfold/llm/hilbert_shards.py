"""Sharding by a Hilbert curve over quantised metadata.

Every row gets a place on a space-filling curve through its metadata dimensions;
the rows are range-sorted by that place and the order is cut into runs, so each
shard file covers a compact box of every dimension and readers can prune files
on any of them. Copies of one text share the coordinates of the copy with the
smallest id, so they stand next to each other and only a cut can part them.

Defined cases: a null or empty text counts no bytes; null metadata is a value of its own;
an empty table gives no rows; repeated rows and null ids each get their own slot; places of
equal rank keys are told apart in any order; a very long text counts by its bytes and is
never gathered with others; columns of the input other than those named are neither read
nor clashed with.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from glyphfold.session import settle

#: Bytes each row counts besides those of its text.
ROW_OVERHEAD = 16


def hilbert_index(coords: np.ndarray, bits: int) -> np.ndarray:
    """Curve index of integer points (rows of ``coords``, each below 2**bits)."""
    x = coords.astype(np.int64).T.copy()
    dims = len(x)
    top = 1 << (bits - 1)
    q = top
    while q > 1:  # undo the rotations of the coarser cells
        low = q - 1
        for i in range(dims):
            on = (x[i] & q) != 0
            swap = np.where(on, 0, (x[0] ^ x[i]) & low)
            x[0] = np.where(on, x[0] ^ low, x[0] ^ swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, dims):  # Gray code across the dimensions
        x[i] ^= x[i - 1]
    flip = np.zeros_like(x[0])
    q = top
    while q > 1:
        flip = np.where(x[-1] & q, flip ^ (q - 1), flip)
        q >>= 1
    x ^= flip
    out = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(dims):
            out = (out << 1) | ((x[i] >> b) & 1)
    return out


def hilbert_column(dims: list, bits: int):
    """Column of the curve index of integer columns ``dims``."""

    @F.pandas_udf(T.LongType())
    def place(points: pd.DataFrame) -> pd.Series:
        return pd.Series(hilbert_index(points.to_numpy(), bits))

    return place(F.struct(*dims))


def quantised(column, kind: str, bits: int):
    """Categories fall in ``2**bits`` hashed cells, sizes in eighths of an octave."""
    cells = (1 << bits) - 1
    if kind == "category":
        return F.shiftrightunsigned(F.crc32(F.coalesce(column, F.lit("\0")).cast("binary")), 32 - bits).cast("int")
    return F.least(F.lit(cells), F.floor(8 * F.log2(1.0 + F.coalesce(column, F.lit(0)).cast("double")))).cast("int")


def ranked(df: DataFrame, keys: list[str], name: str = "order") -> tuple[DataFrame, int]:
    """Rows of ``df`` with ``rank`` (from 0, by ``keys``) and their number.

    A range shuffle sorts; ranks come from the rows' place in their partition plus
    the counts of the partitions before. The driver holds one count a partition.
    """
    spark = df.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    placed = settle(
        df.repartitionByRange(parts, *keys).sortWithinPartitions(*keys).withColumn("_at", F.monotonically_increasing_id()),
        name,
    )
    counts = {int(r[0]): int(r[1]) for r in placed.groupBy(F.shiftright("_at", 33)).count().collect()}
    starts, total = [], 0
    for part in sorted(counts):
        starts.append((part, total))
        total += counts[part]
    if not starts:
        return placed.withColumn("rank", F.lit(0).cast("long")).drop("_at"), 0
    offsets = spark.createDataFrame(starts, "_part int, _before long")
    return (
        placed.withColumn("_part", F.shiftright("_at", 33).cast("int"))
        .join(F.broadcast(offsets), "_part")
        .withColumn("rank", F.col("_before") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1)))
        .drop("_part", "_before", "_at"),
        total,
    )


def hilbert_shards(
    docs: DataFrame, shards: int = 40, bits: int = 8, id_col: str = "doc_id", text_col: str = "text", categories: tuple = ("lang", "source")
) -> DataFrame:
    """``(id, size, text_crc32, curve, shard, slot)``: runs of the curve, equal in rows."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    size = F.octet_length(text).cast("long")
    rows = docs.select(
        F.col(id_col).alias("doc_id"),
        (size + ROW_OVERHEAD).alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.xxhash64(text, size).alias("copy"),
        F.struct(F.col(id_col).alias("doc_id"), *(quantised(F.col(c), "category", bits).alias(f"d{i}") for i, c in enumerate(categories)), quantised(size, "size", bits).alias("ds")).alias("at"),
    )
    rows = settle(rows, "shard_rows")
    first = rows.groupBy("copy").agg(F.min("at").alias("first"))
    dims = [F.col(f"first.d{i}") for i in range(len(categories))] + [F.col("first.ds")]
    first = first.select("copy", hilbert_column(dims, bits).alias("curve"))
    placed = rows.drop("at").join(first, "copy")
    order, n = ranked(placed, ["curve", "copy", "doc_id"], "shard_order")
    base, more = divmod(n, shards)
    cut = more * (base + 1)
    r = F.col("rank")
    late = r - F.lit(cut)
    shard = F.when(r < cut, F.expr(f"rank div {base + 1}")).otherwise(more + (F.expr(f"(rank - {cut}) div {max(base, 1)}")))
    slot = F.when(r < cut, r % (base + 1)).otherwise(late % max(base, 1))
    return order.select("doc_id", "size", "text_crc32", "curve", shard.cast("int").alias("shard"), slot.cast("long").alias("slot"))


def write_shards(docs: DataFrame, shards: DataFrame, path: str) -> None:
    """Write the documents as one folder a shard, rows in slot order."""
    tagged = docs.join(shards.select("doc_id", "shard", "slot"), "doc_id")
    n = docs.sparkSession.conf.get("spark.sql.shuffle.partitions")
    tagged.repartition(int(n), "shard").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = hilbert_shards(docs)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve")
