from pyspark.sql import functions as F

from glyphfold import session


def test_tables_of_many_rows_are_not_broadcast(spark, monkeypatch):
    """Files of few bytes don't tell how many rows would be sent to the driver; small tables are broadcast as before."""
    rows = spark.range(0, 300_000, 1, 4).select("id", (F.col("id") % 7).alias("sid"), F.lit("disconnected").alias("glyph"))
    monkeypatch.setattr(session, "COUNTED_BYTES", 0)
    monkeypatch.setattr(session, "BROADCAST_ROWS", 100_000)
    many, few = session.settle(rows, "many"), session.settle(rows.limit(100), "few")
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    other = many.select(F.col("id").alias("src"), F.col("sid").alias("a"))
    wide = spark.range(10**9).withColumnRenamed("id", "src")
    assert "Broadcast" not in plan(wide.join(other.where("a > 2"), "src"))
    assert "Broadcast" in plan(wide.join(few.select(F.col("id").alias("src")), "src"))
    assert many.join(few.select("id"), "id").count() == 100
    session.discard(many)


def test_bound_of_broadcast_tables_fits_a_small_driver():
    """Rows of a hash table take some 100 bytes, and a plan may broadcast several: all must fit a heap of 750 MB."""
    assert session.BROADCAST_ROWS * 100 * 10 <= 750_000_000
    assert session.COUNTED_BYTES <= session.BROADCAST_ROWS * 2
