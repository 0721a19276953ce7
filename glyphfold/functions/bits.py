"""Code lengths in bits, as native column expressions and as scalars for kernels."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Number of glyph kinds.
GLYPHS = ("clique", "in_star", "out_star", "disconnected")
#: Up to this many picks a binomial is a product; beyond, Stirling's series is exact to 1e-12.
DIRECT_PICKS = 32


def int_bits(k: Column, zero_bits: float = 3.0) -> Column:
    """Universal code of an integer from 1 on; zero has a codeword of its own."""
    return F.when(k == 0, F.lit(zero_bits)).otherwise(2 * F.log2(k.cast("double")) + 1)


def uniform_bits(n: Column) -> Column:
    return F.log2(n.cast("double"))


def log2_binomial(n: Column, k: Column) -> Column:
    """log2 of n choose k; n up to 1e22 as a double."""
    n, k = n.cast("double"), k.cast("double")
    j = F.least(k, n - k)
    short = F.aggregate(F.sequence(F.lit(1), F.greatest(j, F.lit(1.0)).cast("int")), F.lit(0.0), lambda a, i: a + F.log2((n - i + 1) / i))
    rest = n - j
    inv = lambda x, p: 1 / F.pow(x, F.lit(float(p)))
    long = (
        j * F.log(n / j)
        - rest * F.log1p(-j / n)
        + 0.5 * F.log(n / (2 * math.pi * j * rest))
        + (inv(n, 1) - inv(j, 1) - inv(rest, 1)) / 12
        - (inv(n, 3) - inv(j, 3) - inv(rest, 3)) / 360
    ) / math.log(2)
    return F.when(j <= 0, F.lit(0.0)).when(j <= DIRECT_PICKS, short).otherwise(long)


def entropy_bits(n: Column, k: Column) -> Column:
    """n times the entropy of k hits in n, each slot coded alone."""
    n, k = n.cast("double"), k.cast("double")
    part = lambda x: F.when(x > 0, -x * F.log2(x / n)).otherwise(0.0)
    return part(k) + part(n - k)


def channel_bits(n: Column, k: Column, code: str = "binomial", zero_bits: float = 3.0, charged: bool = False) -> Column:
    """How many corrections there are, and which; a channel without slots is free."""
    which = log2_binomial(n, k) if code == "binomial" else entropy_bits(n, k)
    bits = int_bits(k, zero_bits) + which
    return bits if charged else F.when(n <= 0, F.lit(0.0)).otherwise(bits)


def diff_bits(true: Column, rep: Column) -> Column:
    """Signed difference to a representative: 1 bit if equal."""
    d = F.abs(true - rep)
    return F.when(d == 0, F.lit(1.0)).otherwise(2 * F.log2(d.cast("double")) + 3)


def bag_diff_bits(df: DataFrame, keys: list[str], m: str, rep: str) -> DataFrame:
    return df.groupBy(*keys).agg(F.sum(diff_bits(F.col(m), F.col(rep))).alias("bits"))


def uniform_multiplicity_bits(edges: DataFrame) -> DataFrame:
    """The rejected alternative: every multiplicity costs the log of the largest."""
    return edges.agg(F.count("*").alias("n"), F.max("m").alias("top")).select((F.col("n") * F.log2(F.col("top").cast("double"))).alias("bits"))


def threshold(r: Column, b: Column) -> Column:
    """Similarity at which b bands of r rows start to catch pairs."""
    return F.pow(1.0 / b, 1.0 / r)


def band_curve(j: Column, r: Column, b: Column) -> Column:
    """Chance that a pair of similarity j shares a bucket in some band."""
    return 1 - F.pow(1 - F.pow(j, r), b)


def code_gap(spark: SparkSession, n_max: int) -> DataFrame:
    """Grid of subset codes: the entropy code never undercuts the binomial one."""
    n = spark.range(1, n_max + 1).select(F.col("id").alias("n"))
    return subset_codes(n.select("n", F.explode(F.sequence(F.lit(0).cast("long"), "n")).alias("k")))


def subset_codes(grid: DataFrame) -> DataFrame:
    """Adds the bits of both subset codes to rows with n and k."""
    return grid.select(*grid.columns, log2_binomial(F.col("n"), F.col("k")).alias("binomial"), entropy_bits(F.col("n"), F.col("k")).alias("entropy"))


def weight_to_multiplicity(w: Column, mode: str = "round") -> Column:
    """Positive integer multiplicities of real weights."""
    v = F.ceil(w) if mode == "ceil" else F.round(w)
    return F.greatest(v.cast("long"), F.lit(1).cast("long"))


def register_sql(spark: SparkSession) -> None:
    """The codes as SQL functions of the session; Catalyst inlines them."""
    for text in (
        "int_bits(k DOUBLE) RETURNS DOUBLE RETURN IF(k = 0, 3.0D, 2 * log2(k) + 1)",
        "diff_bits(a DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN IF(a = b, 1.0D, 2 * log2(abs(a - b)) + 3)",
        "lsh_threshold(r DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN pow(1.0D / b, 1.0D / r)",
        "band_curve(j DOUBLE, r DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN 1 - pow(1 - pow(j, r), b)",
        """log2_binomial(n DOUBLE, k DOUBLE) RETURNS DOUBLE RETURN IF(least(k, n - k) <= 0, 0.0D, IF(least(k, n - k) <= 32,
           aggregate(sequence(1, cast(greatest(least(k, n - k), 1) as int)), 0.0D, (a, i) -> a + log2((n - i + 1) / i)),
           (least(k, n - k) * ln(n / least(k, n - k)) - greatest(k, n - k) * log1p(-least(k, n - k) / n)
            + 0.5D * ln(n / (2 * pi() * k * (n - k))) + (1 / n - 1 / k - 1 / (n - k)) / 12
            - (pow(n, -3) - pow(k, -3) - pow(n - k, -3)) / 360) / ln(2)))""",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")


# scalars for kernels


def n_int_bits(k: float, zero_bits: float = 3.0) -> float:
    return zero_bits if k == 0 else 2 * math.log2(k) + 1


def n_log2_binomial(n: float, k: float) -> float:
    j = min(k, n - k)
    if j <= 0:
        return 0.0
    if j <= DIRECT_PICKS:
        return sum(math.log2((n - i + 1) / i) for i in range(1, int(j) + 1))
    rest = n - j
    x = j * math.log(n / j) - rest * math.log1p(-j / n) + 0.5 * math.log(n / (2 * math.pi * j * rest))
    return (x + (1 / n - 1 / j - 1 / rest) / 12 - (n**-3 - j**-3 - rest**-3) / 360) / math.log(2)


def n_channel_bits(n: float, k: float, zero_bits: float = 3.0) -> float:
    return 0.0 if n <= 0 else n_int_bits(k, zero_bits) + n_log2_binomial(n, k)


def n_diff_bits(true: int, rep: int) -> float:
    return 1.0 if true == rep else 2 * math.log2(abs(true - rep)) + 3
