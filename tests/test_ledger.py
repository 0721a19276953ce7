import pytest

from glyphfold.functions import bits
from glyphfold.operators import ledger, summary
from glyphfold.sources.graphs import PropertyGraph, from_edges


def toy(spark):
    a = range(1, 5)
    e = [(i, j, 5 if (i, j) == (1, 2) else 2) for i in a for j in a if i != j]
    e += [(1, 5, 1), (2, 5, 1), (3, 5, 1), (4, 5, 4), (5, 6, 1), (6, 6, 7)]
    nodes = [(i, "a") for i in a] + [(5, "b"), (6, "b")]
    return PropertyGraph(spark.createDataFrame(nodes, "id long, label string"), spark.createDataFrame(e, "src long, dst long, m long"))


def merged(spark, g, glyph, m, edges, hub=None):
    sn = [(1, "a", 4, glyph, m, hub, None), (5, "b", 1, "disconnected", 1, None, None), (6, "b", 1, "disconnected", 1, None, 7)]
    mem = [(i, 1) for i in range(1, 5)] + [(5, 5), (6, 6)]
    return summary.Summary(g, spark.createDataFrame(sn, summary.SUPERNODES), spark.createDataFrame(mem, summary.MEMBERS), spark.createDataFrame(edges, summary.SUPEREDGES))


BASE = [(5, 6, 1), (6, 6, 7)]


@pytest.mark.parametrize(
    "glyph, m, edges, printed, sound",
    [
        ("clique", 2, [(1, 5, 1), *BASE], 92.711075, 97.465963),
        ("clique", 2, BASE, 90.956188, 97.296038),
        ("disconnected", 1, [(1, 5, 1), *BASE], 125.184654, 129.939542),
    ],
)
def test_toy_partitions(spark, glyph, m, edges, printed, sound):
    g = toy(spark)
    s = merged(spark, g, glyph, m, edges)
    got = ledger.ledgers(s)
    assert got["printed"] == pytest.approx(printed, abs=1e-5) and got["sound"] == pytest.approx(sound, abs=1e-5)
    assert s.validate().count() == 0
    assert sorted(map(tuple, summary.reconstruct(s).collect())) == sorted(map(tuple, g.edges.collect()))


def test_identity(spark):
    got = ledger.bits_before(toy(spark))
    assert got["printed"] == pytest.approx(163.245528, abs=1e-5) and got["sound"] == pytest.approx(178.755303, abs=1e-5)


def test_isolated_star(spark):
    g = from_edges(spark.createDataFrame([(0, i) for i in range(1, 5)], "src long, dst long"))
    got = ledger.bits_before(g)
    assert got["printed"] == pytest.approx(60.185065, abs=1e-5) and got["sound"] == pytest.approx(71.794706, abs=1e-5)
    one = summary.Summary(g, spark.createDataFrame([(0, "*", 5, "out_star", 1, 0, None)], summary.SUPERNODES), g.nodes.selectExpr("id", "0L as sid"), spark.createDataFrame([], summary.SUPEREDGES))
    got = ledger.ledgers(one)
    assert got["printed"] == pytest.approx(22.965784, abs=1e-5) == got["sound"]


def test_expansion_of_ports(spark):
    """An in-star joined to three nodes attaches its hub only; two stars attach hub to hub."""
    g = from_edges(spark.createDataFrame([(i, i) for i in range(1, 9)], "src long, dst long"))
    sn = [(1, "*", 3, "in_star", 2, 3, None), (4, "*", 3, "disconnected", 1, None, 5), (7, "*", 2, "out_star", 1, 7, None)]
    mem = [(1, 1), (2, 1), (3, 1), (4, 4), (5, 4), (6, 4), (7, 7), (8, 7)]
    s = summary.Summary(g, spark.createDataFrame(sn, summary.SUPERNODES), spark.createDataFrame(mem, summary.MEMBERS), spark.createDataFrame([(1, 4, 3), (4, 4, 5), (1, 7, 9)], summary.SUPEREDGES))
    got = sorted((r.src, r.dst, r.m) for r in summary.decompress(s).collect())
    assert got == sorted([(1, 3, 2), (2, 3, 2), (7, 8, 1), (3, 4, 3), (3, 5, 3), (3, 6, 3), (4, 4, 5), (5, 5, 5), (6, 6, 5), (3, 7, 9)])
    assert "->" in summary.to_dot(s) and '"nodes"' in summary.to_json(s) and "<edge" in summary.to_graphml(s)


def test_code_lengths(spark):
    from pyspark.sql import functions as F

    assert [bits.n_int_bits(k) for k in (1, 2, 4, 0)] == [1, 3, 5, 3]
    assert [bits.n_diff_bits(a, 3) for a in (3, 4, 7)] == [1, 3, 7]
    assert bits.n_log2_binomial(12, 3) == pytest.approx(7.781360, abs=1e-6)
    bits.register_sql(spark)
    row = spark.sql("select int_bits(4) a, diff_bits(7, 3) b, log2_binomial(12, 3) c, log2_binomial(1e22, 1e11) d, lsh_threshold(2, 5) e").first()
    assert row.a == 5 and row.b == 7 and row.c == pytest.approx(7.781360, abs=1e-6) and row.e == pytest.approx(0.4472, abs=1e-4)
    assert row.d == pytest.approx(bits.n_log2_binomial(1e22, 1e11), rel=1e-12)
    gap = bits.code_gap(spark, 80).where("k > 0 and k < n and entropy < binomial").count()
    assert gap == 0
    import math

    for r in bits.code_gap(spark, 200).where("n = 200").collect():
        assert r.binomial == pytest.approx(math.log2(math.comb(200, r.k)), abs=1e-9)
    assert spark.range(1).select(bits.threshold(F.lit(3), F.lit(10))).first()[0] == pytest.approx(0.4642, abs=1e-4)
