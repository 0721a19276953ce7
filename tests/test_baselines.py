import pytest
from pyspark.sql import functions as F

from glyphfold.operators import baselines, ledger, measures, merge, similarity, sqlext, summary, synth
from glyphfold.operators.candidates import candidate_sets, lsh_clusters, minhash
from glyphfold.sources import io
from glyphfold.sources.graphs import PropertyGraph, from_edges


def small(spark):
    e = [(u, v) for u in range(4) for v in range(4) if u != v] + [(u, 9) for u in range(4)] + [(10, u) for u in range(4)] + [(9, 9), (11, 12), (11, 13), (11, 14)]
    nodes = [(i, "a" if i < 9 else "b") for i in (*range(4), *range(9, 15))]
    return PropertyGraph(spark.createDataFrame(nodes, "id long, label string"), from_edges(spark.createDataFrame(e, "src long, dst long")).edges)


def edges(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("how", [baselines.pairmerge_randomized, baselines.pairmerge_greedy, lambda g: baselines.pairmerge_rounds(g, 2)])
def test_pairwise_merging(spark, how):
    g = small(spark)
    s = how(g)
    assert s.validate().count() == 0
    assert edges(summary.reconstruct(s)) == edges(g.edges)
    cost = baselines.pairmerge_cost(s).first()
    assert cost.edges <= g.edges.count()


def test_pairwise_cost_is_incremental(spark):
    p = baselines.Pairs(small(spark))
    want = p.cost_merged(0, 1)
    baselines._merge_pairs(p, 0, 1)
    assert p.cost(0) == want


@pytest.mark.parametrize("kind", ["label", "duplicates", "random"])
def test_groupings(spark, kind):
    g = small(spark)
    for se in ("rule", "all", "none"):
        s = baselines.group_summary(g, kind, se)
        assert s.validate().count() == 0
        assert edges(summary.reconstruct(s)) == edges(g.edges)


def test_vocabulary(spark):
    star = [(0, i) for i in range(1, 30)]
    clique = [(u, v) for u in range(40, 48) for v in range(u + 1, 48)]
    g = from_edges(spark.createDataFrame(star + clique + [(1, 40)], "src long, dst long"), directed=False)
    for select in ("plain", "top10", "top100", "greedy_forget"):
        words = baselines.vocab_summary(g, select)
        assert "star" in set(words["kind"])
        if select == "greedy_forget":
            assert words.attrs["bits"] < words.attrs["before"]


def test_measures(spark):
    g = small(spark)
    s = merge.summarize(g, merge.SummaryConfig(b=3))
    assert measures.compression_ratio(s) == pytest.approx(measures.label_ratio(g, candidate_sets(g, 2, 3), merge.SummaryConfig(b=3)), abs=1e-9)
    walk = merge.Walk(g, merge.SummaryConfig())
    assert measures.ledger_of_identity(walk) == pytest.approx(ledger.bits_before(g)["printed"])
    assert measures.normalized_gain(0.47, 0.36) == pytest.approx(0.1719, abs=1e-4)
    votes = spark.createDataFrame([("x", 0, True), ("x", 0, False), ("x", 1, True), ("x", 1, True)], "g string, ballot long, yes boolean")
    got = {r.ballot: r.entropy for r in measures.vote_entropy(votes, "g").collect()}
    assert got[0] == pytest.approx(0.693147, abs=1e-6) and got[1] == 0
    points = spark.createDataFrame([(10.0, 1.0), (100.0, 10.0), (1000.0, 100.0)], "edges double, seconds double")
    assert measures.scaling_slope(points).first().slope == pytest.approx(1)
    before = sorted(r.label for r in g.nodes.collect())
    assert sorted(r.label for r in measures.shuffled(g, 3).nodes.collect()) == before
    shares = measures.glyph_breakdown(s).collect()
    assert all(r.clique + r.disconnected + r.star + r.single == pytest.approx(1, abs=1e-5) for r in shares)


def test_generators(spark):
    e = synth.kout_edges(spark, 300, 10)
    assert e.where("dst >= src").count() == 0
    assert {r["count"] for r in e.groupBy("src").count().collect()} == {10}
    g = synth.synth_kout(spark, 300, 10)
    half, most = synth.sample_edges(g, 0.4), synth.sample_edges(g, 0.8)
    assert half.edges.exceptAll(most.edges).count() == 0
    assert 0.3 < half.edges.count() / g.edges.count() < 0.5
    p = synth.synth_planted(spark, "clique", 6, 5, context=6)
    jd = {r.jd for r in similarity.exact_simpairs(p, 0.7).where("a < 30").collect()}
    assert jd == {0.75}  # two members share 6 outside neighbours and 3 members, both ways, of 16
    for b in (3, 10):  # the banding curve predicts how many pairs of members come together
        clusters = {r.id: r.cluster for r in lsh_clusters(minhash(p, 2, b), 2, b).collect()}
        met = [clusters.get(5 * k + i, -i) == clusters.get(5 * k + j, -j) for k in range(6) for i in range(5) for j in range(i)]
        assert sum(met) / len(met) >= 1 - (1 - 0.75**2) ** b - 0.1
    s = merge.summarize(p, merge.SummaryConfig(b=10))
    assert s.supernodes.where("glyph = 'clique' and size = 5").count() == 6
    before, after = ledger.identity_bits(p).first(), ledger.ledgers(summary.identity_summary(p))
    assert (before.printed, before.sound) == (pytest.approx(after["printed"]), pytest.approx(after["sound"]))


def test_files_and_sql(spark, tmp_path):
    rows = [("a", "b", 2), ("b", "c", 1), ("a", "b", 1)]
    df = spark.createDataFrame(rows, "src string, dst string, m long")
    for fmt in ("parquet", "orc", "json"):
        df.write.format(fmt).save(f"{tmp_path}/{fmt}")
        assert sorted(r.m for r in io.read_edge_list(spark, f"{tmp_path}/{fmt}", fmt, m="m").edges.collect()) == [1, 3]
    (tmp_path / "e.txt").write_text("# comment\n1 2\n1\t2\n2 3 5\n")
    assert edges(io.read_edge_list(spark, f"{tmp_path}/e.txt", "text").edges) == [(1, 2, 2), (2, 3, 5)]
    (tmp_path / "e.csv").write_text("1,2\n3,4\n")
    assert io.read_edge_list(spark, f"{tmp_path}/e.csv", "csv").edges.count() == 2
    g = small(spark)
    s = merge.summarize(g, merge.SummaryConfig(b=3))
    summary.write_summary(s, f"{tmp_path}/s", {"b": 3})
    again = summary.read_summary(spark, f"{tmp_path}/s")
    assert edges(summary.reconstruct(again)) == edges(g.edges)
    sqlext.register(spark, s, "toy")
    assert spark.sql("select count(*) c from toy_supernodes").first().c == s.supernodes.count()
    assert spark.sql("select * from expand_supernode('in_star', 2L, array(1L, 2L, 3L))").count() == 2
    assert spark.sql("select sum(int_bits(m)) b from toy_superedges").first().b > 0


def test_streams(spark, tmp_path):
    from glyphfold.streaming import windows

    rows = [(i, i % 7, ("view", "click", "buy")[i % 3], 3600 * i // 2) for i in range(120)]
    ev = spark.createDataFrame(rows, "event_id long, user_id long, event_type string, s long").select("event_id", F.timestamp_seconds("s").alias("ts"), "user_id", "event_type")
    for part in range(3):
        ev.where(f"event_id >= {part * 40} and event_id < {part * 40 + 40}").coalesce(1).write.mode("append").parquet(f"{tmp_path}/ev")
    got = windows.fold_edges(windows.run_to_table(windows.successors(windows.read_events(spark, f"{tmp_path}/ev")), "t"))
    from pyspark.sql.window import Window

    from glyphfold.sources.graphs import key_id

    key = key_id(F.concat_ws("@", "event_type", F.hour("ts").cast("string")))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    want = ev.select(key.alias("src"), "user_id", "ts", "event_id").withColumn("dst", F.lead("src").over(w)).where("dst is not null").groupBy("src", "dst").agg(F.count("*").alias("m"))
    assert edges(got) == edges(want)
    assert windows.dirty_nodes(got, got).count() == 0
    stream = windows.run_to_table(windows.window_counts(windows.read_events(spark, f"{tmp_path}/ev"), "1 day", watermark="0 seconds"), "w")
    assert 0 < stream.count() <= windows.window_counts(ev, "1 day").count()


def test_rounds_merge_all_twins(spark):
    """A large group of equal nodes ends as one super-node."""
    twins = [(i, h) for i in range(10, 40) for h in (1, 2, 3)]
    g = from_edges(spark.createDataFrame(twins, "src long, dst long"), directed=True)
    s = baselines.pairmerge_rounds(g)
    sizes = sorted(r.size for r in s.supernodes.collect())
    assert sizes[-1] == 30 and edges(summary.reconstruct(s)) == edges(g.edges)
