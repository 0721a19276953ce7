"""What several resolutions share, pair merging in arrays, and nodes told by written edges."""

import random
from dataclasses import replace

import pytest

from glyphfold.operators import baselines, merge, synth
from glyphfold.plans import workloads
from glyphfold.sources import graphs


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


@pytest.mark.parametrize("nested", [False, True])
def test_resolutions_walk_what_they_share_once(spark, monkeypatch, nested):
    g = synth.synth_planted(spark, "biclique", 12, 5, context=6)
    cfg, bs, calls = merge.SummaryConfig(nested=nested), (1, 2, 5, 10), [0]
    apart = {b: merge.summarize(g, replace(cfg, b=b), merge.candidates_of(g, cfg, 10)) for b in bs}
    judge = merge.Walk.judge
    monkeypatch.setattr(merge.Walk, "judge", lambda self, nodes: calls.__setitem__(0, calls[0] + 1) or judge(self, nodes))
    together = merge.resolutions(g, bs, cfg)
    shared, calls[0] = calls[0], 0
    for b in bs:
        merge.summarize(g, replace(cfg, b=b), merge.candidates_of(g, cfg, 10))
    assert 0 < shared < calls[0]
    assert list(together) == list(bs)
    for b in bs:
        for part in ("supernodes", "members", "superedges"):
            assert rows(getattr(together[b], part)) == rows(getattr(apart[b], part))


def one_by_one(g, seed):
    """Randomized pair merging by weighing every partner within two hops."""
    p, rng = baselines.Pairs(g), random.Random(seed)
    still = sorted(p.members)
    rng.shuffle(still)
    while still:
        u = still[-1]
        best = max(((p.saving(u, v), -v) for v in p.two_hops(u)), default=(0.0, 0)) if u in p.members else (0.0, 0)
        if best[0] > 1e-12:
            baselines._merge_pairs(p, u, -best[1])
            at = rng.randrange(len(still))
            still[-1], still[at] = still[at], still[-1]
        else:
            still.pop()
    return baselines.pair_summary(g, p)


@pytest.mark.parametrize("directed", [True, False])
def test_pair_merging_in_arrays_is_that_of_all_partners(spark, directed):
    rng = random.Random(5)
    edges = {(a, b) for a in range(40) for b in range(40) if (directed or a <= b) and rng.random() < (0.7 if a // 8 == b // 8 else 0.05)}
    nodes = spark.createDataFrame([(u, "ab"[u % 2] if u % 8 else None) for u in range(40)], "id long, label string")
    g = graphs.from_edges(spark.createDataFrame(sorted(edges), "src long, dst long"), nodes, directed)
    for seed in (1, 2):
        got, want = baselines.pairmerge_randomized(g, seed), one_by_one(g, seed)
        for part in ("supernodes", "members", "superedges"):
            assert rows(getattr(got, part)) == rows(getattr(want, part))
        assert got.supernodes.count() < 40


@pytest.mark.parametrize("name", ["vote_sim", "cust_supp", "part_copurchase", "doc_cites"])
def test_nodes_come_from_the_written_edges(spark, name):
    d = "/root/testdata/sf0.001"
    plain, built = graphs.BUILDERS[name](spark, d), workloads.built(spark, d, name)
    assert rows(built.nodes) == rows(plain.nodes)
    assert rows(plain.nodes_of(built.edges.limit(0))) == []
