import random

import pytest

from glyphfold.operators import candidates as cd
from glyphfold.operators import similarity
from glyphfold.sources.graphs import cosine_pairs, from_edges


def copied(spark, seed, directed=True, groups=12, copies=3):
    """A random graph whose nodes come in groups of equal neighbourhoods."""
    random.seed(seed)
    rows = [(g * copies + i, 1000 + t) for g in range(groups) for t in random.sample(range(14), random.choice([3, 4, 9])) for i in range(random.choice([1, copies]))]
    return from_edges(spark.createDataFrame(rows, "src long, dst long"), directed=directed)


@pytest.mark.parametrize("sizes", [(6, 10_000, 4_000_000), (2, 10_000, 9), (2, 5, 40)])
def test_alike_pairs_are_those_of_all_pairs(spark, monkeypatch, sizes):
    """Short lists, blocks and hubs find what comparing all pairs finds, at any bound between them."""
    for name, value in zip(("SHORT_CLASS", "LONG_LIST", "BLOCK_TOKENS"), sizes, strict=True):
        monkeypatch.setattr(similarity, name, value)
    monkeypatch.setattr(similarity, "COUNT_CELLS", 30)
    for directed, t in ((True, 0.2), (False, 0.45)):
        g = copied(spark, 11, directed)
        got = sorted((r.a, r.b, round(r.jd, 9)) for r in similarity.similar_pairs(g, t).collect())
        assert got and got == sorted((r.a, r.b, round(r.jd, 9)) for r in similarity.exact_simpairs(g, t).collect())


def test_cliques_of_groups_are_those_of_their_nodes(spark):
    random.seed(12)
    for _ in range(40):
        n = random.randint(3, 9)
        size = {u * 10: random.choice([1, 1, 2, 4]) for u in range(n)}
        links = [(a, b, round(random.random(), 3)) for a in size for b in size if a < b and random.random() < 0.6]
        nodes = {u: range(u, u + k) for u, k in size.items()}
        every = [(a, b, j) for x, y, j in links for a in nodes[x] for b in nodes[y]] + [(a, b, 1.0) for own in nodes.values() for a in own for b in own if a < b]
        had = {u: random.choice([1, 3]) for u in size if random.random() < 0.4}
        want = sorted(cd.emerge(every, {v: b for u, b in had.items() for v in nodes[u]}))
        weight = {u: k for u, k in size.items() if k > 1}
        assert sorted((sorted(v for u in c for v in nodes[u]), q) for c, q in cd.emerge(links, dict(had), weight)) == want
    alone = {u for u, k in size.items() if k > 1} - {u for x, y, _ in links for u in (x, y)}
    df, w = spark.createDataFrame(links, "a long, b long, jd double"), spark.createDataFrame(list(weight.items()), "id long, w long")
    for wide in (0, 10**6):
        got = sorted((sorted(v for u in r.ids for v in nodes[u]), r.quality) for r in cd.emerging_cliques(df, None, wide, w).collect())
        assert got == sorted(c for c in cd.emerge(every, {}) if c[0][0] // 10 * 10 not in alone)


def test_copies_are_not_paired(spark, monkeypatch):
    """600 leaves of one hub are one class: before, their 179700 pairs were verified one by one."""
    g = from_edges(spark.createDataFrame([(0, i) for i in range(1, 601)] + [(700, i) for i in range(590, 610)], "src long, dst long"))
    seen = []
    own = cd.alike_pairs
    monkeypatch.setattr(cd, "alike_pairs", lambda lists, t: seen.append(lists.select("id").distinct().count()) or own(lists, t))
    few = cd.candidate_sets(g, 2, 3, local_edges=0)
    want = cd.candidate_sets(g, 2, 3)
    assert seen and max(seen) <= 5
    assert few.pairs == want.pairs > 170_000
    assert {b: sorted(s) for b, s in few.sets.items()} == {b: sorted(s) for b, s in want.sets.items()}
    assert max(len(ids) for ids, _ in want.upto(3)) >= 589


def test_blocks_are_dealt_in_bounded_jobs(spark, monkeypatch):
    """Pairs of blocks are counted by many jobs, none of which deals out more tokens than the bound: the pairs are the same."""
    for name, value in (("SHORT_CLASS", 2), ("BLOCK_TOKENS", 20), ("DEALT_TOKENS", 120)):
        monkeypatch.setattr(similarity, name, value)
    names, own = [], similarity.settle
    monkeypatch.setattr(similarity, "settle", lambda df, name="t": names.append(name) or own(df, name))
    g = copied(spark, 13)
    got = sorted((r.a, r.b, round(r.jd, 9)) for r in similarity.similar_pairs(g, 0.2).collect())
    assert names.count("block_meetings") > 3
    assert got == sorted((r.a, r.b, round(r.jd, 9)) for r in similarity.exact_simpairs(g, 0.2).collect())


def test_blocks_of_vectors_grow_with_their_number(spark):
    """A vector is sent to every block: their number is bounded by the largest block, and the pairs are the same for any size."""
    random.seed(14)
    rows = [(i, [random.gauss(0, 1) for _ in range(4)]) for i in range(150)]
    v = spark.createDataFrame(rows, "id long, v array<double>")
    unit = lambda x: [y / sum(z * z for z in x) ** 0.5 for y in x]
    every = {i: unit(x) for i, x in rows}
    want = {(a, b) for a in every for b in every if a < b and sum(x * y for x, y in zip(every[a], every[b], strict=True)) > 0.5}
    for how in ({}, {"block": 10}, {"block": 10, "most": 11, "cells": 30}):
        got = [tuple(r) for r in cosine_pairs(v, "id", "v", 0.5, **how).collect()]
        assert len(got) == len(want) and set(got) == want
