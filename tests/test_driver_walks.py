"""Pair merging and the structure vocabulary as loops in the JVM: results are those of plain code, and thousands of steps take seconds."""

import math
import random
import time

import numpy as np
import pytest

from glyphfold.operators import baselines
from glyphfold.sources.graphs import from_edges


def blocks(spark, rng, n):
    p, size = rng.choice([0.03, 0.1, 0.5]), rng.choice([3, 5, 8])
    pairs = {(7 * a, 7 * b) for a in range(n) for b in range(a + 1, n) if rng.random() < (0.85 if a // size == b // size else p * (a + b & 1))}
    chain = {(7 * n + i, 7 * n + i + 1) for i in range(rng.choice([0, 4]))}
    return from_edges(spark.createDataFrame(sorted(pairs | chain | {(1, 2)}), "src long, dst long"), directed=False)


def hub_sets(adj, hubs):
    """Stars of the largest hubs and the pieces that fall off, by searching all that is left after every step."""
    live, piece, out = {u: set(x) for u, x in adj.items()}, set(adj), []
    while len(piece) >= 3:
        top = sorted(piece, key=lambda u: (-len(live[u]), u))[:hubs]
        if len(live[top[0]]) < 2:
            break
        for h in top:
            out.append(sorted({h, *live[h]}))
            for w in live.pop(h):
                live[w].discard(h)
            piece.discard(h)
        parts, left = [], set(piece)
        while left:
            part, todo = set(), [min(left)]
            while todo:
                x = todo.pop()
                if x not in part:
                    part.add(x)
                    todo += live[x]
            parts.append(sorted(part))
            left -= part
        parts.sort(key=lambda c: (-len(c), c[0]))
        out += parts[1:]
        piece = set(parts[0]) if parts else set()
    return [c for c in out if len(c) >= 3]


def neighbours(g):
    e = [(r.src, r.dst) for r in g.edges.where("src <> dst").collect()]
    number = {u: i for i, u in enumerate(sorted({x for pair in e for x in pair}))}
    adj = {i: set() for i in number.values()}
    for a, b in e:
        adj[number[a]].add(number[b])
        adj[number[b]].add(number[a])
    return adj


def claimed(sets, s, kind):
    part = lambda what: sets.part(s, what).tolist()
    if kind == "chain":
        x = part("path")
        return {frozenset(p) for p in zip(x, x[1:], strict=False)}
    if kind == "star":
        return {frozenset((part("hub")[0], y)) for y in part("all")} - {frozenset(part("hub"))}
    if kind.endswith("clique"):
        return {frozenset((x, y)) for x in part("all") for y in part("all") if x < y}
    return {frozenset((x, y)) for x in part("left") for y in part("right")}


def test_vocabulary_is_that_of_plain_sets(spark):
    rng = random.Random(8)
    for n in (9, 20, 40, 40):
        g = blocks(spark, rng, n)
        adj = neighbours(g)
        edges = {frozenset((u, w)) for u, x in adj.items() for w in x}
        for hubs in (1, 3):
            sets = baselines.Peeled(g, hubs)
            assert [sets.part(s, "all").tolist() for s in range(sets.sets)] == hub_sets(adj, hubs)
        for s, (size, inner, hub, path, left, right, across) in enumerate(sets.counts()):
            own = {k: claimed(sets, s, k) for k in ("clique", "star", "chain", "bipartite")}
            real = {k: len(x & edges) for k, x in own.items()}
            assert (len(own["clique"]), real["clique"], real["star"], len(own["chain"]), real["chain"]) == (size * (size - 1) // 2, inner, hub, path - 1, path - 1)
            assert (len(own["bipartite"]), real["bipartite"]) == (left * right, across)
            for kind in ("clique", "near_clique", "star", "chain", "bipartite", "near_bipartite"):
                want = {tuple(sorted(x)) for x in own[kind.removeprefix("near_")]}
                at, none = sets.claims(s, kind)
                got = [tuple(map(int, divmod(x, sets.v))) for x in sets.pairs[at].tolist() + ([] if kind.startswith("near_") else none.tolist())]
                assert len(got) == len(set(got)) and set(got) == (want & {tuple(sorted(x)) for x in edges} if kind.startswith("near_") else want)
        for select in ("plain", "greedy_forget"):
            assert_bits(g, adj, edges, select)


def assert_bits(g, adj, edges, select):
    """The total of the chosen structures, from sets of pairs."""
    words, sets, v = baselines.vocab_summary(g, select), baselines.Peeled(g), g.nodes.count()
    slots = v * (v - 1) / 2
    error = lambda cells: 2 * math.log2(slots + 1) + baselines._entropy(slots, len(cells - edges)) + baselines._entropy(slots, len(edges) - len(cells & edges))
    scored = []
    for s, own in enumerate(sets.counts()):
        bits, kind, *_ = baselines.label_structure(*own, v)
        cells = claimed(sets, s, kind.removeprefix("near_"))
        cells = cells & edges if kind.startswith("near_") else cells
        scored.append((error(set()) - bits - math.log2(6) - error(cells), own[0], bits, cells))
    total, cells, model, n = error(set()), set(), 0.0, 0
    for _, _, bits, own in sorted(scored, key=lambda w: (-round(w[0], 9), w[1])):
        after = model + bits + math.log2(6) + error(cells | own) + baselines.n_int_bits(n + 1)
        if select == "plain" or after < total:
            total, cells, model, n = after, cells | own, model + bits + math.log2(6), n + 1
    assert len(words) == n and words.attrs["bits"] == pytest.approx(total)


def random_graph(spark, left, right, each):
    rng = np.random.default_rng(3)
    pairs = {(u, left + int(w)) for u in range(left) for w in rng.choice(right, each, replace=False)}
    return from_edges(spark.createDataFrame(sorted(pairs), "src long, dst long"), directed=False)


def test_thousands_of_hubs(spark):
    """Before, every hub taken out cost a search of all that was left: this graph took minutes."""
    g = random_graph(spark, 8000, 8000, 8)
    began = time.time()
    words = baselines.vocab_summary(g, "top10")
    assert len(words) == 10 and time.time() - began < 20


def test_thousands_of_merges(spark):
    """Before, a step took milliseconds, most of them to start array operations."""
    g = random_graph(spark, 15000, 1000, 25)
    began = time.time()
    s = baselines.pairmerge_randomized(g)
    assert time.time() - began < 15
    assert s.supernodes.count() < 10000
