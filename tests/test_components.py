import random

from glyphfold.operators import components


def brute(edges):
    near = {}
    for u, v in edges:
        if u is not None and v is not None and u != v:
            near.setdefault(u, set()).add(v)
            near.setdefault(v, set()).add(u)
    root = {}
    for i in sorted(near):
        todo = [i] if i not in root else []
        while todo:
            a = todo.pop()
            if a not in root:
                root[a] = i
                todo += near[a]
    return root


def test_both_ways_give_the_smallest_id(spark, monkeypatch):
    """One task and rounds of contraction agree with a walk: chains, hubs, repeats, loops and nulls."""
    random.seed(1)
    edges = [(i, i + 1) for i in range(100, 160)] + [(7, i) for i in range(200, 260)] + [(random.randrange(300, 400), random.randrange(300, 400)) for _ in range(60)]
    edges += [(5, 5), (None, 3), (3, None), (9, 8), (9, 8), (-4, 10**17)]
    df = spark.createDataFrame(edges, "src long, dst long").repartition(3)
    for most in (10**6, 0):
        monkeypatch.setattr(components, "FOLDED_EDGES", most)
        assert {r.id: r.root for r in components.connected_components(df).collect()} == brute(edges)
        assert components.connected_components(df.limit(0)).count() == 0
