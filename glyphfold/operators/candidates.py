"""Candidate sets: incremental minhash banding, verified pairs, emerging cliques.

Pairs are verified once, when banding first brings them together, and kept with the
number of bands from which their similarity passes the threshold (``entry_b``), so
all resolutions share one table of pairs.

Small graphs (at most ``local_edges`` edges, checked) run the same steps in arrays on
the driver; larger ones as DataFrames.
"""

from __future__ import annotations

import math
from collections import defaultdict
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from glyphfold.operators.components import connected_components
from glyphfold.operators.similarity import alike_pairs, degrees, jaccard_for, neighbor_tokens, token_classes, window_pairs
from glyphfold.session import discard, gathered, large, release, settle
from glyphfold.sources.graphs import PropertyGraph

#: Modulus of the ``affine31`` hash family, whose products fit a long, and the factor of its second step.
PRIME, SECOND = (1 << 31) - 1, 40_692


def affine(seed: int, row: int) -> tuple[int, int]:
    """Coefficients of one hash row: a token x goes to y = a x + c, then to SECOND y y + c.

    Without the square, rows order ids that lie close together alike, and some pairs of
    nodes meet far more rarely than their similarity says.
    """
    a = (seed * 1_103_515_245 + row * 40_503 * 2_654_435 + 12_345) % (PRIME - 1) + 1
    c = (seed * 69_069 + row * 362_437 + 1) % PRIME
    return a, c


def row_hash(tok: Column, seed: int, row: int, family: str = "affine31") -> Column:
    if family == "xx64":
        return F.xxhash64(F.lit(seed), F.lit(row), tok)
    a, c = affine(seed, row)
    y = (F.pmod(tok, F.lit(PRIME).cast("long")) * F.lit(a).cast("long") + c) % PRIME
    return ((y * y) % PRIME * SECOND + c) % PRIME


def minhash(g: PropertyGraph, r: int, bands: int, family: str = "affine31", seed: int = 42, mode: str = "directed") -> DataFrame:
    """``(id, d, h_0 ...)``: r * bands minima over the neighbour tokens, in one aggregate."""
    return signatures(neighbor_tokens(g, mode), r, bands, family, seed)


def signatures(tok: DataFrame, r: int, bands: int, family: str = "affine31", seed: int = 42) -> DataFrame:
    return tok.groupBy("id").agg(F.count("*").alias("d"), *(F.min(row_hash(F.col("tok"), seed, i, family)).alias(f"h_{i}") for i in range(r * bands)))


def buckets(sig: DataFrame, r: int, band: int) -> DataFrame:
    """``(key, id)`` of one band, without buckets of one node."""
    key = F.concat_ws("-", *(F.col(f"h_{i}").cast("string") for i in range(r * band, r * band + r)))
    rows = sig.select(key.alias("key"), "id")
    many = rows.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key")
    return rows.join(many, "key")


def bucket_links(rows: DataFrame) -> DataFrame:
    """Star edges that join each bucket."""
    low = rows.groupBy("key").agg(F.min("id").alias("dst"))
    return rows.join(low, "key").select(F.col("id").alias("src"), "dst").where("src <> dst")


def grow_clusters(clusters: DataFrame | None, rows: DataFrame) -> DataFrame:
    """``(id, cluster)`` after one more band: overlapping buckets and clusters coalesce."""
    links = bucket_links(rows)
    if clusters is not None:
        links = links.unionByName(clusters.where("id <> cluster").select(F.col("id").alias("src"), F.col("cluster").alias("dst")))
    return connected_components(links).select("id", F.col("root").alias("cluster"))


def lsh_clusters(sig: DataFrame, r: int, b: int) -> DataFrame:
    """Plain banding at a fixed number of bands, from scratch."""
    links = None
    for band in range(b):
        own = bucket_links(buckets(sig, r, band))
        links = own if links is None else links.unionByName(own)
    return connected_components(links).select("id", F.col("root").alias("cluster"))


def entry_band(jd: Column, r: int) -> Column:
    """First number of bands whose threshold a similarity passes."""
    return F.ceil(F.pow(jd, F.lit(-float(r))) - 1e-9).cast("int")


def threshold(r: int, b: int) -> float:
    return (1 / b) ** (1 / r)


def large_pairs(nodes: DataFrame, tokens: DataFrame, t_min: float) -> DataFrame:
    """``(a, b, jd)``: all pairs of one cluster at ``t_min`` or more, without a table of all its pairs.

    Equal neighbourhoods are folded, others meet by ``alike_pairs``. nodes has (cluster, id).
    """
    own = settle(tokens.join(nodes, "id").select("cluster", "id", "tok"), "cluster_tokens")
    folded = settle(token_classes(own, ("cluster",)), "folded")
    reps = folded.where("id = rep").select("cluster", "id", "d")
    alike = alike_pairs(settle(own.join(reps, ["cluster", "id"]).select("cluster", "id", "tok", "d"), "fold_tokens"), t_min)
    same = folded.where("id = rep").select("cluster", F.col("rep").alias("a"), F.col("rep").alias("b"), F.lit(1.0).alias("jd"))
    u, v = folded.select("cluster", F.col("rep").alias("a"), F.col("id").alias("u")), folded.select("cluster", F.col("rep").alias("b"), F.col("id").alias("v"))
    out = alike.unionByName(same).join(u, ["cluster", "a"]).join(v, ["cluster", "b"]).where("a <> b or u < v")
    return out.select(F.least("u", "v").alias("a"), F.greatest("u", "v").alias("b"), "jd")


def verify_new_pairs(before: DataFrame | None, now: DataFrame, tokens: DataFrame, r: int, t_min: float, large: DataFrame | None = None) -> DataFrame:
    """``(a, b, jd, entry_b)`` of pairs that just came together and may reach t_min; large has the clusters not to be paired at once."""

    def fresh(pairs):
        if before is None:
            return pairs
        x, y = before.select(F.col("id").alias("a"), F.col("cluster").alias("ca")), before.select(F.col("id").alias("b"), F.col("cluster").alias("cb"))
        return pairs.join(x, "a", "left").join(y, "b", "left").where("ca is null or cb is null or ca <> cb")

    small = now if large is None else now.join(large, "cluster", "left_anti")
    out = jaccard_for(tokens, fresh(window_pairs(small.join(degrees(tokens), "id"), t_min))).where(F.col("jd") >= t_min - 1e-12)
    if large is not None:
        out = out.unionByName(fresh(large_pairs(now.join(large, "cluster", "left_semi"), tokens, t_min)).select("a", "b", "jd"))
    return out.withColumn("entry_b", entry_band(F.col("jd"), r))


def simgraph(simpairs: DataFrame, b: int) -> DataFrame:
    return simpairs.where(F.col("entry_b") <= b)


# cliques


def emerge(pairs: list[tuple[int, int, float]], best: dict[int, int], weight: dict[int, int] | None = None) -> list[tuple[list[int], float]]:
    """New maximal cliques of a similarity graph, greedily from each node's neighbourhood.

    ``best`` holds each node's largest clique so far and is updated; a node whose
    degree can't beat it is skipped. Neighbours are tried by degree, ids break ties.
    With ``weight`` a node stands for so many of equal neighbourhoods, itself the smallest:
    these are linked to each other and to the same others, so every clique that is taken
    holds all of them or none, and is the one found from them one by one.
    """
    w = (lambda u: weight.get(u, 1)) if weight else (lambda u: 1)
    adj: dict[int, dict[int, float]] = defaultdict(dict)
    for u in weight or ():
        adj[u] = {}
    for a, b, j in pairs:
        adj[a][b] = j
        adj[b][a] = j
    deg = {u: w(u) - 1 + (sum(map(w, near)) if weight else len(near)) for u, near in adj.items()}
    out = []
    order = sorted(adj, key=lambda u: (-deg[u], u))
    for u in order:
        if deg[u] + 1 <= best.get(u, 1):
            continue
        near = sorted(adj[u], key=lambda v: (-deg[v], v))
        clique, inside, size, left = [u], set(adj[u]), w(u), deg[u] + 1 - w(u)
        for v in near:
            if size + left <= best.get(u, 1):
                break
            if v in inside:
                clique.append(v)
                size += w(v)
                inside &= adj[v].keys()
                left = sum(map(w, inside)) if weight else len(inside)
        if size > best.get(u, 1):
            q = min((adj[x][y] for i, x in enumerate(clique) for y in clique[i + 1 :]), default=1.0)
            for v in clique:
                best[v] = max(best.get(v, 1), size)
            out.append((sorted(clique), q))
    return out


def maximal_cliques_exact(pairs: list[tuple[int, int]]) -> list[list[int]]:
    """All maximal cliques by recursion with pivots; for small components."""
    adj: dict[int, set[int]] = defaultdict(set)
    for a, b in pairs:
        adj[a].add(b)
        adj[b].add(a)
    out = []

    def go(r, p, x):
        if not p and not x:
            out.append(sorted(r))
            return
        pivot = max(p | x, key=lambda u: len(adj[u] & p))
        for v in sorted(p - adj[pivot]):
            go(r | {v}, p & adj[v], x & adj[v])
            p = p - {v}
            x = x | {v}

    go(set(), set(adj), set())
    return sorted(out)


#: Pairs of a similarity component above which its cliques are searched node by node.
WIDE_COMPONENT = 2_000_000


def emerging_cliques(pairs: DataFrame, best: DataFrame | None, wide: int = WIDE_COMPONENT, weights: DataFrame | None = None) -> DataFrame:
    """``(ids, size, quality)`` of new cliques: component by component, the largest ones node by node; results are equal.

    weights (id, w) says for how many nodes of equal neighbourhoods an id stands, as in ``emerge``; size counts them.
    """
    comp = connected_components(pairs, "a", "b").withColumnRenamed("root", "comp")
    rows = settle(pairs.select("a", "b", "jd").join(comp.withColumnRenamed("id", "a"), "a"), "clique_pairs")
    large = settle(rows.groupBy("comp").count().where(F.col("count") > wide).select("comp"), "wide_components")
    known = rows.select("comp", "a", "b", "jd")
    for df, name in ((best, "best"), (weights, "w")):
        for end in ("a", "b"):
            of = known.withColumn(f"{name}_{end}", F.lit(None).cast("int")) if df is None else known.join(df.select(F.col("id").alias(end), F.col(name).cast("int").alias(f"{name}_{end}")), end, "left")
            known = of
    cells = 16 * int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def own(df: pd.DataFrame) -> pd.DataFrame:
        """All components of one cell; they don't touch each other."""
        sizes, weight = {}, {}
        for name, into in (("best", sizes), ("w", weight)):
            for end in ("a", "b"):
                some = df[df[f"{name}_{end}"].notna()]
                into.update(zip(some[end].tolist(), some[f"{name}_{end}"].astype("int64").tolist(), strict=True))
        found = emerge(list(zip(df["a"].tolist(), df["b"].tolist(), df["jd"].tolist(), strict=True)), sizes, weight or None)
        return pd.DataFrame([(c, sum(weight.get(u, 1) for u in c), q) for c, q in found], columns=["ids", "size", "quality"])

    out = known.join(large, "comp", "left_anti").groupBy(F.pmod(F.xxhash64("comp"), F.lit(cells)).alias("cell")).applyInPandas(own, SETS)
    return out if large.isEmpty() else out.unionByName(cliques_by_node(rows.join(large, "comp", "left_semi").select("a", "b", "jd"), best, weights))


def cliques_by_node(pairs: DataFrame, best: DataFrame | None, weights: DataFrame | None = None) -> DataFrame:
    """What ``emerge`` finds, from the neighbourhood of each node alone.

    A node's greedy clique depends on its neighbours and the pairs among them only. The
    walk takes it if it is larger than all taken before it that hold the node, in the
    order of degrees; so a clique is taken once none of those is open, and dropped once
    one of them is taken.
    """
    both = pairs.select(F.col("a").alias("u"), F.col("b").alias("v"), "jd").unionByName(pairs.select(F.col("b").alias("u"), F.col("a").alias("v"), "jd"))
    one = F.lit(1).cast("long")
    weigh = lambda df, end: df.withColumn(f"w_{end}", one) if weights is None else df.join(weights.select(F.col("id").alias(end), F.col("w").cast("long").alias(f"w_{end}")), end, "left").withColumn(f"w_{end}", F.coalesce(f"w_{end}", one))
    both = settle(weigh(both, "v"), "clique_ends")
    deg = weigh(both.groupBy("u").agg(F.sum("w_v").alias("deg")), "u").withColumn("deg", F.col("deg") + F.col("w_u") - 1)
    if best is not None:
        deg = deg.join(best.select(F.col("id").alias("u"), "best"), "u", "left")
    deg = settle(deg.withColumn("best", F.coalesce("best", F.lit(1)) if best is not None else F.lit(1)), "clique_degrees")
    open_ = deg.where("deg + 1 > best")
    near = settle(both.join(open_.select("u"), "u", "left_semi").join(deg.select(F.col("u").alias("v"), F.col("deg").alias("d")), "v").select("u", "v", "d", "jd", "w_v"), "clique_neighbours")
    x, y = near.select("u", F.col("v").alias("a")), near.select("u", F.col("v").alias("b"))
    ties = pairs.join(x, "a").join(y, ["u", "b"]).select("u", F.col("a").alias("v"), F.col("b").alias("w"), F.lit(0).cast("long").alias("d"), "jd", one.alias("w_v"))
    rows = near.select("u", "v", F.lit(None).cast("long").alias("w"), "d", "jd", "w_v").unionByName(ties).join(open_, "u")

    def greedy(df: pd.DataFrame) -> pd.DataFrame:
        u, deg_, least, mine = (int(df[c].iloc[0]) for c in ("u", "deg", "best", "w_u"))
        own = df[df["w"].isna()]
        tied = df[df["w"].notna()]
        adj: dict[int, dict[int, float]] = defaultdict(dict)
        for a, b, j in zip(tied["v"].tolist(), tied["w"].astype("int64").tolist(), tied["jd"].tolist(), strict=True):
            adj[a][b] = adj[b][a] = j
        adj[u] = dict(zip(own["v"].tolist(), own["jd"].tolist(), strict=True))
        weight = dict(zip(own["v"].tolist(), own["w_v"].tolist(), strict=True))
        clique, inside, size, left = [u], set(adj[u]), mine, sum(weight.values())
        for v in own.sort_values(["d", "v"], ascending=[False, True])["v"].tolist():
            if size + left <= least:
                break
            if v in inside:
                clique.append(v)
                size += weight[v]
                inside &= adj[v].keys()
                left = sum(weight[x] for x in inside)
        if size <= least:
            return pd.DataFrame([], columns=["u", "deg", "ids", "size", "quality"])
        q = min((adj[x][y] for i, x in enumerate(clique) for y in clique[i + 1 :]), default=1.0)
        return pd.DataFrame({"u": [u], "deg": [deg_], "ids": [sorted(clique)], "size": [size], "quality": [q]})

    found = settle(rows.groupBy("u").applyInPandas(greedy, "u long, deg long, " + SETS), "node_cliques")
    holds = found.select(F.col("u").alias("by"), F.col("deg").alias("by_deg"), F.col("size").alias("by_size"), F.explode("ids").alias("u"))
    before = (F.col("by_deg") > F.col("deg")) | ((F.col("by_deg") == F.col("deg")) & (F.col("by") < F.col("u")))
    blocks = settle(found.select("u", "deg", "size").join(holds, "u").where(before & (F.col("by_size") >= F.col("size"))).select("u", "by"), "clique_blocks")
    open_nodes, taken = found.select("u"), None
    while True:
        free = settle(open_nodes.join(blocks.select("u"), "u", "left_anti"), "clique_free")  # the first open one is always among them
        taken = free if taken is None else taken.unionByName(free)
        lost = settle(blocks.join(free.select(F.col("u").alias("by")), "by", "left_semi").select("u").distinct(), "clique_lost")
        open_nodes = settle(open_nodes.join(free, "u", "left_anti").join(lost, "u", "left_anti"), "clique_open")
        if open_nodes.isEmpty():
            return found.join(taken, "u", "left_semi").select("ids", "size", "quality")
        blocks = settle(blocks.join(open_nodes, "u", "left_semi").join(lost.select(F.col("u").alias("by")), "by", "left_anti").select("u", "by"), "clique_blocks")


@dataclass
class Candidates:
    """New sets of each number of bands: as lists (``local``) or as tables (ids, size, quality) that stay distributed."""

    r: int
    local: dict[int, list[tuple[tuple[int, ...], float]]] = field(default_factory=dict)
    tables: dict[int, DataFrame] = field(default_factory=dict)
    pairs: int = 0
    capped: int = 0

    def of(self, b: int) -> list[tuple[tuple[int, ...], float]]:
        """The new sets of round b, collected if they are a table."""
        if b not in self.local and b in self.tables:
            self.local[b] = [(tuple(row.ids), row.quality) for row in self.tables[b].orderBy("size", "ids").collect()]
        return self.local.get(b, [])

    @property
    def sets(self) -> dict[int, list[tuple[tuple[int, ...], float]]]:
        return {b: self.of(b) for b in sorted(self.local.keys() | self.tables.keys())}

    def upto(self, b: int) -> list[tuple[tuple[int, ...], float]]:
        return [s for k, own in self.sets.items() if k <= b for s in own]

    def table(self, spark, b: int) -> DataFrame:
        """``(ids, size, quality)`` of all sets up to b; tables are not collected."""
        out = spark.createDataFrame([(list(ids), len(ids), q) for k, own in self.local.items() if k <= b and k not in self.tables for ids, q in own], SETS)
        for k, own in self.tables.items():
            if k <= b:
                out = out.unionByName(own.select("ids", "size", "quality"))
        return out


SETS = "ids array<long>, size int, quality double"


def candidate_sets(
    g: PropertyGraph, r: int = 2, b_max: int = 5, filtered: bool = True, seed: int = 42, family: str = "affine31", mode: str = "directed", max_cluster: int = 5000, local_edges: int = 2_000_000
) -> Candidates:
    """Candidate sets for every number of bands up to ``b_max``; both ways find the same sets."""
    if g.edges.limit(local_edges + 1).count() <= local_edges:
        tok = gathered(neighbor_tokens(g, mode))
        sig = None if family == "affine31" else gathered(minhash(g, r, b_max, family, seed, mode))
        return local_candidates(tok["id"].to_numpy(np.int64), tok["tok"].to_numpy(np.int64), r, b_max, filtered, seed, max_cluster, sig)
    return spark_candidates(g, r, b_max, filtered, seed, family, mode, max_cluster)


def local_candidates(ids: np.ndarray, tok: np.ndarray, r: int, b_max: int, filtered: bool = True, seed: int = 42, max_cluster: int = 5000, sig: pd.DataFrame | None = None) -> Candidates:
    """The rounds in arrays; ``sig`` has the signatures of another hash family than ``affine31``."""
    order = np.lexsort((tok, ids))
    ids, tok = ids[order], tok[order]
    nodes, start = np.unique(ids, return_index=True)
    ends = np.append(start[1:], len(ids))[: len(nodes)]
    lists = {int(u): tok[a:b] for u, a, b in zip(nodes, start, ends, strict=True)}
    out, best = Candidates(r), {}
    group: dict[int, list[int]] = {}
    if filtered:  # nodes of equal neighbourhoods always come together: the smallest stands for all
        first: dict[bytes, int] = {}
        for u, own in lists.items():
            group.setdefault(first.setdefault(own.tobytes(), u), []).append(u)
        some = np.isin(nodes, list(group))
        lists = {u: lists[u] for u in group}
        if sig is not None:
            sig = sig[sig["id"].isin(group)]
        keep = np.repeat(some, ends - start)
        ids, tok = ids[keep], tok[keep]
        nodes, start = np.unique(ids, return_index=True)
    weight = {u: len(own) for u, own in group.items() if len(own) > 1}
    size = lambda us: sum(weight.get(u, 1) for u in us)
    out.pairs = sum(n * (n - 1) // 2 for n in weight.values())
    out.capped = sum(n > max_cluster for n in weight.values())
    clusters: dict[int, list[int]] = {int(u): [int(u)] for u in nodes}
    home = {int(u): int(u) for u in nodes}
    entry: dict[int, list] = defaultdict(list)
    live: list[tuple[int, int, float]] = []
    t_min = threshold(r, b_max)
    reduced = tok % PRIME
    if sig is not None:
        sig = sig.sort_values("id")
    for b in range(1, b_max + 1):
        key = np.zeros((len(nodes), r), np.int64)
        for i in range(r):
            row = r * (b - 1) + i
            if sig is not None:
                key[:, i] = sig[f"h_{row}"].to_numpy(np.int64)
                continue
            a, c = affine(seed, row)
            y = (reduced * a + c) % PRIME
            key[:, i] = np.minimum.reduceat((y * y % PRIME * SECOND + c) % PRIME, start) if len(start) else 0
        _, bucket = np.unique(key, axis=0, return_inverse=True) if len(nodes) else (None, np.zeros(0, int))
        groups: dict[int, list[int]] = defaultdict(list)
        for u, k in zip(nodes.tolist(), bucket.ravel().tolist(), strict=True):
            groups[k].append(u)
        fused: dict[int, int] = {}

        def find(x):
            while fused.get(x, x) != x:  # noqa: B023
                x = fused[x]  # noqa: B023
            return x

        for own in groups.values():
            roots = sorted({find(home[u]) for u in own})
            for other in roots[1:]:
                fused[other] = roots[0]
        joins: dict[int, list[int]] = defaultdict(list)
        for c in clusters:
            joins[find(c)].append(c)
        for top, parts in joins.items():
            if len(parts) == 1:
                continue
            if filtered:
                new = new_pairs([clusters[p] for p in parts], lists, t_min)
                for x, y, j in new:
                    entry[max(b, math.ceil(j ** -r - 1e-9))].append((x, y, j))
                    out.pairs += size((x,)) * size((y,))
                out.capped += sum(size(clusters[p]) for p in parts) > max_cluster
            whole = sorted(u for p in parts for u in clusters[p])
            for p in parts:
                del clusters[p]
            clusters[top] = whole
            for u in whole:
                home[u] = top
        if filtered:
            fresh = entry.pop(b, [])
            live += fresh
            found = emerge(live, best, weight) if fresh or b == 1 else []
            out.local[b] = [(tuple(sorted(v for u in c for v in group[u])), q) for c, q in found]
        else:
            out.local[b] = [(tuple(m), threshold(r, b)) for t, m in sorted(clusters.items()) if len(joins[t]) > 1]
    return out


def new_pairs(parts: list[list[int]], lists: dict, t_min: float) -> list[tuple[int, int, float]]:
    """Exact similarities of pairs from different parts, at t_min or more; no two lists are equal."""
    nodes = sorted(((len(lists[u]), u, k) for k, part in enumerate(parts) for u in part))
    home = np.array([k for _, _, k in nodes])
    sets = [lists[u] for _, u, _ in nodes]
    # every new pair has an end outside the largest part
    small = home != max(range(len(parts)), key=lambda k: len(parts[k]))
    every, sizes = np.concatenate(sets), np.array([n for n, _, _ in nodes])
    words, code = np.unique(every, return_inverse=True)
    order = np.argsort(code, kind="stable")
    at = np.repeat(np.arange(len(sets)), sizes)[order]
    first = np.searchsorted(code[order], np.arange(len(words) + 1))
    ends = np.concatenate([[0], np.cumsum(sizes)])
    found = []
    for i in np.flatnonzero(small).tolist():
        met = np.concatenate([at[first[c] : first[c + 1]] for c in code[ends[i] : ends[i + 1]].tolist()])
        hit = np.bincount(met, minlength=len(sets)) if len(met) * 8 > len(sets) else None
        near, both = (np.flatnonzero(hit), hit[hit > 0]) if hit is not None else np.unique(met, return_counts=True)
        j = both / (sizes[i] + sizes[near] - both)
        fits = (j >= t_min - 1e-12) & (home[near] != home[i]) & ~(small[near] & (near < i))
        for o, q in zip(near[fits].tolist(), j[fits].tolist(), strict=True):
            u, v = nodes[i][1], nodes[o][1]
            found.append((min(u, v), max(u, v), q))
    return found


def spark_candidates(g: PropertyGraph, r: int, b_max: int, filtered: bool, seed: int, family: str, mode: str, max_cluster: int = 5000) -> Candidates:
    """The same rounds as DataFrames; each round's tables are written, its sets among them.

    Nodes of equal neighbourhoods always come together: the smallest stands for all, and is
    paired with others that share one of its clusters over rare tokens. Clusters of more than
    ``max_cluster`` nodes are counted as capped; none loses a pair.
    """
    tokens = settle(neighbor_tokens(g, mode), "tokens")
    out = Candidates(r)
    if not filtered:
        return spark_clusters(settle(signatures(tokens, r, b_max, family, seed), "signatures"), r, b_max, out)
    t_min = threshold(r, b_max)
    fold = settle(token_classes(tokens), "folded")
    weights = settle(fold.groupBy(F.col("rep").alias("id")).agg(F.count("*").alias("w")).where("w > 1"), "class_sizes")
    lists = settle(tokens.join(fold.where("id = rep").select("id", "d"), "id").select("id", "tok", "d"), "class_tokens")
    pause = large(tokens)
    discard(tokens)
    sig = settle(signatures(lists, r, b_max, family, seed), "signatures")
    if pause:
        release(g.edges.sparkSession)
    now, seen = None, None
    for b in range(1, b_max + 1):
        now = settle(grow_clusters(now, buckets(sig, r, b - 1)), "clusters")
        size = now.join(weights, "id", "full_outer").groupBy(F.coalesce("cluster", "id").alias("cluster")).agg(F.sum(F.coalesce("w", F.lit(1))).alias("n"))
        out.capped += size.where(F.col("n") > max_cluster).count()
        rows = now.select("id", "cluster", F.lit(b).alias("b"))
        seen = rows if seen is None else seen.unionByName(rows)
    homes = lambda end: history.select(F.col("id").alias(end), *(F.col(f"c{b}").alias(f"{end}{b}") for b in range(1, b_max + 1)))
    history = settle(seen.groupBy("id").agg(*(F.max(F.when(F.col("b") == b, F.col("cluster"))).alias(f"c{b}") for b in range(1, b_max + 1))), "cluster_history")
    lists, whole = settle(lists.join(now, "id").select("cluster", "id", "tok", "d"), "cluster_tokens"), lists
    discard(whole)
    alike = settle(alike_pairs(lists, t_min).select("a", "b", "jd"), "alike")
    discard(lists)
    if pause:
        release(g.edges.sparkSession)
    met = F.coalesce(*(F.when(F.col(f"a{b}") == F.col(f"b{b}"), b) for b in range(1, b_max + 1)))
    pairs = settle(alike.join(homes("a"), "a").join(homes("b"), "b").select("a", "b", "jd", F.greatest(entry_band(F.col("jd"), r), met).alias("entry_b")), "simpairs")
    of = lambda end: weights.select(F.col("id").alias(end), F.col("w").alias(f"w_{end}"))
    linked = pairs.join(of("a"), "a", "left").join(of("b"), "b", "left").agg(F.sum(F.coalesce("w_a", F.lit(1)) * F.coalesce("w_b", F.lit(1))).alias("n")).first().n or 0
    out.pairs = linked + (weights.agg(F.sum(F.expr("w * (w - 1) div 2")).alias("n")).first().n or 0)
    fresh = {row.entry_b for row in pairs.select("entry_b").distinct().collect()}
    best = None
    for b in range(1, b_max + 1):
        live = simgraph(pairs, b)
        found = emerging_cliques(live, best, weights=weights) if b in fresh else g.edges.sparkSession.createDataFrame([], SETS)
        if b == 1:  # groups that nothing else is linked to
            tied = live.select(F.col("a").alias("id")).union(live.select("b"))
            found = found.unionByName(weights.join(tied, "id", "left_anti").select(F.array("id").alias("ids"), F.col("w").cast("int").alias("size"), F.lit(1.0).alias("quality")))
        found = settle(found.withColumn("cid", F.monotonically_increasing_id()), "class_cliques")
        sizes = found.select(F.explode("ids").alias("id"), F.col("size").alias("best"))
        best = settle((sizes if best is None else best.unionByName(sizes)).groupBy("id").agg(F.max("best").alias("best")), "best")
        ids = found.select("cid", F.explode("ids").alias("rep")).join(fold.select("rep", "id"), "rep").groupBy("cid").agg(F.array_sort(F.collect_list("id")).alias("ids"))
        out.tables[b] = settle(found.drop("ids").join(ids, "cid").select("ids", "size", "quality"), "cliques")
    return out


def spark_clusters(sig: DataFrame, r: int, b_max: int, out: Candidates) -> Candidates:
    """Clusters that are new or have grown, as candidate sets of each round."""
    clusters = None
    for b in range(1, b_max + 1):
        now = settle(grow_clusters(clusters, buckets(sig, r, b - 1)), "clusters")
        sets = now.groupBy("cluster").agg(F.array_sort(F.collect_list("id")).alias("ids")).where(F.size("ids") > 1)
        if clusters is not None:
            old = clusters.groupBy("cluster").agg(F.count("*").alias("n"))
            sets = sets.join(old, "cluster", "left").where("n is null or n < size(ids)")
        out.tables[b] = settle(sets.select("ids", F.size("ids").alias("size"), F.lit(threshold(r, b)).alias("quality")), "cluster_sets")
        clusters = now
    return out
