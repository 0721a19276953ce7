"""Other ways to summarise: pairwise merging, a structure vocabulary, fixed groupings."""

from __future__ import annotations

import heapq
import math
import random
from collections import Counter, defaultdict
from collections.abc import Iterator
from functools import cache, reduce
from operator import and_

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from glyphfold.functions.bits import channel_bits, diff_bits, int_bits, n_int_bits, n_log2_binomial
from glyphfold.operators.compiled import chunks, java_object, packed, unpacked
from glyphfold.operators.merge import as_summary, column_summary, decide_glyph, rep_exact_sql
from glyphfold.operators.ordering import node_draw, numbered
from glyphfold.operators.similarity import neighbor_tokens
from glyphfold.operators.summary import STARS, Summary, corrections
from glyphfold.session import gathered, settle
from glyphfold.sources.graphs import PropertyGraph

# pairwise merging -------------------------------------------------------------------

#: Nodes whose super-edges are read from a walk at once.
PLACES_READ = 1 << 14


class Pairs:
    """Super-nodes with counts of edges between them; multiplicities are ignored."""

    def __init__(self, g: PropertyGraph):
        n, e = g.nodes.toPandas(), g.edges.toPandas()
        self.directed = g.directed
        self.label = dict(zip(n["id"].tolist(), n["label"].tolist(), strict=True))
        self.members = {u: [u] for u in self.label}
        self.out: dict[int, Counter] = defaultdict(Counter)
        self.into: dict[int, Counter] = defaultdict(Counter)
        self.loops: Counter = Counter()
        for u, v in zip(e["src"].tolist(), e["dst"].tolist(), strict=True):
            if u == v:
                self.loops[u] += 1
                continue
            self.out[u][v] += 1
            self.into[v][u] += 1
            if not g.directed:
                self.out[v][u] += 1
                self.into[u][v] += 1

    def cost(self, u: int) -> float:
        n = len(self.members[u])
        total = min(self.loops[u], n - self.loops[u] + 1) if self.loops[u] else 0
        for side in (self.out[u], self.into[u]) if self.directed else (self.out[u],):
            for z, c in side.items():
                if z != u:
                    total += min(c, n * len(self.members[z]) - c + 1)
        c = self.out[u][u] if u in self.out[u] else 0
        return total + (min(c, n * (n - 1) - c + 1) if c else 0)

    def cost_merged(self, u: int, v: int) -> float:
        n = len(self.members[u]) + len(self.members[v])
        k = self.loops[u] + self.loops[v]
        total = min(k, n - k + 1) if k else 0
        for a, b in ((self.out[u], self.out[v]), (self.into[u], self.into[v])) if self.directed else ((self.out[u], self.out[v]),):
            for z in a.keys() | b.keys():
                if z not in (u, v):
                    c = a[z] + b[z]
                    total += min(c, n * len(self.members[z]) - c + 1) if c else 0
        c = self.out[u][v] + self.out[v][u] + self.out[u][u] + self.out[v][v]
        return total + (min(c, n * (n - 1) - c + 1) if c else 0)

    def saving(self, u: int, v: int) -> float:
        both = self.cost(u) + self.cost(v)
        return (both - self.cost_merged(u, v)) / both if both else 0.0

    def two_hops(self, u: int) -> set[int]:
        near = (self.out[u].keys() | self.into[u].keys()) - {u}
        far = set(near)
        for z in near:
            far |= self.out[z].keys() | self.into[z].keys()
        return {v for v in far if v != u and self.label[v] == self.label[u]}

    def merge(self, u: int, v: int) -> None:
        for side, back in ((self.out, self.into), (self.into, self.out)):
            for z, c in list(side[v].items()):
                del back[z][v]
                t = u if z == v else z
                side[u][t] += c
                back[t][u] += c
            side.pop(v)
        # edges between the two are now inside
        self.loops[u] += self.loops.pop(v, 0)
        self.members[u] += self.members.pop(v)


def _merge_pairs(p: Pairs, u: int, v: int) -> None:
    inside = p.out[u][u] + p.out[v][v] + p.out[u][v] + p.out[v][u]
    for x in (u, v):
        for y in (u, v):
            p.out[x].pop(y, None)
            p.into[x].pop(y, None)
    p.merge(u, v)
    if inside:
        p.out[u][u] = inside
        p.into[u][u] = inside


def pairmerge_randomized(g: PropertyGraph, seed: int = 42) -> Summary:
    """A random open node merges with its best same-label partner within two hops, or closes.

    Every step depends on the last one, so the walk is one loop, in the driver's JVM (``PairWalk``).
    """
    n, e = gathered(g.nodes).sort_values("id"), gathered(g.edges.select("src", "dst"))
    ids = n["id"].to_numpy(np.int64)
    src, dst = (np.searchsorted(ids, e[c].to_numpy(np.int64)).astype(np.int32) for c in ("src", "dst"))
    rng = random.Random(seed)
    still = list(range(len(ids)))
    rng.shuffle(still)
    walk = java_object(g.edges.sparkSession, "PairWalk", len(ids), g.directed, packed(pd.factorize(n["label"], use_na_sentinel=False)[0]), packed(np.array(still, np.int32)))
    for part in chunks(src, dst):
        walk.add(part)
    walk.ready()
    while not walk.walk(bytearray(rng.randbytes(1 << 18))):
        pass
    return walked_summary(g, ids, n["label"].to_numpy(object), walk)


def pairmerge_greedy(g: PropertyGraph) -> Summary:
    """The best of all two-hop pairs first, by a heap; for small graphs."""
    p = Pairs(g)
    heap = [(-s, u, v) for u in p.members for v in p.two_hops(u) if u < v and (s := p.saving(u, v)) > 1e-12]
    heapq.heapify(heap)
    while heap:
        s, u, v = heapq.heappop(heap)
        if u not in p.members or v not in p.members:
            continue
        now = p.saving(u, v)
        if now <= 1e-12:
            continue
        if -s > now + 1e-12:
            heapq.heappush(heap, (-now, u, v))
            continue
        _merge_pairs(p, u, v)
        for w in p.two_hops(u):
            if (s2 := p.saving(u, w)) > 1e-12:
                heapq.heappush(heap, (-s2, min(u, w), max(u, w)))
    return pair_summary(g, p)


def pairmerge_rounds(g: PropertyGraph, max_rounds: int | None = None) -> Summary:
    """Parallel form: in each round nodes that choose each other merge, until no pair saves anything.

    Ties go by a hash of the pair that changes with the round, so that many pairs of
    equal nodes merge at once; the best pair of all is always mutual, so every round
    merges one at least. ``max_rounds`` stops earlier.
    """
    spark = g.edges.sparkSession
    e = settle((g.edges if g.directed else g.mirrored()).select("src", "dst"), "pm_edges")
    mem = settle(g.nodes.select("id", F.col("id").alias("sid"), "label"), "pm_members")
    bound = g.nodes.count() + 1
    for round_ in range(bound if max_rounds is None else max_rounds):
        s = mem.select(F.col("id").alias("src"), F.col("sid").alias("a")), mem.select(F.col("id").alias("dst"), F.col("sid").alias("b"))
        links = settle(e.join(s[0], "src").join(s[1], "dst").groupBy("a", "b").agg(F.count("*").alias("c"), F.count_if(F.col("src") != F.col("dst")).alias("pairs")), "pm_links")
        size = mem.groupBy(F.col("sid")).agg(F.count("*").alias("n"), F.min("label").alias("label"))
        n = lambda x: size.select(F.col("sid").alias(x), F.col("n").alias(f"n_{x}"))
        slot = lambda c, k: F.least(c, k - c + 1)
        # rows (x, way, z, c, n): what each super-node sees
        seen = links.where("a <> b").select(F.col("a").alias("x"), F.lit(0).alias("way"), F.col("b").alias("z"), "c").union(links.where("a <> b").select("b", F.lit(1), "a", "c"))
        seen = settle(seen.join(n("z"), "z").join(n("x"), "x"), "pm_seen")
        inner = links.where("a = b and pairs > 0").select(F.col("a").alias("x"), F.col("pairs").alias("c")).join(n("x"), "x").select("x", slot(F.col("c"), F.col("n_x") * (F.col("n_x") - 1)).alias("k"))
        cost = seen.select("x", slot(F.col("c"), F.col("n_x") * F.col("n_z")).alias("k")).unionByName(inner).groupBy("x").agg(F.sum("k").alias("cost"))
        pair = seen.select("z", "way", F.col("x").alias("u"), F.col("c").alias("cu"), F.col("n_x").alias("nu"), "n_z").join(seen.select("z", "way", F.col("x").alias("v"), F.col("c").alias("cv"), F.col("n_x").alias("nv")), ["z", "way"]).where("u < v")
        # shared neighbours: what merging saves over two separate slots
        gain = pair.select("u", "v", (slot(F.col("cu"), F.col("nu") * F.col("n_z")) + slot(F.col("cv"), F.col("nv") * F.col("n_z")) - slot(F.col("cu") + F.col("cv"), (F.col("nu") + F.col("nv")) * F.col("n_z"))).alias("g"))
        # the whole cost of the merged node decides: slots of all neighbours, the inside and loops
        lab = lambda x: size.select(F.col("sid").alias(x), F.col("label").alias(f"l_{x}"), F.col("n").alias(f"m_{x}"))
        c = lambda x: cost.select(F.col("x").alias(x), F.col("cost").alias(f"c_{x}"))
        k = lambda x: loops.select(F.col("x").alias(x), F.col("k").alias(f"k_{x}"))
        loops = e.where("src = dst").join(s[0], "src").groupBy(F.col("a").alias("x")).agg(F.count("*").alias("k"))
        looped = lambda k, n: F.when(k > 0, slot(k, n)).otherwise(0)
        score = gain.where("g > 0").select("u", "v").distinct().join(lab("u"), "u").join(lab("v"), "v").where("l_u = l_v")
        score = settle(score.join(c("u"), "u").join(c("v"), "v").join(k("u"), "u", "left").join(k("v"), "v", "left").na.fill(0, ["k_u", "k_v"]), "pm_candidates")
        each = score.select("u", "v", (F.col("m_u") + F.col("m_v")).alias("n"), F.explode(F.array("u", "v")).alias("x"))
        outer = each.join(seen.select("x", "z", "way", "c", "n_z"), "x").where("z <> u and z <> v").groupBy("u", "v", "n", "z", "way", "n_z").agg(F.sum("c").alias("c"))
        outer = outer.groupBy("u", "v").agg(F.sum(slot(F.col("c"), F.col("n") * F.col("n_z"))).alias("outer"))
        inside = each.join(links.where("pairs > 0").select(F.col("a").alias("x"), "b", F.col("pairs").alias("c")), "x").where("b = u or b = v").groupBy("u", "v", "n").agg(F.sum("c").alias("c"))
        inside = inside.select("u", "v", slot(F.col("c"), F.col("n") * (F.col("n") - 1)).alias("inside"))
        now = F.col("c_u") + F.col("c_v") + looped(F.col("k_u"), F.col("m_u")) + looped(F.col("k_v"), F.col("m_v"))
        then = F.coalesce("outer", F.lit(0)) + F.coalesce("inside", F.lit(0)) + looped(F.col("k_u") + F.col("k_v"), F.col("m_u") + F.col("m_v"))
        score = score.join(outer, ["u", "v"], "left").join(inside, ["u", "v"], "left").select("u", "v", ((now - then) / now).alias("s")).where("s > 1e-12")
        score = settle(score, "pm_score")
        w = Window.partitionBy("x").orderBy(F.desc("s"), "tie", "y")
        score = score.withColumn("tie", F.xxhash64("u", "v", F.lit(round_)))
        both = score.select(F.col("u").alias("x"), F.col("v").alias("y"), "s", "tie").union(score.select("v", "u", "s", "tie"))
        best = both.withColumn("r", F.row_number().over(w)).where("r = 1").select("x", "y")
        mutual = settle(best.join(best.select(F.col("x").alias("y"), F.col("y").alias("x")), ["x", "y"]).where("x < y"), "pm_mutual")
        if mutual.isEmpty():
            break
        mem = settle(mem.join(mutual.select(F.col("y").alias("sid"), F.col("x").alias("to")), "sid", "left").select("id", F.coalesce("to", "sid").alias("sid"), "label"), "pm_members")
    else:
        if max_rounds is None:
            raise RuntimeError("pairs did not settle")
    return pair_tables(g, mem)


def pair_tables(g: PropertyGraph, mem: DataFrame) -> Summary:
    """As ``pair_summary``, from a table of members (id, sid, label)."""
    e = (g.edges if g.directed else g.mirrored()).select("src", "dst")
    a, b = mem.select(F.col("id").alias("src"), F.col("sid").alias("a")), mem.select(F.col("id").alias("dst"), F.col("sid").alias("b"))
    links = settle(e.join(a, "src").join(b, "dst").groupBy("a", "b").agg(F.count_if(F.col("src") != F.col("dst")).alias("c"), F.count_if(F.col("src") == F.col("dst")).alias("k")), "pm_links")
    size = mem.groupBy("sid").agg(F.min("label").alias("label"), F.count("*").alias("size"))
    inside = links.where("a = b").select(F.col("a").alias("sid"), "c", "k")
    sn = size.join(inside, "sid", "left").na.fill(0, ["c", "k"])
    n = F.col("size")
    full = (F.col("c") > 0) & (n * (n - 1) - F.col("c") + 1 <= F.col("c"))
    looped = F.when((F.col("k") > 0) & (n - F.col("k") + 1 <= F.col("k")), F.lit(1).cast("long"))
    glyph = F.when(full, "clique").otherwise("disconnected")
    sn = settle(sn.select("sid", "label", "size", glyph.alias("glyph"), F.lit(1).cast("long").alias("m"), F.lit(None).cast("long").alias("hub"), looped.alias("self_m")), "pm_sn")
    of = lambda x: size.select(F.col("sid").alias(x), F.col("size").alias(f"n_{x}"))
    outer = links.where("a <> b" if g.directed else "a < b").join(of("a"), "a").join(of("b"), "b")
    kept = outer.where((F.col("c") > 0) & (F.col("n_a") * F.col("n_b") - F.col("c") + 1 <= F.col("c")))
    se = kept.select(F.col("a").alias("ssid"), F.col("b").alias("dsid"), F.lit(1).cast("long").alias("m"))
    se = se.unionByName(sn.where("self_m is not null").select(F.col("sid").alias("ssid"), F.col("sid").alias("dsid"), F.lit(1).cast("long").alias("m")))
    return Summary(g, sn, mem.select("id", "sid"), settle(se, "pm_se"))


def pair_summary(g: PropertyGraph, p: Pairs) -> Summary:
    """As a super-graph: dense pairs get a super-edge of multiplicity 1, dense insides a clique."""
    sn, mem, se = [], [], []
    for u, ids in p.members.items():
        n = len(ids)
        c = p.out[u][u] if u in p.out[u] else 0
        full = c > 0 and n * (n - 1) - c + 1 <= c
        k = p.loops[u]
        self_m = 1 if k and n - k + 1 <= k else None
        sn.append((u, p.label[u], n, "clique" if full else "disconnected", 1, None, self_m))
        mem += [(i, u) for i in ids]
        if self_m:
            se.append((u, u, 1))
        for z, c in p.out[u].items():
            if z != u and c and (p.directed or u < z) and n * len(p.members[z]) - c + 1 <= c:
                se.append((u, z, 1))
    return as_summary(g, (sn, mem, se))


def walked_summary(g: PropertyGraph, ids: np.ndarray, names: np.ndarray, walk) -> Summary:
    """As ``pair_summary``, of a ``PairWalk`` at its end."""
    home, inside, loops = unpacked(walk.homes()), unpacked(walk.insides()), unpacked(walk.loops())
    sid, n = np.unique(home, return_counts=True)
    full = (inside[sid] > 0) & (n * (n - 1) - inside[sid] + 1 <= inside[sid])
    looped = (loops[sid] > 0) & (n - loops[sid] + 1 <= loops[sid])
    one, own = np.ones(len(sid), np.int64), ids[sid]
    ends = [unpacked(walk.dense(at, min(at + PLACES_READ, len(ids)))).reshape(-1, 2) for at in range(0, len(ids), PLACES_READ)]
    a, b = np.concatenate([np.zeros((0, 2), np.int64), *ends]).T
    glyph = np.where(full, "clique", "disconnected").astype(object)
    sn = (own, names[sid], n, glyph, one, pa.nulls(len(sid)), pa.array(one, mask=~looped))
    self_edges = own[looped]
    se = (np.concatenate([self_edges, ids[a]]), np.concatenate([self_edges, ids[b]]), np.ones(len(self_edges) + len(a), np.int64))
    return column_summary(g, (sn, (ids, ids[home]), se))


def pairmerge_cost(s: Summary) -> DataFrame:
    """Its own cost: super-edges and corrections (multiplicities ignored), and their bits."""
    fixes = corrections(s).where("kind <> 'retune'").agg(F.count("*").alias("fixes"))
    inner = s.supernodes.agg(F.count("*").cast("double").alias("vs"), F.sum("size").cast("double").alias("v"), F.count_if(F.col("glyph") == "clique").alias("inner"))
    edges = s.superedges.agg(F.count("*").alias("se")).crossJoin(inner).crossJoin(fixes)
    n = F.col("se") + F.col("inner")
    bits = n * 2 * F.log2("vs") + F.col("fixes") * (2 * F.log2("v") + 1)
    return edges.select((n + F.col("fixes")).alias("edges"), n.alias("superedges"), "fixes", bits.alias("bits"))


# structure vocabulary ---------------------------------------------------------------

#: Node sets whose counts are read at once.
SETS_READ = 1 << 16


def _entropy(n: float, k: float) -> float:
    return sum(-x * math.log2(x / n) for x in (k, n - k) if 0 < x < n)


class Peeled:
    """Node sets from repeated removal of the largest hubs (``HubPeel``): each hub's star, and what falls off.

    Nodes with edges are numbered in the order of their ids; a pair of them is the number of its smaller node times
    their count, plus the larger one's. ``pairs`` has those that are edges, in order.
    """

    def __init__(self, g: PropertyGraph, hubs: int = 1, least: int = 3):
        e = gathered(g.edges.where("src <> dst").select("src", "dst"))
        ids = np.unique(np.concatenate([e["src"].to_numpy(np.int64), e["dst"].to_numpy(np.int64)]))
        src, dst = (np.searchsorted(ids, e[c].to_numpy(np.int64)) for c in ("src", "dst"))
        self.v = len(ids)
        self.pairs = np.unique(np.minimum(src, dst) * self.v + np.maximum(src, dst))
        self.low, self.high = (x.astype(np.int32) for x in np.divmod(self.pairs, max(self.v, 1)))
        self.first = np.searchsorted(self.low, np.arange(self.v + 1))
        self.peel = java_object(g.edges.sparkSession, "HubPeel", self.v)
        for part in chunks(self.low, self.high):
            self.peel.add(part)
        self.sets = self.peel.peel(hubs, least)

    def counts(self) -> Iterator[list[int]]:
        """Of each set: nodes, edges, edges of its hub, nodes of its path, nodes of both sides, edges between them."""
        for at in range(0, self.sets, SETS_READ):
            yield from unpacked(self.peel.counts(at, min(at + SETS_READ, self.sets))).reshape(-1, 7).tolist()

    def part(self, s: int, what: str) -> np.ndarray:
        return unpacked(self.peel.part(s, what))

    def edges_at(self, nodes: np.ndarray) -> np.ndarray:
        """Places in ``pairs`` of all edges whose smaller end is among ``nodes``."""
        n = self.first[nodes + 1] - self.first[nodes]
        return np.arange(n.sum()) + np.repeat(self.first[nodes] - (np.cumsum(n) - n), n)

    def claims(self, s: int, kind: str) -> tuple[np.ndarray, np.ndarray]:
        """What a structure over set s claims: places of edges in ``pairs``, and pairs that are none."""
        if kind == "chain":
            x = self.part(s, "path")
            at = np.searchsorted(self.pairs, np.minimum(x[1:], x[:-1]) * self.v + np.maximum(x[1:], x[:-1]))
            return np.sort(at), at[:0]
        every = self.part(s, "all")
        a = every if kind.endswith("clique") else self.part(s, "hub" if kind == "star" else "left")
        b = every if kind.endswith("clique") else np.setdiff1d(every, a) if kind == "star" else self.part(s, "right")
        in_a, in_b = np.zeros(self.v, bool), np.zeros(self.v, bool)
        in_a[a], in_b[b] = True, True
        at = self.edges_at(every)
        low, high = self.low[at], self.high[at]
        at = at[(in_a[low] & in_b[high]) | (in_b[low] & in_a[high])]
        if kind.startswith("near_"):
            return at, at[:0]
        own = self.pairs[at]
        lacks = []
        for x in a.tolist():
            y = b[b > x] if kind == "clique" else b
            pair = np.minimum(x, y) * self.v + np.maximum(x, y)
            lacks.append(pair[~found(own, pair)])
        return at, np.sort(np.concatenate([at[:0], *lacks]))


def found(known: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Which of x are in ``known``, which is sorted."""
    at = np.searchsorted(known, x)
    return np.append(known, -1)[at] == x


@cache
def chain_bits(n: int, v: int) -> float:
    return n_int_bits(max(n - 1, 1)) + sum(math.log2(max(v - i, 1)) for i in range(n))


def structure_bits(kind: str, a: int, b: int, v: int, hits: int) -> float:
    """Model bits of one structure over a (and b) nodes of v, ``hits`` edges among the pairs that it claims."""
    if kind in ("clique", "near_clique"):
        bits, slots = n_int_bits(a) + n_log2_binomial(v, a), a * (a - 1) / 2
    elif kind == "chain":
        bits, slots = chain_bits(a, v), 0
    elif kind == "star":
        bits, slots = n_int_bits(max(b, 1)) + math.log2(v) + n_log2_binomial(v - 1, b), b
    else:
        bits = n_int_bits(a) + n_int_bits(max(b, 1)) + n_log2_binomial(v, a) + n_log2_binomial(v - a, b)
        slots = a * b
    if kind.startswith("near_"):
        bits += math.log2(max(slots, 1)) + _entropy(slots, hits)
    return bits


def label_structure(n: int, edges: int, hub: int, path: int, a: int, b: int, across: int, v: int) -> tuple[float, str, int, int]:
    """The vocabulary word with the least bits for a node set, its own errors included: (bits, kind, pairs it claims, edges among them).

    Its counts are those of ``Peeled.counts``.
    """
    words = [
        ("clique", n, 0, n * (n - 1) // 2, edges), ("near_clique", n, 0, edges, edges),
        ("star", 1, n - 1, n - 1, hub), ("chain", path, 0, path - 1, path - 1),
    ]
    if a and b:
        words += [("bipartite", a, b, a * b, across), ("near_bipartite", a, b, across, across)]
    best = None
    slots = max(n * (n - 1) / 2, 1)
    for kind, x, y, claimed, hits in words:
        bits = structure_bits(kind, x, y, v, hits)
        wrong = claimed - hits + edges - hits
        total = bits + math.log2(slots + 1) + _entropy(slots, min(wrong, slots))
        if best is None or total < best[0]:
            best = (total, kind, claimed, hits)
    return best


def vocab_summary(g: PropertyGraph, select: str = "plain") -> pd.DataFrame:
    """Structures chosen for a simple undirected graph: (kind, size, gain); bits in ``attrs``.

    select: plain (all), top10, top100, or greedy_forget (keep one if the total falls).
    Sets of any size are tried as every kind of structure; pairs that are no edges are held for chosen ones only.
    """
    sets = Peeled(g)
    v = g.nodes.count()
    edges = len(sets.pairs)
    slots = max(v * (v - 1) / 2, 1)

    def error(extra: int, covered: int) -> float:
        return math.log2(slots + 1) * 2 + _entropy(slots, extra) + _entropy(slots, max(edges - covered, 0))

    scored = []
    for s, own in enumerate(sets.counts()):
        bits, kind, claimed, hit = label_structure(*own, v)
        scored.append((error(0, 0) - (bits + math.log2(6) + error(claimed - hit, hit)), bits, kind, own[0], s))
    scored.sort(key=lambda w: (-w[0], w[3]))
    chosen, model = [], 0.0
    taken, lacking = np.zeros(edges, bool), np.zeros(0, np.int64)
    total, n_claimed, n_hit = error(0, 0), 0, 0
    limit = {"top10": 10, "top100": 100}.get(select, len(scored))
    for gain, bits, kind, n, s in scored[:limit]:
        real, none = sets.claims(s, kind)
        real, none = real[~taken[real]], none[~found(lacking, none)]
        now, hit = n_claimed + len(real) + len(none), n_hit + len(real)
        after = model + bits + math.log2(6) + error(now - hit, hit) + n_int_bits(len(chosen) + 1)
        if select == "greedy_forget" and after >= total:
            continue
        taken[real] = True
        if len(none):
            lacking = np.union1d(lacking, none)
        n_claimed, n_hit, model, total = now, hit, model + bits + math.log2(6), after
        chosen.append((kind, n, gain))
    out = pd.DataFrame(chosen, columns=["kind", "size", "gain"])
    out.attrs = {"bits": total, "before": error(0, 0), "model": model}
    return out


# fixed groupings --------------------------------------------------------------------


def decide_superedges(bundles: DataFrame) -> DataFrame:
    """Adds with/without bits and the verdict to bundles (n_a, n_b, p_a, p_b, n, hit, covered_bits, plain_bits, plain_hit_bits, rep)."""
    every, cover = F.col("n_a") * F.col("n_b"), F.col("p_a") * F.col("p_b")
    chan = lambda n, k: F.when(every == 1, 0.0).otherwise(channel_bits(n, k))
    with_ = int_bits(F.col("rep")) + chan(cover, cover - F.col("hit")) + chan(every - cover, F.col("n") - F.col("hit")) + F.col("covered_bits") + F.col("plain_bits") - F.col("plain_hit_bits")
    without = chan(every, F.col("n")) + F.col("plain_bits")
    return bundles.withColumns({"with_bits": with_, "without_bits": without}).withColumn("keep", (F.col("hit") > 0) & (F.col("with_bits") < F.col("without_bits")))


def bundle_edges(s_members: DataFrame, supernodes: DataFrame, edges: DataFrame, directed: bool = True) -> DataFrame:
    """Edges between different super-nodes bundled per ordered pair (per pair without directions), with exact representatives."""
    a, b = s_members.select(F.col("id").alias("src"), F.col("sid").alias("a")), s_members.select(F.col("id").alias("dst"), F.col("sid").alias("b"))
    side = lambda x: supernodes.select(F.col("sid").alias(x), F.col("size").alias(f"n_{x}"), F.col("glyph").alias(f"g_{x}"), F.col("hub").alias(f"h_{x}"))
    e = edges.join(a, "src").join(b, "dst").where("a <> b").select("src", "dst", "m", "a", "b")
    if not directed:
        flip = F.col("a") > F.col("b")
        e = e.select(F.when(flip, F.col("dst")).otherwise(F.col("src")).alias("src"), F.when(flip, F.col("src")).otherwise(F.col("dst")).alias("dst"), "m", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    e = e.join(side("a"), "a").join(side("b"), "b")
    star = lambda x: F.col(f"g_{x}").isin(*STARS)
    e = e.withColumn("hit", (~star("a") | (F.col("src") == F.col("h_a"))) & (~star("b") | (F.col("dst") == F.col("h_b"))))
    rep = rep_exact_sql(e.where("hit"), ["a", "b"])
    e = e.join(rep.select("a", "b", "rep"), ["a", "b"], "left")
    hit = F.col("hit")
    return e.groupBy("a", "b").agg(
        F.first("n_a").alias("n_a"), F.first("n_b").alias("n_b"),
        F.first(F.when(star("a"), 1).otherwise(F.col("n_a"))).alias("p_a"), F.first(F.when(star("b"), 1).otherwise(F.col("n_b"))).alias("p_b"),
        F.count("*").alias("n"), F.count_if(hit).alias("hit"), F.first("rep").alias("rep"),
        F.coalesce(F.sum(F.when(hit, diff_bits(F.col("m"), F.col("rep")))), F.lit(0.0)).alias("covered_bits"),
        F.sum(int_bits(F.col("m"))).alias("plain_bits"),
        F.coalesce(F.sum(F.when(hit, int_bits(F.col("m")))), F.lit(0.0)).alias("plain_hit_bits"),
    )


def summary_of_partition(g: PropertyGraph, members: DataFrame, superedges: str = "rule") -> Summary:
    """The summary of a given label-pure partition; superedges: rule, all or none."""
    lab = members.join(g.nodes, "id")
    size = lab.groupBy("sid").agg(F.min("label").alias("label"), F.count("*").cast("long").alias("size"))
    glyph = decide_glyph(members.select(F.col("sid").alias("pid"), "id"), g.edges, g.directed).select(F.col("pid").alias("sid"), "glyph", "hub", "n")
    glyph = glyph.select("sid", F.when(F.col("n") == 1, "disconnected").otherwise(F.col("glyph")).alias("glyph"), F.when(F.col("n") > 1, F.col("hub")).alias("hub"))
    sn = size.join(glyph, "sid")
    a, b = members.select(F.col("id").alias("src"), F.col("sid").alias("a")), members.select(F.col("id").alias("dst"), F.col("sid").alias("b"))
    inner = g.edges.join(a, "src").join(b, "dst").where("a = b").join(glyph.select(F.col("sid").alias("a"), "glyph", "hub"), "a")
    spoke = F.col("hub").isNotNull() & ((F.col("src") == F.col("hub")) | (F.col("dst") == F.col("hub")))
    hit = (F.col("glyph") == "clique") | spoke if not g.directed else (F.col("glyph") == "clique") | ((F.col("glyph") == "in_star") & (F.col("dst") == F.col("hub"))) | ((F.col("glyph") == "out_star") & (F.col("src") == F.col("hub")))
    m = rep_exact_sql(inner.where("src <> dst").where(hit), ["a"]).select(F.col("a").alias("sid"), F.col("rep").alias("m"))
    loops = rep_exact_sql(inner.where("src = dst"), ["a"]).select(F.col("a").alias("sid"), F.col("rep").alias("self_m"))
    if superedges == "none":
        loops = loops.join(size.where("size = 1"), "sid", "left_semi")
    sn = sn.join(m, "sid", "left").join(loops, "sid", "left").select("sid", "label", "size", "glyph", F.coalesce("m", F.lit(1).cast("long")).alias("m"), "hub", "self_m")
    sn = settle(sn, "part_sn")
    bundles = decide_superedges(bundle_edges(members, sn, g.edges, g.directed))
    # single nodes keep their plain super-edges
    keep = {"rule": F.col("keep"), "all": F.col("hit") > 0, "none": F.lit(False)}[superedges] | (F.col("n_a") * F.col("n_b") == 1)
    se = bundles.where(keep).select(F.col("a").alias("ssid"), F.col("b").alias("dsid"), F.col("rep").cast("long").alias("m"))
    se = se.unionByName(sn.where("self_m is not null").select(F.col("sid").alias("ssid"), F.col("sid").alias("dsid"), F.col("self_m").alias("m")))
    return Summary(g, sn, members.select("id", "sid"), settle(se, "part_se"))


def label_members(g: PropertyGraph) -> DataFrame:
    first = g.nodes.groupBy("label").agg(F.min("id").alias("sid"))
    return g.nodes.join(first, "label").select("id", "sid")


def duplicate_members(g: PropertyGraph) -> DataFrame:
    """Nodes of one label with equal neighbour lists together; lists are told by their length and two 64-bit sums."""
    tok = neighbor_tokens(g)
    prints = [F.sum(F.xxhash64("tok", F.lit(k)).cast("decimal(38,0)")).alias(f"p{k}") for k in (0, 1)]
    key = tok.groupBy("id").agg(F.count("*").alias("d"), *prints)
    keyed = g.nodes.join(key, "id", "left").withColumn("alone", F.when(F.col("d").isNull(), F.col("id")))
    first = keyed.groupBy("label", "d", "p0", "p1", "alone").agg(F.min("id").alias("sid"))
    same = reduce(and_, (F.col(f"x.{c}").eqNullSafe(F.col(f"y.{c}")) for c in ("label", "d", "p0", "p1", "alone")))
    return keyed.alias("x").join(first.alias("y"), same).select("x.id", "y.sid")


def random_members(g: PropertyGraph, members: DataFrame, seed: int = 42) -> DataFrame:
    """Groups of the same sizes and labels, filled at random."""
    slot = numbered(members.join(g.nodes, "id"), ["label", "sid", "id"], "r").select("r", F.col("sid").alias("g"))
    who = numbered(g.nodes.withColumn("draw", node_draw(F.col("id"), seed)), ["label", "draw", "id"], "r")
    drawn = who.join(slot, "r").select("id", "g")
    first = drawn.groupBy("g").agg(F.min("id").alias("sid"))
    return drawn.join(first, "g").select("id", "sid")


def star_members(g: PropertyGraph, where: str = "dst % 8 = 3") -> DataFrame:
    """Targets of some edges join their smallest source; other nodes stay alone."""
    home = g.edges.where(where).groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("home"))
    return g.nodes.join(home, "id", "left").select("id", F.coalesce("home", "id").alias("sid"))


def group_summary(g: PropertyGraph, key: str = "label", superedges: str = "rule", seed: int = 42) -> Summary:
    """A super-node for each label, each set of equal neighbourhoods, a random filling of the latter, or each star."""
    members = {"label": label_members, "stars": star_members}.get(key, duplicate_members)(g)
    if key == "random":
        members = random_members(g, settle(members, "drawn_members"), seed)
    return summary_of_partition(g, settle(members, "part_members"), superedges)
