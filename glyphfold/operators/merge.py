"""Merging of candidate sets: glyphs, super-edges, representative multiplicities.

One kernel judges one part (same-label free nodes of a candidate) from its incident
edges and what is known of the super-nodes around it. Two engines share it: the
serial one walks the ranking on the driver's copy of the graph, the rounds one joins
whole rounds of parts that don't share a node and judges them in parallel.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator, Sequence
from copy import copy
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from glyphfold.functions.bits import n_channel_bits, n_diff_bits, n_int_bits, n_log2_binomial
from glyphfold.operators.candidates import Candidates, candidate_sets
from glyphfold.operators.ordering import numbered
from glyphfold.operators.summary import MEMBERS, STARS, SUPEREDGES, SUPERNODES, Summary, identity_summary
from glyphfold.session import discard, few, gathered, large, release, settle
from glyphfold.sources.graphs import PropertyGraph


@dataclass(frozen=True)
class SummaryConfig:
    """Every choice of the method; the defaults are the paper's where it prints one."""

    r: int = 2
    b: int = 5
    family: str = "affine31"
    seed: int = 42
    filtered: bool = True
    similarity: str = "directed"
    max_cluster: int = 5000
    max_candidates: int | None = None
    glyph_rule: str = "proxy"  # or "best": true bits of all glyphs
    rep: str = "dichotomous"  # or "exact", "median", "mode", "mean"
    ledger: str = "printed"  # or "sound"
    zero_bits: float = 3.0
    mark_policy: str = "always"  # or "on_commit"
    engine: str = "auto"  # or "serial", "rounds"
    local_edges: int = 2_000_000  # up to so many, candidates and the walk are held by the driver
    isolation: str = "nodes"  # or "neighbours"
    include_membership: bool = False
    nested: bool = False


# representative multiplicities


def bag_cost(bag: list[int] | Counter, m: int) -> float:
    items = bag.items() if isinstance(bag, Counter) else ((x, 1) for x in bag)
    return sum(c * n_diff_bits(x, m) for x, c in items)


def rep_dichotomous(bag: list[int]) -> int:
    """Halve the range, going left where the cost does not fall to the right."""
    hist = Counter(bag)
    lo, hi = min(hist), max(hist)
    while lo < hi:
        mid = (lo + hi) // 2
        if bag_cost(hist, mid) <= bag_cost(hist, mid + 1):
            hi = mid
        else:
            lo = mid + 1
    return lo


def rep_exact(bag: list[int]) -> int:
    """Between observed values the cost is concave, so an optimum lies at one of them or next to it."""
    hist = Counter(bag)
    tries = sorted({x + k for x in hist for k in (-1, 0, 1) if x + k >= 1})
    return min(tries, key=lambda m: (bag_cost(hist, m), m))


def rep_of(bag: list[int], how: str) -> int:
    if not bag:
        return 1
    if how == "dichotomous":
        return rep_dichotomous(bag)
    if how == "exact":
        return rep_exact(bag)
    x = sorted(bag)
    if how == "median":
        return x[(len(x) - 1) // 2]
    if how == "mode":
        top = Counter(x)
        return min(top, key=lambda v: (-top[v], v))
    return max(1, round(sum(x) / len(x)))


def rep_exact_sql(edges: DataFrame, keys: list[str], m: str = "m") -> DataFrame:
    """Exact representative of each group as a join of its histogram with itself."""
    hist = edges.groupBy(*keys, F.col(m).alias("x")).agg(F.count("*").alias("c"))
    tries = hist.select(*keys, F.explode(F.array(F.col("x") - 1, F.col("x"), F.col("x") + 1)).alias("rep")).where("rep >= 1").distinct()
    d = F.abs(F.col("x") - F.col("rep")).cast("double")
    cost = F.sum(F.col("c") * F.when(d == 0, 1.0).otherwise(2 * F.log2(d) + 3))
    costs = tries.join(hist, keys).groupBy(*keys, "rep").agg(F.round(cost, 6).alias("bits"))
    return costs.groupBy(*keys).agg(F.min(F.struct("bits", "rep")).alias("best")).select(*keys, "best.rep", "best.bits")


# glyphs


def glyph_of(n: int, edges: list[tuple[int, int]], directed: bool = True) -> tuple[str, int | None]:
    """Glyph and hub of n nodes with these induced edges (no loops)."""
    e = len(edges)
    if (2 if directed else 4) * e >= n * (n - 1) and n > 1:
        return "clique", None
    if directed:
        d_in, d_out = Counter(v for _, v in edges), Counter(u for u, _ in edges)
    else:
        d_in = Counter(x for pair in edges for x in pair)
        d_out = d_in
    top = lambda d: min(d, key=lambda x: (-d[x], x)) if d else None
    h_in, h_out = top(d_in), top(d_out)
    c_in = n - 1 + e - 2 * d_in[h_in] if h_in is not None else n - 1 + e
    c_out = n - 1 + e - 2 * d_out[h_out] if h_out is not None else n - 1 + e
    if min(c_in, c_out) < e:
        if not directed:
            return "out_star", h_in
        return ("in_star", h_in) if c_in <= c_out else ("out_star", h_out)
    return "disconnected", None


def decide_glyph(parts: DataFrame, edges: DataFrame, directed: bool = True) -> DataFrame:
    """The glyph rule for parts (pid, id) at once: (pid, glyph, hub, n, e, d_in, d_out, cost_in, cost_out).

    Without directions d_in counts both ends of an edge, and a star is an ``out_star``.
    """
    x, y = parts.select("pid", F.col("id").alias("src")), parts.select(F.col("pid").alias("p2"), F.col("id").alias("dst"))
    inner = edges.where("src <> dst").join(x, "src").join(y, "dst").where("pid = p2").select("pid", "src", "dst")
    count = parts.groupBy("pid").agg(F.count("*").cast("long").alias("n"))
    e = inner.groupBy("pid").agg(F.count("*").alias("e"))
    into, out = inner.select("pid", F.col("dst").alias("x")), inner.select("pid", F.col("src").alias("x"))
    best = lambda ends, d: ends.groupBy("pid", "x").agg(F.count("*").alias("d")).groupBy("pid").agg(F.max("d").alias(f"d_{d}"), F.max_by("x", F.struct("d", (-F.col("x")).alias("y"))).alias(f"h_{d}"))
    df = count.join(e, "pid", "left").join(best(into if directed else into.unionByName(out), "in"), "pid", "left").join(best(out, "out"), "pid", "left").na.fill(0, ["e", "d_in", "d_out"])
    df = df.withColumns({"cost_in": F.col("n") - 1 + F.col("e") - 2 * F.col("d_in"), "cost_out": F.col("n") - 1 + F.col("e") - 2 * F.col("d_out")})
    dense = F.when((2 if directed else 4) * F.col("e") >= F.col("n") * (F.col("n") - 1), "clique")
    if directed:
        glyph = dense.when((F.col("cost_in") < F.col("e")) & (F.col("cost_in") <= F.col("cost_out")), "in_star").when(F.col("cost_out") < F.col("e"), "out_star").otherwise("disconnected")
        hub = F.when(glyph == "in_star", F.col("h_in")).when(glyph == "out_star", F.col("h_out"))
    else:
        glyph = dense.when(F.col("cost_in") < F.col("e"), "out_star").otherwise("disconnected")
        hub = F.when(glyph == "out_star", F.col("h_in"))
    return df.select("pid", glyph.alias("glyph"), hub.alias("hub"), "n", "e", "d_in", "d_out", "cost_in", "cost_out")


# the kernel


@dataclass
class Side:
    """What a part must know of a super-node next to it."""

    size: int = 1
    glyph: str = "disconnected"
    hub: int | None = None
    out: int = 0  # super-edges out
    loose: int = 0  # targets reached by corrections only


@dataclass
class Verdict:
    delta: float
    local: float  # the change without the terms of the whole summary
    glyph: str
    hub: int | None
    m: int
    self_m: int | None
    edges: list[tuple[int, int, int]]  # super-edges, the part itself being PART
    sides: dict[int, tuple[int, int]]  # new out and loose counts of neighbours
    own: tuple[int, int]  # the part's own
    whole: float  # the terms of the whole summary after it


PART = -1


def port(side_glyph: str, hub: int | None, node: int) -> bool:
    return side_glyph not in STARS or node == hub


def bundle(rows: list[tuple[int, int, int]], a: tuple, b: tuple, cfg: SummaryConfig) -> tuple[float, float, int | None]:
    """Bits with and without a super-edge, and its multiplicity; a, b: (size, glyph, hub) of the ends.

    Both include all corrections; the first also the super-edge's own multiplicity.
    """
    (na, ga, ha), (nb, gb, hb) = a, b
    every = na * nb
    z = cfg.zero_bits
    plain = sum(n_int_bits(m) for _, _, m in rows)
    without = (n_channel_bits(every, len(rows), z) if every > 1 else 0.0) + plain
    hit = [m for u, v, m in rows if port(ga, ha, u) and port(gb, hb, v)]
    if not hit:
        return math.inf, without, None
    cover = (1 if ga in STARS else na) * (1 if gb in STARS else nb)
    rep = rep_of(hit, cfg.rep)
    out = plain - sum(n_int_bits(m) for m in hit) + sum(n_diff_bits(m, rep) for m in hit) + n_int_bits(rep)
    topo = n_channel_bits(cover, cover - len(hit), z) + n_channel_bits(every - cover, len(rows) - len(hit), z) if every > 1 else 0.0
    return out + topo, without, rep


def covered(glyph: str, hub: int | None, u: int, v: int, directed: bool) -> bool:
    if u == v:
        return False
    if glyph == "clique":
        return True
    if not directed:
        return glyph in STARS and hub in (u, v)
    return (glyph == "in_star" and v == hub) or (glyph == "out_star" and u == hub)


def inner_bits(n: int, rows: list, glyph: str, hub: int | None, directed: bool, cfg: SummaryConfig) -> tuple[float, int, int | None]:
    """Bits inside a part (corrections, multiplicities, self super-edge), and its multiplicities."""
    z = cfg.zero_bits
    loops = [m for u, v, m in rows if u == v]
    hit = [m for u, v, m in rows if covered(glyph, hub, u, v, directed)]
    rest = [m for u, v, m in rows if u != v and not covered(glyph, hub, u, v, directed)]
    pairs = n * (n - 1) if directed else n * (n - 1) // 2
    cover = pairs if glyph == "clique" else n - 1 if glyph in STARS else 0
    rep = rep_of(hit, cfg.rep)
    bits = sum(n_diff_bits(m, rep) for m in hit) + sum(n_int_bits(m) for m in rest)
    if n > 1 and cover:
        bits += n_channel_bits(cover, cover - len(hit), z)
    plus = lambda slots, k: n_channel_bits(slots, k, z) if n > 1 else 0.0
    open_bits = plus(pairs + n - cover, len(rest) + len(loops)) + sum(map(n_int_bits, loops))
    if not loops:
        return bits + open_bits, rep, None
    self_m = rep_of(loops, cfg.rep)
    closed = plus(pairs - cover, len(rest)) + (n_channel_bits(n, n - len(loops), z) if n > 1 else 0.0)
    closed += sum(n_diff_bits(m, self_m) for m in loops) + n_int_bits(self_m)
    if closed < open_bits or n == 1:
        return bits + closed, rep, self_m
    return bits + open_bits, rep, None


def global_bits(vs: int, out: dict[int, int], loose: dict[int, int], cfg: SummaryConfig) -> float:
    """Terms that depend on the number of super-nodes and on the histograms of their out-counts."""
    bits = n_int_bits(vs) + vs * math.log2(vs) + sum(c * n_log2_binomial(vs, d) for d, c in out.items() if c)
    if cfg.ledger == "sound":
        bits += vs * math.log2(vs) + sum(c * n_log2_binomial(vs, d) for d, c in loose.items() if c)
    return bits


def own_bits(size: int, glyph: str, m: int, v: int, n_labels: int) -> float:
    """Model and mapping terms of one super-node that don't depend on the others."""
    return math.log2(n_labels) + 2 + n_int_bits(size) + n_int_bits(m) + n_log2_binomial(v, size) + (math.log2(size) if glyph in STARS else 0.0)


@dataclass
class World:
    """Counts of the whole summary that a merge changes."""

    v: int
    n_labels: int
    vs: int
    out: Counter
    loose: Counter
    bits: float | None = None  # the terms that depend on these counts, once computed


def pair_of(a: int, b: int, directed: bool) -> tuple[int, int]:
    """The super-edge between a and b; without directions the smaller id holds it."""
    return (a, b) if directed or a <= b else (b, a)


def oriented(outer: dict[int, list], me: int, directed: bool) -> dict[int, list]:
    """Without directions a bundle is one: all its edges run from the smaller super-node to the larger."""
    if directed:
        return outer
    return {z: [(me < z, *((u, v) if t == (me < z) else (v, u)), m) for t, u, v, m in rows] for z, rows in outer.items()}


def out_counts(me: int, outer: dict[int, list], sides: dict[int, Side], held: set, edges: list, self_m: int | None, directed: bool) -> tuple[dict, tuple[int, int]]:
    """Super-edges and loose targets that each neighbour, and the part itself, would hold after the merge.

    held: the super-edges between neighbours and single nodes of the part before it.
    """
    kept = {(me if a == PART else a, me if b == PART else b) for a, b, _ in edges}
    own_out, own_loose = int(self_m is not None), 0
    moved = {}
    for z, rows in outer.items():
        o, l = sides[z].out, sides[z].loose
        old = {pair_of(u, z, directed) if to else pair_of(z, v, directed) for to, u, v, _ in rows}
        for pair in old:
            if pair[0] == z:
                o -= pair in held
                l -= pair not in held
        for to in {t for t, *_ in rows}:
            pair = (me, z) if to else (z, me)
            has = pair in kept
            if pair[0] == z:
                o += has
                l += not has
            else:
                own_out += has
                own_loose += not has
        moved[z] = (o, l)
    return moved, (own_out, own_loose)


def judge(nodes: list[int], inner: list, outer: dict[int, list], sides: dict[int, Side], held: set, world: World, directed: bool, cfg: SummaryConfig, singles: dict[int, Side]) -> Verdict:
    """Change of the total bits if ``nodes`` became one super-node.

    inner: edges among the nodes; outer: for each neighbouring super-node z the edges
    (u, v, m) with (True) towards it or (False) from it, as z: [(to, u, v, m)], oriented;
    held: the super-edges there are between neighbours and nodes.
    """
    n, me = len(nodes), min(nodes)
    pairs = [(u, v) for u, v, _ in inner if u != v]
    choices = [glyph_of(n, pairs, directed)]
    if cfg.glyph_rule == "best":
        d_in, d_out = Counter(v for _, v in pairs), Counter(u for u, _ in pairs)
        d_in, d_out = (d_in, d_out) if directed else (d_in + d_out, d_in + d_out)
        hubs = [("in_star", max(d_in, key=lambda x: (d_in[x], -x)))] if d_in and directed else []
        hubs += [("out_star", max(d_out, key=lambda x: (d_out[x], -x)))] if d_out else []
        choices = [("clique", None), ("disconnected", None), *hubs]
    before = n * own_bits(1, "disconnected", 1, world.v, world.n_labels)
    if world.bits is None:
        world.bits = global_bits(world.vs, world.out, world.loose, cfg)
    for u, v, m in inner:  # plain edges between single nodes: super-edges with their own multiplicity
        before += 1 + n_int_bits(m)
    for z, rows in outer.items():
        side = sides[z]
        if side.size == 1:
            before += sum(1 + n_int_bits(m) for *_, m in rows)
            continue
        by: dict[tuple, list] = defaultdict(list)
        for to, u, v, m in rows:
            by[to, u if to else v].append((u, v, m))
        ends = (side.size, side.glyph, side.hub)
        for (to, x), own in by.items():
            single = (1, "disconnected", None)
            with_, without, _m = bundle(own, single if to else ends, ends if to else single, cfg)
            before += with_ if (pair_of(x, z, directed) if to else pair_of(z, x, directed)) in held else without
    best = None
    for glyph, hub in choices:
        bits, m, self_m = inner_bits(n, inner, glyph, hub, directed, cfg)
        after = own_bits(n, glyph, m, world.v, world.n_labels) + bits
        edges = []
        for z, rows in outer.items():
            side = sides[z]
            for to in (True, False):
                own = [(u, v, m_) for t, u, v, m_ in rows if t == to]
                if not own:
                    continue
                me_, other = (n, glyph, hub), (side.size, side.glyph, side.hub)
                with_, without, rep = bundle(own, me_ if to else other, other if to else me_, cfg)
                if with_ + membership(world, cfg) < without:
                    after += with_
                    edges.append((PART, z, rep) if to else (z, PART, rep))
                else:
                    after += without
        moved, own_counts = out_counts(me, outer, sides, held, edges, self_m, directed)
        hist, lhist = Counter(world.out), Counter(world.loose)
        for s in singles.values():
            hist[s.out] -= 1
            lhist[s.loose] -= 1
        for z, (o, l) in moved.items():
            hist[sides[z].out] -= 1
            lhist[sides[z].loose] -= 1
            hist[o] += 1
            lhist[l] += 1
        hist[own_counts[0]] += 1
        lhist[own_counts[1]] += 1
        vs = world.vs - n + 1
        local = after - before
        whole = global_bits(vs, hist, lhist, cfg)
        delta = local + whole - world.bits
        if best is None or delta < best.delta:
            best = Verdict(delta, local, glyph, hub, m, self_m, edges, moved, own_counts, whole)
    return best


def membership(world: World, cfg: SummaryConfig) -> float:
    """Optional share of the out-set that a super-edge adds (left out of the local rule by default)."""
    return math.log2(max(world.vs, 1)) if cfg.include_membership else 0.0


# engines


def ranked(sets: list[tuple[tuple[int, ...], float]], limit: int | None = None) -> list[tuple[tuple[int, ...], float]]:
    """By size times quality, then size, then the ids."""
    out = sorted(sets, key=lambda s: (-len(s[0]) * s[1], -len(s[0]), s[0]))
    return out[:limit] if limit else out


def rank_candidates(candidates: DataFrame) -> DataFrame:
    """``rank`` (from 1) and ``score`` of candidates (cid, size, quality)."""
    scored = candidates.withColumn("score", F.col("size") * F.col("quality"))
    return numbered(scored, [F.desc("score"), F.desc("size"), "cid"], start=1, name="ranking")


def split_by_label(members: DataFrame, nodes: DataFrame) -> DataFrame:
    """Parts (cid, label, ids) of more than one node."""
    return members.join(nodes, "id").groupBy("cid", "label").agg(F.array_sort(F.collect_list("id")).alias("ids")).where(F.size("ids") > 1)


class Walk:
    """The serial engine's state: the graph in memory and the summary so far."""

    def __init__(self, g: PropertyGraph, cfg: SummaryConfig, nodes: pd.DataFrame | None = None, edges: pd.DataFrame | None = None):
        nodes = gathered(g.nodes) if nodes is None else nodes
        edges = gathered(g.edges) if edges is None else edges
        self.cfg, self.directed = cfg, g.directed
        self.label = dict(zip(nodes["id"].tolist(), nodes["label"].tolist(), strict=True))
        self.of = {u: u for u in self.label}
        self.sides = {u: Side() for u in self.label}
        self.super: dict[int, tuple] = {}
        self.edges: dict[tuple[int, int], int] = {}
        self.out: dict[int, list] = defaultdict(list)
        self.into: dict[int, list] = defaultdict(list)
        for u, v, m in zip(edges["src"].tolist(), edges["dst"].tolist(), edges["m"].tolist(), strict=True):
            self.out[u].append((v, m))
            self.into[v].append((u, m))
            self.edges[u, v] = m
            self.sides[u].out += 1
        self.marked: set[int] = set()
        self.world = World(len(self.label), max(1, len(set(self.label.values()))), len(self.label), Counter(s.out for s in self.sides.values()), Counter({0: len(self.label)}))
        self.delta = 0.0

    def around(self, nodes: list[int]) -> tuple[list, dict[int, list]]:
        own = set(nodes)
        inner, outer = [], defaultdict(list)
        for u in nodes:
            for v, m in self.out[u]:
                if v in own:
                    inner.append((u, v, m))
                else:
                    outer[self.of[v]].append((True, u, v, m))
            for w, m in self.into[u]:
                if w not in own:
                    outer[self.of[w]].append((False, w, u, m))
        return inner, oriented(outer, min(nodes), self.directed)

    def judge(self, nodes: list[int]) -> Verdict:
        inner, outer = self.around(nodes)
        pair = lambda z, to, u, v: pair_of(u, z, self.directed) if to else pair_of(z, v, self.directed)
        held = {p for z, rows in outer.items() for to, u, v, _ in rows if (p := pair(z, to, u, v)) in self.edges}
        return judge(nodes, inner, outer, {z: self.sides[z] for z in outer}, held, self.world, self.directed, self.cfg, {u: self.sides[u] for u in nodes})

    def commit(self, nodes: list[int], v: Verdict) -> None:
        sid = min(nodes)
        own = set(nodes)
        w = self.world
        for u in nodes:
            s = self.sides.pop(u)
            w.out[s.out] -= 1
            w.loose[s.loose] -= 1
            for x, _ in self.out[u]:
                self.edges.pop((u, self.of[x]), None)
                self.edges.pop((self.of[x], u), None)
            for x, _ in self.into[u]:
                self.edges.pop((self.of[x], u), None)
                self.edges.pop((u, self.of[x]), None)
        for z, (o, l) in v.sides.items():
            s = self.sides[z]
            w.out[s.out] -= 1
            w.loose[s.loose] -= 1
            self.sides[z] = replace(s, out=o, loose=l)
            w.out[o] += 1
            w.loose[l] += 1
        self.sides[sid] = Side(len(nodes), v.glyph, v.hub, *v.own)
        w.out[v.own[0]] += 1
        w.loose[v.own[1]] += 1
        w.vs -= len(nodes) - 1
        w.bits = v.whole
        for u in own:
            self.of[u] = sid
        for a, b, m in v.edges:
            self.edges[sid if a == PART else a, sid if b == PART else b] = m
        if v.self_m is not None:
            self.edges[sid, sid] = v.self_m
        self.super[sid] = (self.label[sid], len(nodes), v.glyph, v.m, v.hub, v.self_m)
        self.delta += v.delta

    def run(self, sets: list[tuple[tuple[int, ...], float]]) -> None:
        self.follow(ranked(sets, self.cfg.max_candidates))

    def fork(self) -> Walk:
        """The same state, to go on apart; the graph itself is shared."""
        other = copy(self)
        other.of, other.sides, other.super, other.edges, other.marked = dict(self.of), dict(self.sides), dict(self.super), dict(self.edges), set(self.marked)
        other.world = replace(self.world, out=Counter(self.world.out), loose=Counter(self.world.loose))
        return other

    def follow(self, sets: list[tuple[tuple[int, ...], float]]) -> None:
        """Judge sets in the order given."""
        for ids, _ in sets:
            parts: dict[str, list[int]] = defaultdict(list)
            for u in ids:
                if u not in self.marked and u in self.label:
                    parts[self.label[u]].append(u)
            for label in sorted(parts, key=str):
                nodes = parts[label]
                if len(nodes) < 2:
                    continue
                v = self.judge(nodes)
                if v.delta < -1e-9:
                    self.commit(nodes, v)
                    self.marked.update(nodes)
                elif self.cfg.mark_policy == "always":
                    self.marked.update(nodes)

    def tables(self) -> tuple[list, list, list]:
        sn, loops = [], {a: m for (a, b), m in self.edges.items() if a == b}
        for sid in self.sides:
            if sid in self.super:
                sn.append((sid, *self.super[sid]))
            else:
                sn.append((sid, self.label[sid], 1, "disconnected", 1, None, loops.get(sid)))
        return sn, list(self.of.items()), [(a, b, m) for (a, b), m in self.edges.items()]


def as_summary(g: PropertyGraph, tables: tuple[list, list, list]) -> Summary:
    """A summary of rows on the driver."""
    widths = (len(schema.split(", ")) for schema in (SUPERNODES, MEMBERS, SUPEREDGES))
    return column_summary(g, tuple(list(zip(*rows, strict=True)) if rows else [()] * n for rows, n in zip(tables, widths, strict=True)))


def column_summary(g: PropertyGraph, tables: tuple[Sequence, Sequence, Sequence]) -> Summary:
    """A summary of columns on the driver; its tables are written once, as many plans read them."""
    spark = g.edges.sparkSession
    frames = []
    for columns, schema, name in zip(tables, (SUPERNODES, MEMBERS, SUPEREDGES), ("sn", "mem", "se"), strict=True):
        names = [c.split()[0] for c in schema.split(", ")]
        kinds = [pa.int64() if c.endswith("long") else pa.string() for c in schema.split(", ")]
        columns = [c.cast(k) if isinstance(c, pa.Array) else pa.array(c, k) for c, k in zip(columns, kinds, strict=True)]
        frames.append(settle(spark.createDataFrame(pa.table(columns, names)), name))
    return Summary(g, *frames)


def walk_order(cands: Candidates, cfg: SummaryConfig, b: int) -> list[tuple[tuple[int, ...], float]]:
    """The sets of a serial walk at b bands, in its order."""
    if cfg.nested:
        return [s for k in range(1, b + 1) for s in ranked(cands.of(k), cfg.max_candidates)]
    return ranked(cands.upto(b), cfg.max_candidates)


def walks(walk: Walk, orders: dict[int, list[tuple[tuple[int, ...], float]]], at: int = 0) -> Iterator[tuple[list[int], Walk]]:
    """The ends of several walks from one state, with the keys of all that end alike.

    What their orders have in common from place ``at`` on is walked once; where they part, the state is copied.
    """
    first, *others = orders.values()
    end = at
    for end in range(at, len(first) + 1):
        if any(o[end : end + 1] != first[end : end + 1] for o in others) or end == len(first):
            break
    walk.follow(first[at:end])
    ways: dict[tuple | None, list[int]] = {}
    for b, o in orders.items():
        ways.setdefault(o[end] if end < len(o) else None, []).append(b)
    for left, (way, bs) in zip(range(len(ways) - 1, -1, -1), ways.items(), strict=True):
        own = walk.fork() if left else walk
        if way is None:
            yield bs, own
        else:
            yield from walks(own, {b: orders[b] for b in bs}, end)


def serial(g: PropertyGraph, cfg: SummaryConfig) -> bool:
    """Whether the serial engine takes the graph: by ``engine``, or by the number of its edges."""
    return g.edges.limit(cfg.local_edges + 1).count() <= cfg.local_edges if cfg.engine == "auto" else cfg.engine == "serial"


def summarize(g: PropertyGraph, cfg: SummaryConfig = SummaryConfig(), candidates: Candidates | None = None) -> Summary:
    """A summary at resolution ``cfg.b``; ``engine="auto"`` walks serially up to ``local_edges`` edges, and in rounds beyond."""
    cands = candidates or candidates_of(g, cfg, cfg.b)
    if not serial(g, cfg):
        return summarize_rounds(g, cands.table(g.edges.sparkSession, cfg.b), cfg)
    walk = Walk(g, cfg)
    walk.follow(walk_order(cands, cfg, cfg.b))
    return as_summary(g, walk.tables())


def candidates_of(g: PropertyGraph, cfg: SummaryConfig, b: int) -> Candidates:
    return candidate_sets(g, cfg.r, b, cfg.filtered, cfg.seed, cfg.family, cfg.similarity, cfg.max_cluster, cfg.local_edges)


def resolutions(g: PropertyGraph, bs: tuple[int, ...] = (1, 2, 5, 10), cfg: SummaryConfig = SummaryConfig()) -> dict[int, Summary]:
    """One summary per number of bands, from one run of candidate generation; numbers whose walks are the same share one."""
    cands = candidates_of(g, cfg, max(bs))
    if not serial(g, cfg):
        return {b: summarize(g, replace(cfg, b=b), cands) for b in bs}
    out = {}
    for same, walk in walks(Walk(g, cfg), {b: walk_order(cands, cfg, b) for b in bs}):
        out |= dict.fromkeys(same, as_summary(g, walk.tables()))
    return {b: out[b] for b in bs}


# rounds


JUDGED = "pid long, delta double, local double, glyph string, hub long, m long, self_m long, ids array<long>, label string"


def summarize_rounds(g: PropertyGraph, sets: DataFrame, cfg: SummaryConfig) -> Summary:
    return rounds(g, sets, cfg)[0]


def rounds(g: PropertyGraph, sets: DataFrame, cfg: SummaryConfig) -> tuple[Summary, float]:
    """Rounds of parts whose every free node has no better-ranked candidate left; node ids are not negative.

    sets: (ids, size, quality). Node conflicts resolve as in rank order. All parts of a
    round are judged by joins against the summary at its start; counts of the whole
    summary are one row. Every round settles the best-ranked part there is, so rounds go
    on until no candidate is left. Tables and shuffles of a round are dropped once the next
    has its own. Also returns the change of the bits: exact with
    ``isolation="neighbours"``, where no two parts of a round are adjacent, an estimate
    with ``"nodes"``.
    """
    ranks = numbered(sets.select("ids", "size", "quality"), [F.desc(F.col("size") * F.col("quality")), F.desc("size"), "ids"], name="ranked_sets")
    if cfg.max_candidates:
        ranks = ranks.where(F.col("rank") < cfg.max_candidates)
    cand = settle(ranks.select("rank", F.explode("ids").alias("id")).join(g.nodes, "id").select("rank", "id", "label"), "cand")
    e = g.edges if hasattr(g.edges, "_settled_at") else settle(g.edges, "edges")
    pause = large(e)
    sn = settle(identity_summary(g).supernodes.select("sid", "label", "size", "glyph", "m", "hub", "self_m"), "sn")
    mem = settle(g.nodes.select("id", F.col("id").alias("sid")), "mem")
    se = e.select(F.col("src").alias("ssid"), F.col("dst").alias("dsid"), "m")
    v_count = g.nodes.count()
    n_labels = max(1, g.nodes.select("label").distinct().count())
    counts = settle(held_counts(sn, se), "counts")
    world, delta = world_of(counts, v_count, n_labels), 0.0
    while not cand.isEmpty():
        first = cand.groupBy("id").agg(F.min("rank").alias("first"))
        ready = cand.join(first, "id").groupBy("rank").agg(F.max(F.col("rank") > F.col("first")).alias("waits")).where("not waits").select("rank")
        active = settle(cand.join(ready, "rank").select("rank", "id", "label"), "active")
        parts = active.groupBy("rank", "label").agg(F.min("id").alias("pid"), F.count("*").alias("n"))
        part_of = active.join(parts.where("n > 1"), ["rank", "label"]).select("id", "pid", "label", "rank")
        if cfg.isolation == "neighbours":
            every = settle(part_of, "parts")
            part_of = isolated(every, e)
        part_of = settle(part_of, "parts")
        old = [cand, active, part_of]
        judged = settle(judge_round(part_of, e, mem, sn, se, counts, world, g.directed, cfg), "judged")
        good = judged.where("delta < -1e-9")
        moved = settle(good.select(F.explode("ids").alias("id"), F.col("pid").alias("to")), "moved")
        old += [judged, moved, *([every] if cfg.isolation == "neighbours" else [])]
        if not moved.isEmpty():
            old += [mem, sn, se, counts]
            gone = moved.select(F.col("id").alias("sid"))
            mem = settle(mem.join(few(moved), "id", "left").select("id", F.coalesce("to", "sid").alias("sid")), "mem")
            fresh = good.select(F.col("pid").alias("sid"), "label", F.size("ids").cast("long").alias("size"), "glyph", "m", "hub", "self_m")
            sn = settle(sn.join(gone, "sid", "left_anti").unionByName(fresh), "sn")
            se = settle(rebundle(se, moved, e, mem, sn, world, g.directed, cfg), "se")
            counts = settle(held_counts(sn, se), "counts")
            was, world = world, world_of(counts, v_count, n_labels)
            delta += good.agg(F.sum("local")).first()[0] + global_bits(world.vs, world.out, world.loose, cfg) - global_bits(was.vs, was.out, was.loose, cfg)
        # parts that were judged are done, those that must wait for a neighbour stay
        alone = active.join(parts.where("n = 1").select("rank", "label"), ["rank", "label"], "left_semi")
        done = part_of.select("rank", "label").unionByName(alone.select("rank", "label")).distinct()
        used = (part_of if cfg.mark_policy == "always" else moved).select("id").distinct()  # a single node left over stays free
        cand = settle(cand.join(used, "id", "left_anti").join(done, ["rank", "label"], "left_anti").select("rank", "id", "label"), "cand")
        discard(*old)
        if pause:
            release(g.edges.sparkSession)
    return Summary(g, sn, mem, se.where("m is not null")), delta


def world_of(counts: DataFrame, v_count: int, n_labels: int) -> World:
    """Sizes and histograms of a summary; the driver holds a number per distinct count."""
    hist = {c: Counter(dict(map(tuple, counts.groupBy(c).count().collect()))) for c in ("out", "loose")}
    return World(v_count, n_labels, sum(hist["out"].values()), hist["out"], hist["loose"])


def isolated(part_of: DataFrame, e: DataFrame) -> DataFrame:
    """Parts no better-numbered part of the round is adjacent to."""
    own = few(part_of)
    x = e.join(own.select(F.col("id").alias("src"), F.col("pid").alias("a")), "src").join(own.select(F.col("id").alias("dst"), F.col("pid").alias("b")), "dst").where("a <> b")
    late = x.select(F.greatest("a", "b").alias("pid")).distinct()
    return part_of.join(late, "pid", "left_anti").select("id", "pid", "label", "rank")


def held_counts(sn: DataFrame, se: DataFrame) -> DataFrame:
    """``(sid, out, loose)``: super-edges each super-node holds, and its targets that have none: rows without m."""
    held = se.groupBy(F.col("ssid").alias("sid")).agg(F.count("m").alias("out"), F.count_if(F.col("m").isNull()).alias("loose"))
    return sn.select("sid").join(held, "sid", "left").na.fill(0, ["out", "loose"])


def judge_round(part_of: DataFrame, e: DataFrame, mem: DataFrame, sn: DataFrame, se: DataFrame, counts: DataFrame, world: World, directed: bool, cfg: SummaryConfig) -> DataFrame:
    """Verdicts of all parts: each gets its incident edges and the super-nodes at their other ends."""
    info = sn.join(counts, "sid").select(F.col("sid").alias("z"), F.col("size").alias("z_size"), F.col("glyph").alias("z_glyph"), F.coalesce("hub", F.lit(-1)).alias("z_hub"), F.col("out").alias("z_out"), F.col("loose").alias("z_loose"))
    own, mem = few(part_of), few(mem)
    src, dst = own.select(F.col("id").alias("src"), F.col("pid").alias("p")), own.select(F.col("id").alias("dst"), F.col("pid").alias("q"))
    z = lambda end: mem.select(F.col("id").alias(end), F.col("sid").alias(f"z_{end}"))
    x = e.join(src, "src", "left").join(dst, "dst", "left").where("p is not null or q is not null").join(z("src"), "src").join(z("dst"), "dst")
    a, b = (F.col("z_src"), F.col("z_dst")) if directed else (F.least("z_src", "z_dst"), F.greatest("z_src", "z_dst"))
    kept = se.where("m is not null")
    if own is not part_of:  # only super-edges of its free nodes matter; the parts are few, so none is shuffled to find them
        at = lambda end: own.select(F.col("id").alias(end), F.lit(True).alias(f"at_{end}"))
        kept = kept.join(at("ssid"), "ssid", "left").join(at("dsid"), "dsid", "left").where("at_ssid or at_dsid")
    kept = kept.select(F.col("ssid").alias("a"), F.col("dsid").alias("b"), F.lit(True).alias("kept"))
    x = x.withColumns({"a": a, "b": b}).join(kept, ["a", "b"], "left").withColumn("held", F.coalesce("kept", F.lit(False)))
    inside = F.col("p").eqNullSafe(F.col("q"))
    to = x.where("p is not null").select(F.col("p").alias("pid"), "src", "dst", "m", "held", F.when(inside, "in").otherwise("to").alias("way"), F.col("z_dst").alias("z"))
    back = x.where("q is not null").where(~inside).select(F.col("q").alias("pid"), "src", "dst", "m", "held", F.lit("from").alias("way"), F.col("z_src").alias("z"))
    rows = to.unionByName(back).join(info, "z")
    own = part_of.join(counts.withColumnRenamed("sid", "id"), "id")
    zero = F.lit(0).cast("long")
    own = own.select("pid", F.col("id").alias("src"), zero.alias("dst"), zero.alias("m"), F.lit(True).alias("held"), F.lit("node").alias("way"), F.col("id").alias("z"), F.lit(1).cast("long").alias("z_size"), F.col("label").alias("z_glyph"), F.lit(-1).cast("long").alias("z_hub"), F.col("out").alias("z_out"), F.col("loose").alias("z_loose"))

    def one(pid: int, rows_of: list[tuple]) -> tuple:
        singles, inner, outer, sides, held, label = {}, [], defaultdict(list), {}, set(), None
        for u, v, m, is_held, way, z_, size, glyph, hub, out, loose in rows_of:
            if way == "node":
                singles[u], label = Side(out=out, loose=loose), glyph
                continue
            if way == "in":
                inner.append((u, v, m))
                continue
            to_ = way == "to"
            sides[z_] = Side(size, glyph, None if hub < 0 else hub, out, loose)
            outer[z_].append((to_, u, v, m))
            if is_held:
                held.add(pair_of(u, z_, directed) if to_ else pair_of(z_, v, directed))
        nodes = sorted(singles)
        v = judge(nodes, inner, oriented(outer, pid, directed), sides, held, world, directed, cfg, singles)
        return pid, v.delta, v.local, v.glyph, v.hub, v.m, v.self_m, nodes, label

    names = ("src", "dst", "m", "held", "way", "z", "z_size", "z_glyph", "z_hub", "z_out", "z_loose")

    def kernel(df: pd.DataFrame) -> pd.DataFrame:
        """All parts of one cell."""
        own_rows = defaultdict(list)
        for pid, *row in zip(df["pid"].tolist(), *(df[c].tolist() for c in names), strict=True):
            own_rows[pid].append(row)
        out = pd.DataFrame([one(pid, x) for pid, x in own_rows.items()], columns=[c.split()[0] for c in JUDGED.split(", ")])
        return out.astype({"hub": "Int64", "self_m": "Int64"})

    cells = 16 * int(e.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.select(own.columns).unionByName(own).groupBy(F.pmod(F.xxhash64("pid"), F.lit(cells)).alias("cell")).applyInPandas(kernel, JUDGED)


def rebundle(se: DataFrame, moved: DataFrame, e: DataFrame, mem: DataFrame, sn: DataFrame, world: World, directed: bool, cfg: SummaryConfig) -> DataFrame:
    """Super-edges after a round: those away from it stay, bundles that it touched are decided again; m is null where there is none."""
    moved, mem = few(moved), few(mem)
    gone, touched = moved.select(F.col("id").alias("sid")), moved.select(F.col("to").alias("sid")).distinct()
    far = se.join(gone.withColumnRenamed("sid", "ssid"), "ssid", "left_anti").join(gone.withColumnRenamed("sid", "dsid"), "dsid", "left_anti")
    a, b = mem.select(F.col("id").alias("src"), F.col("sid").alias("a")), mem.select(F.col("id").alias("dst"), F.col("sid").alias("b"))
    at = lambda end: moved.select(F.col("id").alias(end), F.lit(True).alias(f"at_{end}"))
    x = e.join(at("src"), "src", "left").join(at("dst"), "dst", "left").where("at_src or at_dst").select("src", "dst", "m")
    x = x.join(a, "src").join(b, "dst").where("a <> b")
    if not directed:
        flip = F.col("a") > F.col("b")
        x = x.select(F.when(flip, F.col("dst")).otherwise(F.col("src")).alias("src"), F.when(flip, F.col("src")).otherwise(F.col("dst")).alias("dst"), "m", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    side = lambda c: sn.select(F.col("sid").alias(c), F.col("size").alias(f"{c}_size"), F.col("glyph").alias(f"{c}_glyph"), F.coalesce("hub", F.lit(-1)).alias(f"{c}_hub"))
    sn = few(sn)
    x = x.select("src", "dst", "m", "a", "b").join(side("a"), "a").join(side("b"), "b")
    cells = 16 * int(e.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def decide(df: pd.DataFrame) -> pd.DataFrame:
        """All bundles of one cell."""
        rows, ends = defaultdict(list), {}
        for a_, b_, *row in zip(*(df[c].tolist() for c in ("a", "b", "src", "dst", "m")), strict=True):
            rows[a_, b_].append(row)
        for c in ("a", "b"):
            for sid, size, glyph, hub in df[[c, f"{c}_size", f"{c}_glyph", f"{c}_hub"]].drop_duplicates(c).itertuples(index=False, name=None):
                ends[sid] = (size, glyph, None if hub < 0 else hub)
        out = []
        for (a_, b_), own in rows.items():
            with_, without, rep = bundle(own, ends[a_], ends[b_], cfg)
            out.append((a_, b_, rep if with_ + membership(world, cfg) < without else None))
        return pd.DataFrame({"ssid": [a_ for a_, _, _ in out], "dsid": [b_ for _, b_, _ in out], "m": pd.array([m for *_, m in out], "Int64")})

    fresh = x.groupBy(F.pmod(F.xxhash64("a", "b"), F.lit(cells)).alias("cell")).applyInPandas(decide, SUPEREDGES)
    loops = sn.join(touched, "sid", "left_semi").where("self_m is not null").select(F.col("sid").alias("ssid"), F.col("sid").alias("dsid"), F.col("self_m").alias("m"))
    return far.select("ssid", "dsid", "m").unionByName(fresh).unionByName(loops)
