"""Measures of summaries and of the methods that make them."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from glyphfold.operators import baselines, ledger, merge
from glyphfold.operators.candidates import candidate_sets, lsh_clusters, minhash
from glyphfold.operators.ordering import node_draw, numbered
from glyphfold.operators.similarity import exact_simpairs
from glyphfold.operators.summary import Summary
from glyphfold.sources.graphs import PropertyGraph


def ratio(before: float, after: float) -> float:
    return (before - after) / before if before else 0.0


def compression_ratio(s: Summary, form: str = "printed") -> float:
    """Share of the bits of the plain graph that the summary saves."""
    return ratio(ledger.bits_before(s.graph)[form], ledger.ledgers(s)[form])


def timed(fn: Callable[[], DataFrame | Summary]) -> tuple[float, object]:
    """Wall seconds of a method; results are forced through a sink that keeps nothing."""
    began = time.time()
    out = fn()
    for df in (out.supernodes, out.members, out.superedges) if isinstance(out, Summary) else [out]:
        if isinstance(df, DataFrame):
            df.write.format("noop").mode("overwrite").save()
    return time.time() - began, out


def method_bits(g: PropertyGraph, method: str, cfg: merge.SummaryConfig = merge.SummaryConfig()) -> dict:
    """Seconds, bits before and after, and ratio of one method in its own code.

    ``common_ratio`` prices its super-graph with the ledger, multiplicities of the graph
    included; a vocabulary of structures makes no super-graph and has none.
    """
    if method == "fold":
        secs, s = timed(lambda: merge.summarize(g, cfg))
        before, after = ledger.bits_before(g)["printed"], ledger.ledgers(s)["printed"]
        common = ratio(before, after)
    elif method == "pairmerge":
        flat = g.simplify({"M"})
        secs, s = timed(lambda: baselines.pairmerge_randomized(flat, cfg.seed))
        v, e = g.nodes.count(), g.edges.count()
        import math

        before, after = e * 2 * math.log2(max(v, 2)), baselines.pairmerge_cost(s).first().bits
        common = ratio(ledger.bits_before(g)["printed"], ledger.ledgers(replace(s, graph=g))["printed"])
    else:
        simple = g.simplify({"L", "M", "D", "S"})
        secs, words = timed(lambda: baselines.vocab_summary(simple, method.removeprefix("vocab_")))
        before, after, common = words.attrs["before"], words.attrs["bits"], None
    return {"method": method, "b": cfg.b if method == "fold" else None, "seconds": secs, "before": before, "bits": after, "ratio": ratio(before, after), "common_ratio": common}


def tradeoff(spark: SparkSession, g: PropertyGraph, bs: tuple[int, ...] = (1, 2, 5, 10), methods: tuple[str, ...] = ("pairmerge",), cfg: merge.SummaryConfig = merge.SummaryConfig()) -> DataFrame:
    """Ratio against time over the number of bands, and of the baselines, in each one's own code and in a common one."""
    rows = [method_bits(g, "fold", replace(cfg, b=b)) for b in bs] + [method_bits(g, m, cfg) for m in methods]
    return spark.createDataFrame([(g.name, r["method"], r["b"], r["seconds"], r["before"], r["bits"], r["ratio"], r["common_ratio"]) for r in rows], "graph string, method string, b int, seconds double, before double, bits double, ratio double, common_ratio double")


def size_reduction(s: Summary) -> DataFrame:
    """How many times fewer nodes and edges the picture has."""
    sn, se = s.supernodes.agg(F.count("*").alias("supernodes"), F.sum("size").alias("nodes")), s.superedges.agg(F.count("*").alias("superedges"))
    e = s.graph.edges.agg(F.count("*").alias("edges"))
    return sn.crossJoin(se).crossJoin(e).select("nodes", "supernodes", "edges", "superedges", (F.col("nodes") / F.col("supernodes")).alias("node_factor"), (F.col("edges") / F.greatest("superedges", F.lit(1))).alias("edge_factor"))


def glyph_breakdown(s: Summary, unit: str = "nodes") -> DataFrame:
    """Share of each label's nodes (or super-nodes) in cliques, disconnected sets, stars, and single."""
    kind = F.when(F.col("size") == 1, "single").when(F.col("glyph").isin("in_star", "out_star"), "star").otherwise(F.col("glyph"))
    w = F.col("size") if unit == "nodes" else F.lit(1)
    t = s.supernodes.select("label", kind.alias("kind"), w.alias("w")).groupBy("label").pivot("kind", ["clique", "disconnected", "star", "single"]).agg(F.sum("w"))
    t = t.na.fill(0)
    total = F.col("clique") + F.col("disconnected") + F.col("star") + F.col("single")
    return t.select("label", total.alias("n"), *(F.round(F.col(k) / total, 6).alias(k) for k in ("clique", "disconnected", "star", "single")))


def shuffled(g: PropertyGraph, seed: int) -> PropertyGraph:
    """Labels permuted among the nodes; their counts stay."""
    a = numbered(g.nodes.select("id"), ["id"], "r")
    b = numbered(g.nodes.select("label", "id", node_draw(F.col("id"), seed).alias("draw")), ["draw", "id"], "r")
    return replace(g, nodes=a.join(b.select("r", "label"), "r").select("id", "label"))


def label_ratio(g: PropertyGraph, cands, cfg: merge.SummaryConfig, nodes=None, edges=None) -> float:
    """Ratio of one labelling from shared candidates; bits follow from the walk's exact change."""
    walk = merge.Walk(g, cfg, nodes, edges)
    before = ledger_of_identity(walk)
    walk.run(cands.upto(cfg.b))
    return -walk.delta / before if before else 0.0


def ledger_of_identity(walk: merge.Walk) -> float:
    """Printed bits of the plain graph from the walk's start state."""
    from glyphfold.functions.bits import n_int_bits

    w, cfg = walk.world, walk.cfg
    if not w.v:
        return 0.0
    bits = merge.global_bits(w.vs, w.out, w.loose, cfg) + n_int_bits(w.n_labels)
    bits += w.v * merge.own_bits(1, "disconnected", 1, w.v, w.n_labels)
    return bits + sum(1 + n_int_bits(m) for m in walk.edges.values())


def shuffled_ratio(g: PropertyGraph, n: int = 20, seed: int = 42, cfg: merge.SummaryConfig = merge.SummaryConfig(), cands=None) -> float:
    """Mean ratio over label shuffles; candidates don't depend on labels and are shared."""
    import numpy as np

    cands = cands or candidate_sets(g, cfg.r, cfg.b, cfg.filtered, cfg.seed)
    nodes, edges = g.nodes.orderBy("id").toPandas(), g.edges.toPandas()
    out = []
    for k in range(n):
        mixed = nodes.assign(label=np.random.default_rng(seed + k).permutation(nodes["label"].to_numpy()))
        out.append(label_ratio(g, cands, cfg, mixed, edges))
    return sum(out) / len(out)


def normalized_gain(actual: float, by_chance: float) -> float:
    return (actual - by_chance) / (1 - by_chance)


def evaluate_labelling(spark: SparkSession, graphs: dict[str, PropertyGraph], n: int = 20, cfg: merge.SummaryConfig = merge.SummaryConfig()) -> DataFrame:
    """Shuffled and actual ratio, and gain, of each labelling of one graph."""
    rows, cands = [], None
    for name, g in graphs.items():
        cands = cands or candidate_sets(g, cfg.r, cfg.b, cfg.filtered, cfg.seed)
        actual, chance = label_ratio(g, cands, cfg), shuffled_ratio(g, n, cfg.seed, cfg, cands)
        rows.append((g.name, name, chance, actual, normalized_gain(actual, chance), actual - chance))
    return spark.createDataFrame(rows, "graph string, labelling string, shuffled double, actual double, gain double, difference double")


def vote_entropy(votes: DataFrame, group: str) -> DataFrame:
    """Entropy in nats of each ballot within each group; votes has (group, ballot, yes boolean)."""
    p = votes.groupBy(group, "ballot").agg(F.avg(F.col("yes").cast("double")).alias("p"), F.count("*").alias("n"))
    h = lambda x: F.when((x > 0) & (x < 1), -x * F.log(x)).otherwise(0.0)
    return p.select(group, "ballot", "n", F.round(h(F.col("p")) + h(1 - F.col("p")), 6).alias("entropy"))


def entropy_summary(entropies: DataFrame, group: str, contested: float = 0.68) -> DataFrame:
    """Median, number of contested ballots (near ln 2), and a histogram of ten bins."""
    bins = [F.count_if(F.width_bucket("entropy", F.lit(0.0), F.lit(0.6931472), F.lit(10)) == i).alias(f"bin_{i}") for i in range(1, 11)]
    return entropies.groupBy(group).agg(F.round(F.percentile("entropy", F.lit(0.5)), 6).alias("median"), F.count_if(F.col("entropy") >= contested).alias("contested"), *bins)


def scaling_slope(points: DataFrame) -> DataFrame:
    """Slope of log seconds over log edges; points has (edges, seconds)."""
    return points.agg(F.regr_slope(F.log("seconds"), F.log("edges")).alias("slope"), F.count("*").alias("points"))


def lsh_quality(g: PropertyGraph, r: int, b: int, seed: int = 42) -> DataFrame:
    """Recall of the verified pairs and false alarms of the clusters, against all pairs."""
    t = (1 / b) ** (1 / r)
    exact = exact_simpairs(g, t).select("a", "b")
    cl = lsh_clusters(minhash(g, r, b, seed=seed), r, b)
    x, y = cl.select(F.col("id").alias("a"), "cluster"), cl.select(F.col("id").alias("b"), "cluster")
    found = exact.join(x, "a", "left").join(y.withColumnRenamed("cluster", "cb"), "b", "left").agg(F.count("*").alias("pairs"), F.count_if(F.col("cluster") == F.col("cb")).alias("found"))
    together = cl.groupBy("cluster").agg((F.count("*") * (F.count("*") - 1) / 2).alias("k")).agg(F.coalesce(F.sum("k"), F.lit(0.0)).alias("together"))
    return found.crossJoin(together).select("pairs", "found", "together", (F.col("found") / F.col("pairs")).alias("recall"), (1 - F.col("found") / F.col("together")).alias("false_alarms"))


def collision_rate(g: PropertyGraph, rows: int = 64, seed: int = 42) -> DataFrame:
    """Share of equal signature rows of each pair, next to its similarity."""
    sig = minhash(g, rows, 1, seed=seed)
    cols = [f"h_{i}" for i in range(rows)]
    x = sig.select(F.col("id").alias("a"), *(F.col(c).alias(f"x_{c}") for c in cols))
    y = sig.select(F.col("id").alias("b"), *(F.col(c).alias(f"y_{c}") for c in cols))
    same = sum((F.col(f"x_{c}") == F.col(f"y_{c}")).cast("int") for c in cols)
    return exact_simpairs(g).join(x, "a").join(y, "b").select("a", "b", "jd", (same / rows).alias("rate"))


def bridge_rate(s: Summary, mixed: str = "mixed") -> DataFrame:
    """Share of unmerged nodes of the mixed label that touch two or more other labels."""
    single = s.supernodes.where((F.col("size") == 1) & (F.col("label") == mixed)).select(F.col("sid").alias("u"))
    both = s.graph.edges.select(F.col("src").alias("u"), F.col("dst").alias("v")).union(s.graph.edges.select("dst", "src"))
    near = both.join(s.graph.nodes.select(F.col("id").alias("v"), "label"), "v").groupBy("u").agg(F.countDistinct("label").alias("k"))
    return single.join(near, "u", "left").agg(F.count("*").alias("single"), F.count_if(F.col("k") >= 2).alias("bridges"))


def group_flow(s: Summary) -> DataFrame:
    """In and out multiplicity of each super-node over its super-edges."""
    e = s.superedges.where("ssid <> dsid")
    out, inn = e.groupBy(F.col("ssid").alias("sid")).agg(F.sum("m").alias("out_m")), e.groupBy(F.col("dsid").alias("sid")).agg(F.sum("m").alias("in_m"))
    return s.supernodes.select("sid", "label", "size", "glyph").join(out, "sid", "left").join(inn, "sid", "left").na.fill(0, ["out_m", "in_m"])


def ablation_rep(edges: DataFrame) -> DataFrame:
    """Bits of each way to choose a representative, over bags (key, m)."""
    rows = edges.groupBy("key").agg(F.collect_list("m").alias("bag"))

    def costs(it):
        import pandas as pd

        for df in it:
            out = {k: [] for k in ("key", "exact", "dichotomous", "median", "mode", "mean")}
            for key, bag in zip(df["key"], df["bag"], strict=True):
                out["key"].append(key)
                for how in ("exact", "dichotomous", "median", "mode", "mean"):
                    bag_ = [int(x) for x in bag]
                    out[how].append(merge.bag_cost(bag_, merge.rep_of(bag_, how)))
            yield pd.DataFrame(out)

    each = rows.mapInPandas(costs, "key string, exact double, dichotomous double, median double, mode double, mean double")
    return each.agg(F.count("*").alias("bags"), F.avg((F.col("dichotomous") <= F.col("exact") + 1e-9).cast("double")).alias("optimal_share"), *(F.sum(c).alias(c) for c in ("exact", "dichotomous", "median", "mode", "mean")))


def ablation_glyph(g: PropertyGraph, cfg: merge.SummaryConfig = merge.SummaryConfig()) -> dict[str, float]:
    """Ratio with the glyph rule and with the true best glyph."""
    cands = candidate_sets(g, cfg.r, cfg.b, cfg.filtered, cfg.seed)
    return {rule: label_ratio(g, cands, replace(cfg, glyph_rule=rule)) for rule in ("proxy", "best")}
