"""The experiments, each a function of (spark, folder of tables)."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from glyphfold.operators import baselines, measures, merge, synth
from glyphfold.operators.candidates import candidate_sets
from glyphfold.operators.ordering import numbered
from glyphfold.operators.summary import Summary, drawing_nodes
from glyphfold.session import settle, table
from glyphfold.sources import graphs

CFG = merge.SummaryConfig()


def built(spark: SparkSession, d: str, name: str, **kw) -> graphs.PropertyGraph:
    """A workload graph with its tables written once."""
    g = graphs.BUILDERS[name](spark, d, **kw)
    edges = settle(g.edges, f"{name}_e")
    return replace(g, nodes=settle(g.nodes_of(edges) if g.nodes_of else g.nodes, f"{name}_v"), edges=edges, nodes_of=None)


def summary_of(spark: SparkSession, d: str, name: str, b: int, **cfg) -> Summary:
    return merge.summarize(built(spark, d, name), replace(CFG, b=b, **cfg))


def dominance_case(spark: SparkSession, d: str) -> DataFrame:
    """A small two-label multigraph: super-nodes, their shapes, and what flows in and out."""
    return measures.group_flow(summary_of(spark, d, "handover", 10))


def coarse_case(spark: SparkSession, d: str) -> DataFrame:
    """How far a coarse summary of the link graph shrinks the picture."""
    return measures.size_reduction(summary_of(spark, d, "host_links", 10))


def top_single_hosts(spark: SparkSession, d: str, k: int = 10) -> DataFrame:
    """Unmerged hosts of the highest degree, by name."""
    s = summary_of(spark, d, "host_links", 10)
    deg = s.graph.edges.groupBy(F.col("src").alias("sid")).agg(F.count("*").alias("degree"))
    single = s.supernodes.where("size = 1").join(deg, "sid").join(graphs.host_names(spark, d).withColumnRenamed("id", "sid"), "sid")
    return single.select("name", "label", "degree").orderBy(F.desc("degree"), "name").limit(k)


def area_breakdown(spark: SparkSession, d: str) -> DataFrame:
    """Share of each area's nodes by kind of super-node."""
    return measures.glyph_breakdown(summary_of(spark, d, "order_coitem", 5))


def area_bridges(spark: SparkSession, d: str) -> DataFrame:
    return measures.bridge_rate(summary_of(spark, d, "order_coitem", 5))


def two_resolutions(spark: SparkSession, d: str) -> DataFrame:
    """The similarity graph at a high and a low resolution."""
    g = built(spark, d, "vote_sim")
    out = None
    for b, s in merge.resolutions(g, (2, 5)).items():
        row = drawing_nodes(s).groupBy("label", "glyph").agg(F.count("*").alias("supernodes"), F.sum("size").alias("nodes")).withColumn("b", F.lit(b))
        out = row if out is None else out.unionByName(row)
    return out


def ballots(spark: SparkSession, d: str) -> DataFrame:
    """Signs of the embedding's entries as votes."""
    v = table(spark, d, "embeddings").select(F.col("label").cast("long").alias("label"), F.posexplode("embedding").alias("ballot", "x"))
    return v.select("label", F.col("ballot").cast("long").alias("ballot"), (F.col("x") > 0).alias("yes"))


def vote_entropies(spark: SparkSession, d: str) -> DataFrame:
    return measures.vote_entropy(ballots(spark, d), "label")


def vote_entropy_summary(spark: SparkSession, d: str) -> DataFrame:
    return measures.entropy_summary(vote_entropies(spark, d), "label")


def labelling_study(spark: SparkSession, d: str, name: str, n: int = 20, b: int = 5) -> DataFrame:
    """Two labellings of one graph against shuffled labels."""
    first = built(spark, d, name)
    second = replace(first, nodes=settle(graphs.BUILDERS[name](spark, d, labels="B").nodes, "labels_b"))
    return measures.evaluate_labelling(spark, {"A": first, "B": second}, n, replace(CFG, b=b))


def tradeoff_of(spark: SparkSession, d: str, name: str, methods: tuple[str, ...], drop: str = "", bs: tuple[int, ...] = (1, 2, 5, 10)) -> DataFrame:
    """Ratio and seconds of all methods on one graph; ``drop`` gives up traits first."""
    return measures.tradeoff(spark, built(spark, d, name).simplify(set(drop)), bs, methods)


def label_gains(spark: SparkSession, d: str) -> DataFrame:
    """For both labellings of the trade graph: share of trade inside a label, the share by chance, and the gain over it."""
    out = None
    for labelling in ("A", "B"):
        g = graphs.trade_nation(spark, d, labels=labelling)
        x, y = g.nodes.select(F.col("id").alias("src"), F.col("label").alias("x")), g.nodes.select(F.col("id").alias("dst"), F.col("label").alias("y"))
        flow = settle(g.edges.join(x, "src").join(y, "dst").groupBy("x", "y").agg(F.sum("m").cast("double").alias("m")), "label_flow")
        ends = flow.groupBy(F.col("x").alias("label")).agg(F.sum("m").alias("o")).join(flow.groupBy(F.col("y").alias("label")).agg(F.sum("m").alias("i")), "label")
        total = flow.agg(F.sum("m").alias("total"), F.sum(F.when(F.col("x") == F.col("y"), F.col("m"))).alias("inside"))
        row = ends.agg(F.sum(F.col("o") * F.col("i")).alias("both")).crossJoin(total)
        actual, chance = F.col("inside") / F.col("total"), F.col("both") / (F.col("total") * F.col("total"))
        row = row.select(F.lit(labelling).alias("labelling"), F.round(actual, 6).alias("actual"), F.round(chance, 6).alias("by_chance"), F.round(measures.normalized_gain(actual, chance), 4).alias("gain"))
        out = row if out is None else out.unionByName(row)
    return out


def customer_growth(spark: SparkSession, d: str, k: int = 10) -> DataFrame:
    """Edges of a growth graph of the customers: in the order of keys, each sends k edges to earlier ones."""
    who = numbered(table(spark, d, "customer").select("c_custkey"), ["c_custkey"], "node", name="growth_nodes")
    return synth.kout_edges(spark, 0, k, nodes=who.select("node"))


def growth_scaling(spark: SparkSession, sizes: tuple[int, ...] = (500, 1000, 2000, 4000, 8000), pairwise: tuple[int, ...] = (125, 250, 500), k: int = 10, b: int = 3) -> DataFrame:
    """Seconds against size on generated growth graphs, of the method and (on smaller ones) of the pairwise baseline."""
    rows = []
    for method, n in [("fold", n) for n in sizes] + [("pairmerge", n) for n in pairwise]:
        g = synth.synth_kout(spark, n, k)
        g = replace(g, nodes=settle(g.nodes, "kout_v"), edges=settle(g.edges, "kout_e"))
        make = (lambda g=g: merge.summarize(g, replace(CFG, b=b))) if method == "fold" else (lambda g=g: baselines.pairmerge_randomized(g))
        secs, s = measures.timed(make)
        rows.append((method, n, g.edges.count(), secs, s.supernodes.count()))
    return spark.createDataFrame(rows, "method string, nodes long, edges long, seconds double, supernodes long")


def growth_slopes(spark: SparkSession, sizes: tuple[int, ...] = (2000, 8000, 32000)) -> DataFrame:
    """Slope of log seconds over log edges; the largest sizes tell most, as small ones show a job's fixed cost."""
    points = growth_scaling(spark, sizes, ())
    return points.groupBy("method").agg(F.regr_slope(F.log("seconds"), F.log("edges")).alias("slope"), F.count("*").alias("points"))


def sampling_scaling(spark: SparkSession, d: str, fracs: tuple[float, ...] = tuple(i / 10 for i in range(1, 11)), b: int = 3, name: str = "order_coitem") -> DataFrame:
    """Seconds against edges on growing samples with all nodes kept."""
    g = built(spark, d, name)
    rows = []
    for f in fracs:
        part = synth.sample_edges(g, f)
        secs, s = measures.timed(lambda part=part: merge.summarize(part, replace(CFG, b=b)))
        rows.append((f, part.edges.count(), secs, s.supernodes.count()))
    return spark.createDataFrame(rows, "fraction double, edges long, seconds double, supernodes long")


def ratios_by_resolution(spark: SparkSession, d: str, name: str, bs: tuple[int, ...] = (1, 2, 5, 10)) -> DataFrame:
    """Printed and sound ratio, super-nodes and super-edges for each number of bands."""
    from glyphfold.operators import ledger

    g = built(spark, d, name)
    before = ledger.bits_before(g)
    rows, priced = [], {}
    for b, s in merge.resolutions(g, bs).items():
        if id(s) not in priced:  # numbers of bands may share a summary
            priced[id(s)] = ledger.ledgers(s), s.supernodes.count(), s.superedges.count()
        after, *counts = priced[id(s)]
        rows.append((name, b, *counts, before["printed"], after["printed"], measures.ratio(before["printed"], after["printed"]), measures.ratio(before["sound"], after["sound"])))
    return spark.createDataFrame(rows, "graph string, b int, supernodes long, superedges long, before double, after double, ratio double, sound_ratio double")


def planted_recall(spark: SparkSession, groups: int = 30, size: int = 6) -> DataFrame:
    """Planted groups whose members (a star's hub aside) share a super-node, and with which glyph most do.

    Spokes outrank their star: they are fully alike, the hub is not, so it stays out.
    """
    rows = []
    for kind in ("clique", "in_star", "out_star", "biclique"):
        g = synth.synth_planted(spark, kind, groups, size, context=8)
        s = merge.summarize(replace(g, nodes=settle(g.nodes, "pl_v"), edges=settle(g.edges, "pl_e")), replace(CFG, b=5))
        found = s.supernodes.where((F.col("label") == "member") & (F.col("size") >= size - 1)).groupBy("glyph").count().orderBy(F.desc("count")).collect()
        hit = sum(r["count"] for r in found)
        rows.append((kind, groups, hit, hit / groups, found[0].glyph if found else None))
    return spark.createDataFrame(rows, "kind string, planted int, found int, recall double, glyph string")


def shuffle_histogram(spark: SparkSession, d: str, name: str = "trade_nation", seed: int = 42) -> DataFrame:
    """A label shuffle keeps every label's count."""
    return measures.shuffled(graphs.BUILDERS[name](spark, d), seed).nodes.groupBy("label").agg(F.count("*").alias("n"))


def candidate_report(spark: SparkSession, d: str, name: str, b_max: int = 10, filtered: bool = True) -> DataFrame:
    """New candidate sets of each round: how many, the largest, and their least quality."""
    c = candidate_sets(built(spark, d, name), CFG.r, b_max, filtered)
    rows = [(name, b, len(s), max((len(ids) for ids, _ in s), default=0), min((q for _, q in s), default=None)) for b, s in c.sets.items()]
    return spark.createDataFrame(rows, "graph string, b int, sets int, largest int, quality double")
