"""Property graphs: model, traits, and the workload graphs built from the given tables."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from glyphfold.session import table


@dataclass(frozen=True)
class PropertyGraph:
    """``nodes(id, label)`` and ``edges(src, dst, m)``, one row a distinct edge.

    An undirected graph stores each edge once, with src <= dst. Where the nodes are told
    by the edges, ``nodes_of`` makes them from an edge table, so that a written one serves.
    """

    nodes: DataFrame
    edges: DataFrame
    directed: bool = True
    name: str = "graph"
    nodes_of: Callable[[DataFrame], DataFrame] | None = field(default=None, compare=False)

    def simplify(self, drop: set[str]) -> PropertyGraph:
        """Give up traits: L labels, M multiplicities, D directions, S self-loops."""
        g = self
        if "L" in drop:
            g = replace(g, nodes=g.nodes.withColumn("label", F.lit("*")))
        if "M" in drop:
            g = replace(g, edges=g.edges.withColumn("m", F.lit(1).cast("long")))
        if "S" in drop:
            g = replace(g, edges=g.edges.where("src <> dst"))
        if "D" in drop and g.directed:
            e = fold(g.edges.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "m"))
            g = replace(g, edges=e.withColumn("m", F.lit(1).cast("long")) if "M" in drop else e, directed=False)
        return g

    def mirrored(self) -> DataFrame:
        """Edges in both directions (of an undirected graph)."""
        return self.edges.union(self.edges.where("src <> dst").select(F.col("dst").alias("src"), F.col("src").alias("dst"), "m"))


def fold(edges: DataFrame) -> DataFrame:
    """Repeats of an ordered pair become its multiplicity."""
    return edges.groupBy("src", "dst").agg(F.sum("m").cast("long").alias("m"))


def from_edges(edges: DataFrame, nodes: DataFrame | None = None, directed: bool = True, name: str = "graph") -> PropertyGraph:
    """A graph from edge rows (src, dst[, m]); nodes default to the unlabelled endpoints."""
    e = edges if "m" in edges.columns else edges.withColumn("m", F.lit(1).cast("long"))
    e = e.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.col("m").cast("long").alias("m"))
    if not directed:
        e = e.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "m")
    e = fold(e.where("src is not null and dst is not null"))
    if nodes is None:
        of = lambda e: endpoints(e).select("id", F.lit("*").alias("label"))
        return PropertyGraph(of(e), e, directed, name, of)
    return PropertyGraph(nodes.select(F.col("id").cast("long").alias("id"), F.col("label").cast("string").alias("label")), e, directed, name)


def linked(nodes: DataFrame, e: DataFrame, directed: bool, name: str) -> PropertyGraph:
    """A graph of those nodes that an edge touches."""
    of = lambda e: nodes.join(endpoints(e), "id", "left_semi")
    return PropertyGraph(of(e), e, directed, name, of)


def profile(g: PropertyGraph) -> DataFrame:
    """One row: sizes and traits of a graph."""
    n = g.nodes.agg(F.count("*").alias("v"), F.countDistinct("label").alias("labels"))
    e = g.edges.agg(
        F.count("*").alias("e"),
        F.coalesce(F.sum("m"), F.lit(0)).cast("long").alias("m_edges"),
        F.coalesce(F.sum((F.col("src") == F.col("dst")).cast("long")), F.lit(0)).cast("long").alias("loops"),
        F.coalesce(F.max("m"), F.lit(0)).cast("long").alias("max_m"),
    )
    return n.join(F.broadcast(e)).select(F.lit(g.name).alias("graph"), "v", "labels", "e", "m_edges", "loops", "max_m", F.lit(g.directed).alias("directed"))


def key_id(c: Column) -> Column:
    """A long of 60 bits for a string key."""
    return F.conv(F.substring(F.md5(c.cast("binary")), 1, 15), 16, 10).cast("long")


def key_collisions(keys: DataFrame, col: str) -> DataFrame:
    """Audit of ``key_id``: ids that stand for more than one key."""
    return keys.groupBy(key_id(F.col(col)).alias("id")).agg(F.countDistinct(col).alias("keys")).where("keys > 1")


def endpoints(e: DataFrame) -> DataFrame:
    return e.select(F.col("src").alias("id")).union(e.select(F.col("dst").alias("id"))).distinct()


# builders ---------------------------------------------------------------------------


def _lines(spark, d) -> DataFrame:
    li = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey")
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey")
    c = table(spark, d, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    s = table(spark, d, "supplier").select("s_suppkey", "s_nationkey")
    return li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(s, li.l_suppkey == s.s_suppkey)


def _nations(spark, d) -> DataFrame:
    n, r = table(spark, d, "nation"), table(spark, d, "region")
    return n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select(F.col("n_nationkey").cast("long").alias("n"), "r_name", "n_name")


def trade_nation(spark: SparkSession, d: str, labels: str = "A") -> PropertyGraph:
    e = _lines(spark, d).groupBy(F.col("c_nationkey").cast("long").alias("src"), F.col("s_nationkey").cast("long").alias("dst")).agg(F.count("*").alias("m"))
    label = F.col("r_name") if labels == "A" else F.when(F.col("n") % 2 == 0, "even").otherwise("odd")
    return PropertyGraph(_nations(spark, d).select(F.col("n").alias("id"), label.alias("label")), e, True, "trade_nation")


def acct_segment(spark: SparkSession, d: str, labels: str = "A") -> PropertyGraph:
    lines = _lines(spark, d).groupBy(F.col("c_nationkey").cast("long").alias("n"), "c_mktsegment", F.col("s_nationkey").cast("long").alias("s")).agg(F.count("*").alias("m"))
    src = F.col("n") * 10 + F.ascii("c_mktsegment") % 10
    e = lines.select(src.alias("src"), (F.col("s") * 10 + 9).alias("dst"), "m")
    nodes = lines.select(src.alias("id"), F.col("c_mktsegment").alias("a"), "n").union(lines.select((F.col("s") * 10 + 9).alias("id"), F.lit("supplier"), "s")).distinct()
    nodes = nodes.join(F.broadcast(_nations(spark, d)), "n")
    return PropertyGraph(nodes.select("id", F.col("a" if labels == "A" else "r_name").alias("label")), e, True, "acct_segment")


def event_states(spark: SparkSession, d: str, labels: str = "A") -> PropertyGraph:
    ev = table(spark, d, "events").select("user_id", "ts", "event_id", "event_type", F.hour("ts").alias("h"))
    key = key_id(F.concat_ws("@", "event_type", F.col("h").cast("string")))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    ev = ev.withColumn("src", key)
    e = fold(ev.select("src", F.lead("src").over(w).alias("dst"), F.lit(1).cast("long").alias("m")).where("dst is not null"))
    day = F.concat(F.lit("part"), F.floor(F.col("h") / 6).cast("string"))
    nodes = ev.select(F.col("src").alias("id"), (F.col("event_type") if labels == "A" else day).alias("label")).distinct()
    return linked(nodes, e, True, "event_states")


def handover(spark: SparkSession, d: str) -> PropertyGraph:
    ev = table(spark, d, "events").select("user_id", "ts", "event_id", "event_type", "value")
    w = Window.partitionBy("event_type").orderBy("ts", "event_id")
    e = fold(ev.select(F.col("user_id").alias("src"), F.lead("user_id").over(w).alias("dst"), F.lit(1).cast("long").alias("m")).where("dst is not null"))
    total = ev.groupBy(F.col("user_id").alias("id")).agg(F.sum("value").alias("total"))
    middle = total.agg(F.percentile("total", F.lit(0.5)).alias("middle"))
    nodes = total.join(F.broadcast(middle)).select("id", F.when(F.col("total") > F.col("middle"), "heavy").otherwise("light").alias("label"))
    return linked(nodes, e, True, "handover")


def cosine_pairs(vectors: DataFrame, id_col: str, vec_col: str, least: float, block: int = 1000, most: int = 8000, cells: int = 4_000_000) -> DataFrame:
    """Pairs (src < dst) whose cosine is above ``least``, by blocks of a matrix product.

    Every block is sent to all others: blocks grow with the table from ``block`` to ``most`` rows,
    so that copies stay few. A task holds ``cells`` cosines at once.
    """

    n = vectors.count()
    blocks = max(1, -(-n // min(most, max(block, n // 12))))
    b = F.pmod(F.xxhash64(id_col), F.lit(blocks)).cast("int")
    rows = vectors.select(F.col(id_col).alias("id"), F.col(vec_col).alias("v"), b.alias("b"))
    every = F.sequence(F.lit(0), F.lit(blocks - 1))
    sides = rows.withColumn("o", F.explode(every)).select("id", "v", "b", F.least("b", "o").alias("lo"), F.greatest("b", "o").alias("hi"))

    def product(df: pd.DataFrame) -> pd.DataFrame:
        x = np.stack(df["v"].to_numpy()).astype(np.float64)
        ids = df["id"].to_numpy()
        x /= np.maximum(np.linalg.norm(x, axis=1), 1e-300)[:, None]
        lo = (df["b"] == df["lo"].iloc[0]).to_numpy()
        hi = (df["b"] == df["hi"].iloc[0]).to_numpy()
        own, other = x[lo], x[hi].T
        step = max(1, cells // max(1, other.shape[1]))
        found = [np.nonzero(own[u : u + step] @ other > least) for u in range(0, len(own), step)]
        i = np.concatenate([np.zeros(0, np.int64), *(i + u * step for u, (i, _) in enumerate(found))])
        j = np.concatenate([np.zeros(0, np.int64), *(j for _, j in found)])
        a, c = ids[lo][i], ids[hi][j]
        keep = a < c if df["lo"].iloc[0] == df["hi"].iloc[0] else a != c
        return pd.DataFrame({"src": np.minimum(a, c)[keep], "dst": np.maximum(a, c)[keep]})

    return sides.groupBy("lo", "hi").applyInPandas(product, "src long, dst long")


def vote_sim(spark: SparkSession, d: str) -> PropertyGraph:
    v = table(spark, d, "embeddings")
    e = cosine_pairs(v, "vec_id", "embedding", 0.3).withColumn("m", F.lit(1).cast("long"))
    nodes = v.select(F.col("vec_id").alias("id"), F.col("label").cast("string").alias("label"))
    return linked(nodes, e, False, "vote_sim")


def host_links(spark: SparkSession, d: str) -> PropertyGraph:
    p = table(spark, d, "pages").select(F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), 1)).alias("path"))
    src, dst = key_id(F.concat(F.lit("h:"), F.col("host"))), key_id(F.concat(F.lit("p:"), F.col("path")))
    rows = p.select(src.alias("src"), dst.alias("dst"), F.element_at(F.split("host", r"\."), -1).alias("tld"), F.lit(1).cast("long").alias("m"))
    nodes = rows.select(F.col("src").alias("id"), F.col("tld").alias("label")).union(rows.select("dst", F.lit("path"))).distinct()
    return PropertyGraph(nodes, fold(rows), True, "host_links")


def host_names(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "pages").select(F.regexp_extract("url", "://([^/?#]*)", 1).alias("name")).distinct()
    return p.select(key_id(F.concat(F.lit("h:"), F.col("name"))).alias("id"), "name")


def order_coitem(spark: SparkSession, d: str) -> PropertyGraph:
    li = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey").distinct()
    a = li.select(F.col("l_orderkey").alias("src"), "l_partkey", "l_suppkey")
    b = li.select(F.col("l_orderkey").alias("dst"), "l_partkey", "l_suppkey")
    e = a.join(b, ["l_partkey", "l_suppkey"]).where("src < dst").select("src", "dst").distinct().withColumn("m", F.lit(1).cast("long"))
    part = table(spark, d, "part").select("p_partkey", "p_type")
    kinds = li.join(part, li.l_partkey == part.p_partkey).groupBy(F.col("l_orderkey").alias("id")).agg(F.min("p_type").alias("lo"), F.max("p_type").alias("hi"))
    nodes = kinds.select("id", F.when(F.col("lo") == F.col("hi"), F.col("lo")).otherwise("mixed").alias("label"))
    return linked(nodes, e, False, "order_coitem")


def doc_cites(spark: SparkSession, d: str, labels: str = "A") -> PropertyGraph:
    docs = table(spark, d, "documents").where("text is not null")
    lines = docs.select("doc_id", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).where(F.length("line") >= 20)
    lines = lines.select("doc_id", F.md5(F.col("line").cast("binary")).alias("line"))
    some = lines.groupBy("line").agg(F.count("*").alias("n")).where("n between 2 and 50").select("line")
    lines = lines.join(some, "line")
    a, b = lines.select(F.col("doc_id").alias("src"), "line"), lines.select(F.col("doc_id").alias("dst"), "line")
    e = a.join(b, "line").where("src > dst").groupBy("src", "dst").agg(F.count("*").alias("m"))
    nodes = docs.select(F.col("doc_id").alias("id"), F.col("lang" if labels == "A" else "source").alias("label"))
    return linked(nodes, e, True, "doc_cites")


def part_copurchase(spark: SparkSession, d: str) -> PropertyGraph:
    li = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    a, b = li.select("l_orderkey", F.col("l_partkey").alias("src")), li.select("l_orderkey", F.col("l_partkey").alias("dst"))
    e = a.join(b, "l_orderkey").where("src < dst").groupBy("src", "dst").agg(F.count("*").alias("m"))
    return replace(from_edges(e, directed=False), name="part_copurchase")


def cust_supp(spark: SparkSession, d: str) -> PropertyGraph:
    e = _lines(spark, d).select((F.col("o_custkey") * 2).alias("src"), (F.col("l_suppkey") * 2 + 1).alias("dst"))
    return replace(from_edges(e), name="cust_supp")


#: Tags of the record kinds in ids of the foreign-key graphs.
FK_TAGS = {"region": 0, "nation": 1, "customer": 2, "orders": 3, "supplier": 4}


def _fk(spark, d) -> tuple[DataFrame, DataFrame]:
    t = lambda name, col: (F.col(col).cast("long") * 8 + FK_TAGS[name])
    n, c, o, s = (table(spark, d, x) for x in ("nation", "customer", "orders", "supplier"))
    e = (
        n.select(t("region", "n_regionkey").alias("src"), t("nation", "n_nationkey").alias("dst"))
        .union(c.select(t("nation", "c_nationkey"), t("customer", "c_custkey")))
        .union(o.select(t("customer", "o_custkey"), t("orders", "o_orderkey")))
        .union(s.select(t("nation", "s_nationkey"), t("supplier", "s_suppkey")))
    )
    keys = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "orders": "o_orderkey", "supplier": "s_suppkey"}
    nodes = None
    for name, key in keys.items():
        part = table(spark, d, name).select(t(name, key).alias("id"), F.lit(name).alias("label"))
        nodes = part if nodes is None else nodes.union(part)
    return nodes, e.withColumn("m", F.lit(1).cast("long"))


def fk_tree(spark: SparkSession, d: str) -> PropertyGraph:
    nodes, e = _fk(spark, d)
    return PropertyGraph(nodes, fold(e), True, "fk_tree")


def fk_full(spark: SparkSession, d: str) -> PropertyGraph:
    nodes, e = _fk(spark, d)
    li = table(spark, d, "lineitem").select((F.col("l_orderkey") * 8 + FK_TAGS["orders"]).alias("src"), (F.col("l_suppkey") * 8 + FK_TAGS["supplier"]).alias("dst"), F.lit(1).cast("long").alias("m"))
    return PropertyGraph(nodes, fold(e.union(li)), True, "fk_full")


def user_kinds(spark: SparkSession, d: str) -> PropertyGraph:
    ev = table(spark, d, "events").select("user_id", F.concat_ws(".", "event_type", F.get_json_object("props", "$.k")).alias("kind"))
    rows = ev.select(key_id(F.concat(F.lit("u:"), F.col("user_id").cast("string"))).alias("src"), key_id(F.concat(F.lit("k:"), F.col("kind"))).alias("dst"), F.lit(1).cast("long").alias("m"))
    nodes = rows.select(F.col("src").alias("id"), F.lit("user").alias("label")).union(rows.select("dst", F.lit("kind"))).distinct()
    return PropertyGraph(nodes, fold(rows), True, "user_kinds")


def turn_flow(spark: SparkSession, d: str) -> PropertyGraph:
    c = table(spark, d, "conversations").select("conv_id", "turn", "role", key_id(F.concat_ws(":", "role", "text")).alias("src"))
    w = Window.partitionBy("conv_id").orderBy("turn")
    e = fold(c.select("src", F.lead("src").over(w).alias("dst"), F.lit(1).cast("long").alias("m")).where("dst is not null"))
    nodes = c.select(F.col("src").alias("id"), F.col("role").alias("label")).distinct()
    return linked(nodes, e, True, "turn_flow")


BUILDERS: dict[str, Callable[..., PropertyGraph]] = {
    f.__name__: f
    for f in (trade_nation, acct_segment, event_states, handover, vote_sim, host_links, order_coitem, doc_cites, part_copurchase, cust_supp, fk_tree, fk_full, user_kinds, turn_flow)
}
#: Graphs with a second labelling.
TWO_LABELLINGS = ("trade_nation", "acct_segment", "event_states", "doc_cites")
