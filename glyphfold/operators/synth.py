"""Generated and sampled graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from glyphfold.sources.graphs import PropertyGraph, from_edges

#: Constants of the integer hash chain (a 31-bit affine step, the same in SQL).
STEP_A, STEP_C, STEP_P = 1_103_515_245, 12_345, (1 << 31) - 1


def kout_edges(spark: SparkSession, n: int, k: int = 10, seed: int = 42, nodes: DataFrame | None = None) -> DataFrame:
    """Directed preferential growth: node i sends k edges to endpoints chosen among earlier ones.

    Nodes are 0 to n - 1, or those of a table nodes(node) numbered from 0.

    Edge slot e belongs to node e div k. Its target picks a slot among the 2e earlier
    endpoint slots; an even slot 2f is edge f's source, an odd one its target, which is
    resolved by the same hash again. Every edge is computed alone: no communication.
    """

    def grow(it):
        import numpy as np
        import pandas as pd

        for df in it:
            e = df["id"].to_numpy(np.int64)
            cur, target = e.copy(), np.full(len(e), -1)
            step = 0
            while (target < 0).any():  # every step goes to an earlier edge, so chains end
                draw = ((cur + e * 31) % STEP_P * STEP_A + STEP_C + step * 7919 + seed * 104_729) % STEP_P
                slot = np.where(cur > 0, draw % np.maximum(cur * 2, 1), 0)
                edge, source = slot // 2, slot % 2 == 0
                open_ = target < 0
                target = np.where(open_ & (cur == 0), 0, np.where(open_ & source, edge // k, target))
                cur = np.where(open_ & ~source, edge, cur)
                step += 1
            src = e // k
            # a node may not meet itself: slots of its own block move to the node before
            dst = np.where(target >= src, np.maximum(src - 1, 0), target)
            keep = src > 0
            yield pd.DataFrame({"e": e[keep], "src": src[keep], "dst": dst[keep]})

    slots = spark.range(n * k) if nodes is None else nodes.select(F.explode(F.sequence(F.col("node") * k, F.col("node") * k + k - 1)).alias("id"))
    return slots.mapInPandas(grow, "e long, src long, dst long")


def synth_kout(spark: SparkSession, n: int, k: int = 10, seed: int = 42) -> PropertyGraph:
    g = from_edges(kout_edges(spark, n, k, seed).select("src", "dst"))
    return PropertyGraph(g.nodes, g.edges, True, f"kout_{n}")


def edge_draw(seed: int):
    """A repeatable draw per edge, below 1e6."""
    x = F.pmod(F.pmod(F.col("src"), F.lit(STEP_P)) * 48_271 + F.pmod(F.col("dst"), F.lit(STEP_P)) * 16_807 + seed * 69_621, F.lit(STEP_P))
    return F.pmod(F.pmod(x * 40_692, F.lit(STEP_P)), F.lit(1_000_000))


def sample_edges(g: PropertyGraph, frac: float, seed: int = 42) -> PropertyGraph:
    """A uniform share of the edges; all nodes stay, larger shares contain smaller ones."""
    return PropertyGraph(g.nodes, g.edges.where(edge_draw(seed) < int(frac * 1_000_000)), g.directed, f"{g.name}_{frac}")


def synth_planted(spark: SparkSession, kind: str, groups: int, size: int, context: int = 5, noise: float = 0.0, seed: int = 42) -> PropertyGraph:
    """Groups of ``size`` nodes that share ``context`` outside neighbours of their own, as cliques, stars or bicliques."""
    base = spark.range(groups).select(F.col("id").alias("g"))
    member = base.select("g", F.explode(F.sequence(F.lit(0), F.lit(size - 1))).alias("i"))
    node = F.col("g") * size + F.col("i")
    outside = groups * size
    far = outside + F.col("g") * context + F.col("c") - 1
    shared = member.select("g", node.alias("src"), F.explode(F.sequence(F.lit(1), F.lit(context))).alias("c")).select("src", far.alias("dst"))
    pair = member.select("g", "i", node.alias("src"), F.explode(F.sequence(F.lit(0), F.lit(size - 1))).alias("j")).where("i <> j")
    to = F.col("g") * size + F.col("j")
    if kind == "clique":
        inner = pair.select("src", to.alias("dst"))
    elif kind == "in_star":
        inner = pair.where("j = 0").select("src", to.alias("dst"))
    elif kind == "out_star":
        inner = pair.where("i = 0").select("src", to.alias("dst"))
    else:
        inner = pair.where("false").select("src", to.alias("dst"))
    e = shared.union(inner).distinct()
    keep = F.pmod(F.xxhash64("src", "dst", F.lit(seed + 1)), F.lit(1_000_000)) >= int(noise * 1_000_000)
    e = e.where(keep)
    label = F.when(F.col("id") >= outside, "context").otherwise("member")
    nodes = e.select(F.col("src").alias("id")).union(e.select("dst")).distinct().withColumn("label", label)
    return PropertyGraph(nodes, e.withColumn("m", F.lit(1).cast("long")), True, f"planted_{kind}")
