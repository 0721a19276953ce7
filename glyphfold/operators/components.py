"""Connected components by alternating star contraction."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from glyphfold.session import discard, settle


#: Edges up to which one task folds them (16 bytes each); more are contracted in rounds. Results are the same.
FOLDED_EDGES = 1_000_000


def folded_components(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Smallest id reachable from every endpoint of a bounded number of edges (u, v), by union of roots."""
    parent: dict[int, int] = {}

    def root(a: int) -> int:
        while (up := parent.setdefault(a, a)) != a:
            parent[a] = parent[up]
            a = up
        return a

    for df in batches:
        for u, v in zip(df["u"].tolist(), df["v"].tolist(), strict=True):
            a, b = root(u), root(v)
            if a != b:
                parent[max(a, b)] = min(a, b)
    if parent:
        yield pd.DataFrame({"id": list(parent), "root": [root(a) for a in list(parent)]})


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """``(id, root)`` for every endpoint of ``edges``; root is the smallest id reachable.

    Every round points the larger neighbours of a node at the node's smallest
    neighbour, then the smaller ones: the number of rounds grows with the
    logarithm of the longest path. Minima are pre-aggregated on the map side; the join
    that brings them back is split by AQE where a hub makes it uneven. Each round is
    written to the shared folder. Up to ``FOLDED_EDGES`` distinct edges, counted first,
    are folded by one task instead. Null endpoints and loops are ignored.
    """
    e = (
        edges.select(F.greatest(F.col(src), F.col(dst)).alias("u"), F.least(F.col(src), F.col(dst)).alias("v"))
        .where("u is not null and v is not null and u <> v")
        .distinct()
    )
    e = settle(e, "cc")
    if e.count() <= FOLDED_EDGES:
        return settle(e.coalesce(1).mapInPandas(folded_components, "id long, root long"), "cc_roots")
    nodes = settle(e.select(F.col("u").alias("id")).union(e.select(F.col("v").alias("id"))).distinct(), "cc_nodes")
    seen = None
    for _ in range(max_rounds):
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u")
        old, e = e, settle(
            small.select(F.col("v").alias("u"), F.col("m").alias("v"))
            .union(small.select("u", F.col("m").alias("v")))
            .where("u <> v")
            .distinct(),
            "cc",
        )
        discard(old)
        now = tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    return nodes.join(e.select(F.col("u").alias("id"), F.col("v").alias("root")), "id", "left").select(
        "id", F.coalesce("root", "id").alias("root")
    )
