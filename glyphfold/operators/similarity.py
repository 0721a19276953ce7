"""Direction-aware Jaccard similarity of neighbourhoods."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from glyphfold.session import discard, release, settle
from glyphfold.sources.graphs import PropertyGraph

#: Length of a token list above which pairs are intersected by a join instead of arrays.
LONG_LIST = 10_000
#: Log2 of the length from which lists are counted in blocks; shorter ones meet over their rare tokens.
SHORT_CLASS = 6
#: Tokens of one block.
BLOCK_TOKENS = 4_000_000
#: Cells of shared tokens that a task counts at once: so few that they stay in a processor's cache.
COUNT_CELLS = 1 << 16
#: Tokens that one job deals out to pairs of blocks; each block meets all others, so all pairs at once would take disk by the square.
DEALT_TOKENS = 100_000_000


def neighbor_tokens(g: PropertyGraph, mode: str = "directed") -> DataFrame:
    """``(id, tok)``: 2 * neighbour + direction; both directions merge for undirected similarity."""
    if mode == "undirected" or not g.directed:
        both = g.edges.select(F.col("src").alias("id"), (F.col("dst") * 2).alias("tok")).union(g.edges.select("dst", F.col("src") * 2))
        return both.distinct()
    return g.edges.select(F.col("src").alias("id"), (F.col("dst") * 2 + 1).alias("tok")).union(g.edges.select("dst", F.col("src") * 2))


def degrees(tokens: DataFrame) -> DataFrame:
    return tokens.groupBy("id").agg(F.count("*").alias("d"))


def size_bound(da: Column, db: Column) -> Column:
    """No pair is more similar than the ratio of its degrees."""
    return F.least(da, db) / F.greatest(da, db)


def exact_simpairs(g: PropertyGraph, t: float = 0.0, mode: str = "directed") -> DataFrame:
    """All pairs (a < b) with a shared token and similarity of t or more: the brute-force reference."""
    tok = neighbor_tokens(g, mode)
    both = tok.select(F.col("id").alias("a"), "tok").join(tok.select(F.col("id").alias("b"), "tok"), "tok").where("a < b")
    return _with_jaccard(both.groupBy("a", "b").agg(F.count("*").alias("both")), degrees(tok)).where(F.col("jd") >= t)


def _with_jaccard(shared: DataFrame, deg: DataFrame) -> DataFrame:
    da, db = deg.select(F.col("id").alias("a"), F.col("d").alias("da")), deg.select(F.col("id").alias("b"), F.col("d").alias("db"))
    jd = F.col("both") / (F.col("da") + F.col("db") - F.col("both"))
    return shared.join(da, "a").join(db, "b").select("a", "b", jd.alias("jd"))


def jaccard_for(tokens: DataFrame, pairs: DataFrame, long_list: int = LONG_LIST) -> DataFrame:
    """``(a, b, jd)`` of the given pairs.

    Only the lists of nodes in pairs are built. Lists up to ``long_list`` tokens are
    intersected as arrays; pairs with a longer one meet in a join over their tokens, so
    no list of unbounded length is gathered.
    """
    pairs = pairs.select("a", "b")
    used = pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct()
    own = tokens.join(used, "id", "left_semi")
    deg = own.groupBy("id").agg(F.count("*").alias("d"))
    of = lambda end, d: deg.select(F.col("id").alias(end), F.col("d").alias(d))
    sized = pairs.join(of("a", "da"), "a").join(of("b", "db"), "b")
    many = F.greatest("da", "db") > long_list
    lists = own.join(deg.where(F.col("d") <= long_list), "id").groupBy("id").agg(F.collect_list("tok").alias("t"))
    list_of = lambda end, t: lists.select(F.col("id").alias(end), F.col("t").alias(t))
    short = sized.where(~many).join(list_of("a", "ta"), "a").join(list_of("b", "tb"), "b")
    short = short.select("a", "b", "da", "db", F.size(F.array_intersect("ta", "tb")).cast("long").alias("both"))
    long = sized.where(many).join(own.select(F.col("id").alias("a"), "tok"), "a").join(own.select(F.col("id").alias("b"), "tok"), ["b", "tok"])
    met = long.groupBy("a", "b").agg(F.count("*").alias("both"))
    long = sized.where(many).join(met, ["a", "b"], "left").select("a", "b", "da", "db", F.coalesce("both", F.lit(0)).alias("both"))
    return short.unionByName(long).select("a", "b", (F.col("both") / (F.col("da") + F.col("db") - F.col("both"))).alias("jd"))


def window_pairs(nodes: DataFrame, t_min: float) -> DataFrame:
    """Pairs of one cluster whose degrees allow similarity t_min; nodes has (cluster, id, d).

    The degree range is turned into an equality: degrees fall in cells whose width is
    the factor 1 / t_min, so partners lie in the same cell or the next.
    """
    import math

    step = max(math.log(1 / t_min), 1e-6) if t_min < 1 else None
    cell = F.floor(F.log(F.col("d").cast("double")) / step + 1e-9) if step else F.col("d").cast("long")
    x = nodes.select("cluster", "id", "d", cell.alias("cell"))
    near = F.explode(F.array(*(F.col("cell") + k for k in ((-1, 0, 1) if step else (0,)))))
    y = x.select("cluster", F.col("id").alias("b"), F.col("d").alias("db"), near.alias("cell"))
    x = x.select("cluster", F.col("id").alias("a"), F.col("d").alias("da"), "cell")
    fits = (F.least("da", "db") >= F.floor(F.greatest("da", "db") * t_min))
    return x.join(y, ["cluster", "cell"]).where((F.col("a") < F.col("b")) & fits).select("cluster", "a", "b")


def token_classes(tokens: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """``(*keys, id, d, rep)``: nodes with equal token lists share the smallest of their ids; lists are told by length and two 64-bit sums."""
    prints = [F.sum(F.xxhash64("tok", F.lit(k)).cast("decimal(38,0)")).alias(f"p{k}") for k in (0, 1)]
    sums = settle(tokens.groupBy(*keys, "id").agg(F.count("*").alias("d"), *prints), "token_sums")
    same = [*keys, "d", "p0", "p1"]
    return sums.join(sums.groupBy(*same).agg(F.min("id").alias("rep")), same).select(*keys, "id", "d", "rep")


def alike_pairs(lists: DataFrame, t: float) -> DataFrame:
    """``(cluster, a, b, jd)``: all pairs of one cluster, a < b, with similarity of t or more (0 < t); lists is (cluster, id, tok, d).

    Lists of fewer than ``2 ** SHORT_CLASS`` tokens meet over their rarest tokens and must pass
    bounds by place and by a bitmap of 256 bits before they are intersected. Longer ones are
    counted in blocks of alike lengths, a bounded number of tokens a job, those above ``LONG_LIST`` by a join over their tokens.
    No bound loses a pair.
    """
    k = F.floor(F.log2(F.col("d").cast("double")) + 1e-12).cast("int")
    rows = lists.select("cluster", "id", "tok", "d", k.alias("k"))
    sizes = {r.k: r.n for r in rows.groupBy("k").agg(F.count("*").alias("n")).collect()}
    out = short_pairs(rows.where(F.col("k") < SHORT_CLASS), t)
    middle = rows.where(F.col("d") <= LONG_LIST)
    if max(sizes, default=0) >= SHORT_CLASS:
        out = out.unionByName(block_pairs(middle, sizes, t))
    if 2 ** (max(sizes, default=0) + 1) > LONG_LIST:
        x = rows.where(F.col("d") > LONG_LIST).select("cluster", "tok", F.col("id").alias("x"), F.col("d").alias("dx"))
        y = rows.where(F.col("d") >= LONG_LIST * t - 1).select("cluster", "tok", F.col("id").alias("y"), F.col("d").alias("dy"))
        smaller = (F.col("dy") < F.col("dx")) | ((F.col("dy") == F.col("dx")) & (F.col("y") < F.col("x")))
        met = x.join(y, ["cluster", "tok"]).where(smaller & (F.col("dy") >= F.col("dx") * t - 1e-9)).groupBy("cluster", "x", "y", "dx", "dy").agg(F.count("*").alias("both"))
        out = out.unionByName(met.select("cluster", F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), (F.col("both") / (F.col("dx") + F.col("dy") - F.col("both"))).alias("jd")))
    return out.where(F.col("jd") >= t - 1e-12)


def short_pairs(rows: DataFrame, t: float) -> DataFrame:
    """Of short lists, two can reach t only if they share a token among their rarest: of d tokens, all
    but t * d - 1 for the longer one, and all but 2 * t / (1 + t) * d - 1 for the other."""
    spread = F.xxhash64("tok", F.lit(7)).bitwiseAND(F.lit(255))
    bit = F.expr("shiftleft(1L, cast(h & 63 as int))")
    maps = rows.withColumn("h", spread).groupBy("cluster", "id").agg(*(F.coalesce(F.bit_or(F.when(F.shiftright("h", 6) == w, bit)), F.lit(0).cast("long")).alias(f"m{w}") for w in range(4)))
    rarity = rows.groupBy("cluster", "tok").agg(F.count("*").alias("f"))
    place = F.row_number().over(Window.partitionBy("cluster", "id").orderBy("f", "tok"))
    kept = lambda share: F.col("place") <= F.col("d") - F.ceil(F.col("d") * share - 1e-9) + 1
    ranked = rows.join(rarity, ["cluster", "tok"]).withColumn("place", place).where(kept(t) & (F.col("f") > 1))
    ranked = settle(ranked.join(maps, ["cluster", "id"]).select("cluster", "tok", "id", F.col("d").cast("int").alias("d"), "place", *(f"m{w}" for w in range(4))), "rare_tokens")
    named = lambda df, e: df.select(*(F.col(c).alias(f"{c}_{e}") for c in df.columns))
    x, y = named(ranked, "x"), named(ranked.where(kept(2 * t / (1 + t))), "y")
    c = F.col
    least = F.ceil((c("d_x") + c("d_y")) * (t / (1 + t)) - 1e-9)
    lacks = lambda u, v: sum((F.bit_count(c(f"m{w}_{u}").bitwiseAND(F.bitwise_not(c(f"m{w}_{v}")))) for w in range(4)), F.lit(0))
    fits = ((c("d_y") < c("d_x")) | ((c("d_y") == c("d_x")) & (c("id_y") < c("id_x")))) & (c("d_y") >= c("d_x") * t - 1e-9)
    fits &= (F.least(c("d_x") - c("place_x"), c("d_y") - c("place_y")) + 1 >= least) & (c("d_x") - lacks("x", "y") >= least) & (c("d_y") - lacks("y", "x") >= least)
    met = x.join(y, (c("cluster_x") == c("cluster_y")) & (c("tok_x") == c("tok_y")) & fits).select(c("cluster_x").alias("cluster"), F.least("id_x", "id_y").alias("a"), F.greatest("id_x", "id_y").alias("b")).distinct()
    met = settle(met, "rare_meetings")
    return met.join(jaccard_for(rows.select("id", "tok"), met.select("a", "b").distinct()), ["a", "b"]).select("cluster", "a", "b", "jd")


def block_pairs(rows: DataFrame, sizes: dict[int, int], t: float) -> DataFrame:
    """Pairs whose longer list has ``2 ** SHORT_CLASS`` tokens or more: shared tokens are counted for two blocks of lists at a time."""
    spark = rows.sparkSession
    low = lambda k: 2 ** (k + 1) > t * 2**SHORT_CLASS
    blocks = [(k, s) for k, n in sorted(sizes.items()) if low(k) for s in range(-(-n // BLOCK_TOKENS))]
    count = {k: -(-n // BLOCK_TOKENS) for k, n in sizes.items()}
    tasks = [(x, y) for i, x in enumerate(blocks) for y in blocks[i:] if y[0] >= SHORT_CLASS and 2 ** (x[0] + 1) > t * 2 ** y[0]]
    jobs, dealt_now = [[]], 0
    for task in tasks:
        size = sum(sizes[k] // count[k] for k, _ in set(task))
        if jobs[-1] and dealt_now + size > DEALT_TOKENS:
            jobs.append([])
            dealt_now = 0
        jobs[-1].append(task)
        dealt_now += size
    number = F.lit(1)
    for k, n in count.items():
        number = F.when(F.col("k") == k, F.lit(n)).otherwise(number)
    own = rows.where(F.col("k") >= min((k for k, _ in blocks), default=0)).groupBy("cluster", "id", "d", "k").agg(F.collect_list("tok").alias("toks"))
    own = own.withColumn("s", F.pmod(F.xxhash64("id"), number.cast("long")).cast("int"))

    def meet(df: pd.DataFrame) -> pd.DataFrame:
        late = df["late"].to_numpy(bool)
        one = bool(df["one"].iloc[0])  # a block against itself
        ys = df[late]
        xs = ys if one else df[~late]
        if not len(xs) or not len(ys):
            return pd.DataFrame({"cluster": [], "a": [], "b": [], "jd": []}).astype({"cluster": "int64", "a": "int64", "b": "int64"})
        (nx, tx), (ny, ty) = ((z["d"].to_numpy(np.int64), np.concatenate(z["toks"].to_list())) for z in (xs, ys))
        words, ty = np.unique(ty, return_inverse=True)
        order = np.argsort(ty, kind="stable")
        at = np.repeat(np.arange(len(ny)), ny)[order]
        first = np.searchsorted(ty[order], np.arange(len(words) + 1))
        place = np.minimum(np.searchsorted(words, tx), len(words) - 1)
        known = words[place] == tx
        row = np.repeat(np.arange(len(nx)), nx)
        ends = np.concatenate([[0], np.cumsum(nx)])
        hits = np.concatenate([[0], np.cumsum(np.where(known, first[place + 1] - first[place], 0))])[ends]
        (cx, ix), (cy, iy) = ((z["cluster"].to_numpy(np.int64), z["id"].to_numpy(np.int64)) for z in (xs, ys))
        parts, u = [], 0
        while u < len(nx):
            v = u + max(1, COUNT_CELLS // len(ny))
            v = max(u + 1, min(v, len(nx), int(np.searchsorted(hits, hits[u] + 2 * COUNT_CELLS, "right")) - 1))
            some = np.arange(ends[u], ends[v])[known[ends[u] : ends[v]]]
            start, n = first[place[some]], first[place[some] + 1] - first[place[some]]
            take = np.arange(n.sum()) + np.repeat(start - (np.cumsum(n) - n), n)
            both = np.bincount(np.repeat((row[some] - u) * len(ny), n) + at[take], minlength=(v - u) * len(ny))
            cell = np.flatnonzero(both)
            i, j = cell // len(ny) + u, cell % len(ny)
            jd = both[cell] / (nx[i] + ny[j] - both[cell])
            good = (jd >= t - 1e-12) & (cx[i] == cy[j]) & ((ix[i] < iy[j]) if one else (ix[i] != iy[j]))
            i, j = i[good], j[good]
            parts.append((cx[i], np.minimum(ix[i], iy[j]), np.maximum(ix[i], iy[j]), jd[good]))
            u = v
        cluster, a, b, jd = (np.concatenate(x) for x in zip(*parts, strict=True))
        return pd.DataFrame({"cluster": cluster, "a": a, "b": b, "jd": jd})

    def met(lists: DataFrame, job: list) -> DataFrame:
        deal = spark.createDataFrame([(i, *b, b == y, x == y) for i, (x, y) in enumerate(job) for b in {x, y}], "task int, k int, s int, late boolean, one boolean")
        return lists.join(F.broadcast(deal), ["k", "s"]).groupBy("task").applyInPandas(meet, "cluster long, a long, b long, jd double")

    if len(jobs) == 1:
        return met(own, jobs[0])
    own, out = settle(own, "block_lists"), None
    for job in jobs:
        some = settle(met(own, job), "block_meetings")
        out = some if out is None else out.unionByName(some)
        release(spark)
    discard(own)
    return out


def similar_pairs(g: PropertyGraph, t: float, mode: str = "directed") -> DataFrame:
    """As ``exact_simpairs`` for 0 < t, without a table of all pairs that share a token: equal lists are one list, and only alike ones meet."""
    tok = settle(neighbor_tokens(g, mode), "tokens")
    fold = settle(token_classes(tok), "folded")
    lists = settle(tok.join(fold.where("id = rep").select("id", "d"), "id").select(F.lit(0).cast("long").alias("cluster"), "id", "tok", "d"), "class_tokens")
    discard(tok)
    same = fold.where("id = rep").select(F.col("id").alias("a"), F.col("id").alias("b"), F.lit(1.0).alias("jd"))
    u, v = fold.select(F.col("rep").alias("a"), F.col("id").alias("u")), fold.select(F.col("rep").alias("b"), F.col("id").alias("v"))
    out = alike_pairs(lists, t).select("a", "b", "jd").unionByName(same).join(u, "a").join(v, "b").where("a <> b or u < v")
    return out.select(F.least("u", "v").alias("a"), F.greatest("u", "v").alias("b"), "jd")


def set_quality(candidate_members: DataFrame, simpairs: DataFrame) -> DataFrame:
    """``(cid, size, quality)``: least pairwise similarity of each candidate; 0 if a pair is missing."""
    x, y = candidate_members.select("cid", F.col("id").alias("a")), candidate_members.select("cid", F.col("id").alias("b"))
    pairs = x.join(y, "cid").where("a < b").join(simpairs.select("a", "b", "jd"), ["a", "b"], "left")
    q = pairs.groupBy("cid").agg(F.min(F.coalesce("jd", F.lit(0.0))).alias("quality"))
    return candidate_members.groupBy("cid").agg(F.count("*").alias("size")).join(q, "cid")


def redundant_sets(members: DataFrame, quality: DataFrame) -> DataFrame:
    """Candidates that are a strict subset of one with equal or better quality: (cid, inside)."""
    m = members.select("cid", "id")
    shared = m.join(m.select(F.col("cid").alias("inside"), "id"), "id").where("cid <> inside").groupBy("cid", "inside").agg(F.count("*").alias("n"))
    a = quality.select("cid", "size", "quality")
    b = quality.select(F.col("cid").alias("inside"), F.col("size").alias("s2"), F.col("quality").alias("q2"))
    return shared.join(a, "cid").join(b, "inside").where("n = size and s2 > size and q2 >= quality").select("cid", "inside").distinct()
