"""The ledger: every bit of a summary and its corrections, from counts only.

Nothing is expanded: edges are joined with the members at both ends, grouped by
pair of super-nodes, and flagged as covered by the expansion rule.

Two ledgers are kept. ``printed`` charges corrections between super-nodes that have
no super-edge for their number and choice, but not for naming the pair; ``sound``
adds that: per super-node its number of such targets and which they are.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from glyphfold.functions.bits import channel_bits, diff_bits, int_bits, log2_binomial
from glyphfold.operators.summary import STARS, Summary, identity_summary
from glyphfold.session import settle
from glyphfold.sources.graphs import PropertyGraph


@dataclass(frozen=True)
class Codes:
    """Options of the codes: how subsets and zero are coded, and what implied channels cost."""

    code: str = "binomial"
    zero_bits: float = 3.0
    charged: bool = False  # channels without slots, or between single nodes, are charged too
    within: str = "cartesian"  # slots of a super-node without self super-edge: with or without loops

    def channel(self, n, k):
        return channel_bits(n, k, self.code, self.zero_bits, self.charged)

    def integer(self, k):
        return int_bits(k, self.zero_bits)


def n_scalars(s: Summary) -> dict:
    """Super-nodes, nodes and labels, as literals of later plans."""
    r = s.supernodes.agg(F.count("*").cast("double").alias("vs"), F.coalesce(F.sum("size"), F.lit(0)).cast("double").alias("v"), F.countDistinct("label").cast("double").alias("t")).first()
    return {k: F.lit(r[k]) for k in ("vs", "v", "t")}


def slots(n, directed: bool, loops: bool):
    """Possible edges among n nodes, with or without loops."""
    n = n.cast("double")
    return (n * n if loops else n * (n - 1)) if directed else (n * (n + 1) / 2 if loops else n * (n - 1) / 2)


def supernode_bits(s: Summary, codes: Codes = Codes()) -> DataFrame:
    """``(sid, part, bits)`` of the model: label, glyph, size, multiplicity, out-set and its multiplicities."""
    n = n_scalars(s)
    out = s.superedges.groupBy(F.col("ssid").alias("sid")).agg(F.count("*").alias("d"), F.sum(codes.integer(F.col("m"))).alias("out_m"))
    df = s.supernodes.join(out, "sid", "left")
    d = F.coalesce("d", F.lit(0))
    parts = {
        "label": F.log2(n["t"]),
        "glyph": F.lit(2.0),
        "size": codes.integer(F.col("size")),
        "m": codes.integer(F.coalesce("m", F.lit(1))),
        "out_count": F.log2(n["vs"]),
        "out_set": log2_binomial(n["vs"], d),
        "out_m": F.coalesce("out_m", F.lit(0.0)),
    }
    rows = F.explode(F.array(*(F.struct(F.lit(k).alias("part"), v.alias("bits")) for k, v in parts.items())))
    return df.select("sid", rows.alias("r")).select("sid", "r.part", "r.bits")


def model_bits(s: Summary, codes: Codes = Codes()) -> DataFrame:
    own = supernode_bits(s, codes).agg(F.coalesce(F.sum("bits"), F.lit(0.0)).alias("own"))
    n = n_scalars(s)
    return own.select((F.col("own") + codes.integer(n["vs"]) + codes.integer(n["t"])).alias("bits"))


def mapping_bits(s: Summary) -> DataFrame:
    """Which nodes each super-node holds, and which is the hub of a star."""
    df, n = s.supernodes, n_scalars(s)
    hub = F.when(F.col("glyph").isin(*STARS), F.log2(F.col("size").cast("double"))).otherwise(0.0)
    return df.agg(F.coalesce(F.sum(log2_binomial(n["v"], F.col("size")) + hub), F.lit(0.0)).alias("bits"))


def bundled(s: Summary) -> DataFrame:
    """Edges with the super-nodes of their ends, and whether the expansion covers them.

    (src, dst, m, a, b, kind, rep): kind is glyph, loop or superedge for covered
    edges, inner or outer for others; rep is the representative multiplicity.
    """
    ma, mb = s.members.select(F.col("id").alias("src"), F.col("sid").alias("a")), s.members.select(F.col("id").alias("dst"), F.col("sid").alias("b"))
    e = s.graph.edges.join(ma, "src").join(mb, "dst")
    if not s.graph.directed:
        flip = F.col("a") > F.col("b")
        e = e.select(
            F.when(flip, F.col("dst")).otherwise(F.col("src")).alias("src"), F.when(flip, F.col("src")).otherwise(F.col("dst")).alias("dst"), "m",
            F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"),
        )
    side = lambda x: s.supernodes.select(F.col("sid").alias(x), *(F.col(c).alias(f"{x}_{c}") for c in ("glyph", "hub", "m", "size")))
    e = e.join(side("a"), "a").join(side("b"), "b")
    se = s.superedges.select(F.col("ssid").alias("a"), F.col("dsid").alias("b"), F.col("m").alias("se_m"))
    e = e.join(se, ["a", "b"], "left")
    has = F.col("se_m").isNotNull()
    loop = F.col("src") == F.col("dst")
    hub = F.col("a_hub")
    if s.graph.directed:
        star = ((F.col("a_glyph") == "in_star") & (F.col("dst") == hub)) | ((F.col("a_glyph") == "out_star") & (F.col("src") == hub))
    else:
        star = F.col("a_glyph").isin(*STARS) & ((F.col("dst") == hub) | (F.col("src") == hub))
    inside = F.col("a") == F.col("b")
    port = lambda x, end: ~F.col(f"{x}_glyph").isin(*STARS) | (F.col(end) == F.col(f"{x}_hub"))
    kind = (
        F.when(inside & loop & has, "loop")
        .when(inside & ~loop & ((F.col("a_glyph") == "clique") | star), "glyph")
        .when(inside, "inner")
        .when(has & port("a", "src") & port("b", "dst"), "superedge")
        .otherwise("outer")
    )
    rep = F.when(F.col("kind") == "glyph", F.col("a_m")).when(F.col("kind").isin("loop", "superedge"), F.col("se_m"))
    return e.withColumn("kind", kind).withColumn("rep", rep).select("src", "dst", "m", "a", "b", "kind", "rep")


def glyph_correction_bits(s: Summary, edges: DataFrame, codes: Codes = Codes()) -> DataFrame:
    """Missing and extra edges inside each super-node: (sid, minus, plus)."""
    seen = edges.where("a = b and kind in ('glyph', 'inner')").groupBy(F.col("a").alias("sid")).agg(F.count_if(F.col("kind") == "glyph").alias("hit"), F.count_if(F.col("kind") == "inner").alias("extra"))
    selfs = s.superedges.where("ssid = dsid").select(F.col("ssid").alias("sid"), F.lit(True).alias("looped"))
    df = s.supernodes.join(seen, "sid", "left").join(selfs, "sid", "left").na.fill(0, ["hit", "extra"])
    n, d = F.col("size"), s.graph.directed
    loops = F.col("looped").isNull() if codes.within == "cartesian" else F.lit(False)
    universe = F.when(loops, slots(n, d, True)).otherwise(slots(n, d, False))
    cover = F.when(F.col("glyph") == "clique", slots(n, d, False)).when(F.col("glyph").isin(*STARS), n.cast("double") - 1).otherwise(0.0)
    single = (n == 1) & F.lit(not codes.charged)
    minus = F.when(single, 0.0).otherwise(codes.channel(cover, cover - F.col("hit")))
    plus = F.when(single, 0.0).otherwise(codes.channel(universe - cover, F.col("extra")))
    minus = F.when(cover > 0, minus).otherwise(F.lit(0.0) if not codes.charged else minus)
    return df.select("sid", minus.alias("minus"), plus.alias("plus"))


def loop_correction_bits(s: Summary, edges: DataFrame, codes: Codes = Codes()) -> DataFrame:
    """Missing loops of each self super-edge: (sid, bits)."""
    seen = edges.where("kind = 'loop'").groupBy(F.col("a").alias("sid")).agg(F.count("*").alias("hit"))
    selfs = s.superedges.where("ssid = dsid").select(F.col("ssid").alias("sid")).join(s.supernodes.select("sid", "size"), "sid").join(seen, "sid", "left")
    bits = F.when((F.col("size") == 1) & F.lit(not codes.charged), 0.0).otherwise(codes.channel(F.col("size").cast("double"), F.col("size") - F.coalesce("hit", F.lit(0))))
    return selfs.select("sid", bits.alias("bits"))


def bundles(s: Summary, edges: DataFrame) -> DataFrame:
    """Pairs of super-nodes with edges between them: (ssid, dsid, hit, extra, kept), kept where they have a super-edge."""
    seen = edges.where("a <> b").groupBy(F.col("a").alias("ssid"), F.col("b").alias("dsid")).agg(F.count_if(F.col("kind") == "superedge").alias("hit"), F.count_if(F.col("kind") == "outer").alias("extra"))
    return seen.join(s.superedges.select("ssid", "dsid", F.lit(True).alias("kept")), ["ssid", "dsid"], "left")


def superedge_correction_bits(s: Summary, edges: DataFrame, codes: Codes = Codes(), seen: DataFrame | None = None) -> DataFrame:
    """Missing and extra edges along each super-edge: (ssid, dsid, minus, plus)."""
    seen = (bundles(s, edges) if seen is None else seen).where("kept").select("ssid", "dsid", "hit", "extra")
    side = lambda x: s.supernodes.select(F.col("sid").alias(x), F.col("size").cast("double").alias(f"{x}_n"), F.when(F.col("glyph").isin(*STARS), 1.0).otherwise(F.col("size").cast("double")).alias(f"{x}_p"))
    df = s.superedges.where("ssid <> dsid").join(side("ssid"), "ssid").join(side("dsid"), "dsid").join(seen, ["ssid", "dsid"], "left").na.fill(0, ["hit", "extra"])
    cover, every = F.col("ssid_p") * F.col("dsid_p"), F.col("ssid_n") * F.col("dsid_n")
    free = (every == 1) & F.lit(not codes.charged)
    return df.select(
        "ssid", "dsid",
        F.when(free, 0.0).otherwise(codes.channel(cover, cover - F.col("hit"))).alias("minus"),
        F.when(free, 0.0).otherwise(codes.channel(every - cover, F.col("extra"))).alias("plus"),
    )


def loose(s: Summary, edges: DataFrame, seen: DataFrame | None = None) -> DataFrame:
    """Bundles without a super-edge: (ssid, dsid, n)."""
    seen = bundles(s, edges) if seen is None else seen
    return seen.where("kept is null").select("ssid", "dsid", F.col("extra").alias("n"))


def loose_correction_bits(s: Summary, edges: DataFrame, codes: Codes = Codes(), seen: DataFrame | None = None) -> DataFrame:
    side = lambda x: s.supernodes.select(F.col("sid").alias(x), F.col("size").cast("double").alias(f"{x}_n"))
    df = loose(s, edges, seen).join(side("ssid"), "ssid").join(side("dsid"), "dsid")
    every = F.col("ssid_n") * F.col("dsid_n")
    bits = F.when((every == 1) & F.lit(not codes.charged), 0.0).otherwise(codes.channel(every, F.col("n")))
    return df.select("ssid", "dsid", "n", bits.alias("bits"))


def multiplicity_bits(s: Summary, edges: DataFrame, codes: Codes = Codes()) -> DataFrame:
    """Difference codes of covered edges, plain codes of the others: (kind, bits)."""
    bits = F.when(F.col("rep").isNotNull(), diff_bits(F.col("m"), F.col("rep"))).otherwise(codes.integer(F.col("m")))
    return edges.groupBy("kind").agg(F.sum(bits).alias("bits"))


def locate_bits(s: Summary, edges: DataFrame, seen: DataFrame | None = None) -> DataFrame:
    """What ``printed`` leaves out: per super-node the number and choice of loose targets."""
    targets = loose(s, edges, seen).groupBy(F.col("ssid").alias("sid")).agg(F.count("*").alias("k"))
    df, n = s.supernodes.select("sid").join(targets, "sid", "left"), n_scalars(s)
    return df.agg(F.coalesce(F.sum(F.log2(n["vs"]) + log2_binomial(n["vs"], F.coalesce("k", F.lit(0)))), F.lit(0.0)).alias("bits"))


PARTS = ("model", "mapping", "glyph_topology", "loop_topology", "superedge_topology", "loose_topology", "multiplicity", "location")


def total_bits(s: Summary, codes: Codes = Codes()) -> DataFrame:
    """``(part, ledger, bits)``; location belongs to the sound ledger only."""
    edges = settle(bundled(s), "bundled")
    seen = settle(bundles(s, edges), "bundles")
    total = lambda df, *cols: df.agg(F.coalesce(F.sum(sum(F.col(c) for c in cols)), F.lit(0.0)).alias("bits"))
    made = {
        "model": model_bits(s, codes),
        "mapping": mapping_bits(s),
        "glyph_topology": total(glyph_correction_bits(s, edges, codes), "minus", "plus"),
        "loop_topology": total(loop_correction_bits(s, edges, codes), "bits"),
        "superedge_topology": total(superedge_correction_bits(s, edges, codes, seen), "minus", "plus"),
        "loose_topology": total(loose_correction_bits(s, edges, codes, seen), "bits"),
        "multiplicity": total(multiplicity_bits(s, edges, codes), "bits"),
        "location": locate_bits(s, edges, seen),
    }
    out = None
    for part, df in made.items():
        row = df.select(F.lit(part).alias("part"), F.lit("sound" if part == "location" else "printed").alias("ledger"), "bits")
        out = row if out is None else out.unionByName(row)
    return out


def ledgers(s: Summary, codes: Codes = Codes()) -> dict[str, float]:
    """Totals of both ledgers."""
    parts = {r.part: r.bits for r in total_bits(s, codes).collect()}
    printed = sum(v for k, v in parts.items() if k != "location")
    return {"printed": printed, "sound": printed + parts["location"]} | parts


def identity_bits(g: PropertyGraph, codes: Codes = Codes()) -> DataFrame:
    """``(printed, sound)`` of the graph described as its own summary, in closed form: only single nodes, so no corrections."""
    deg = g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("d"), F.sum(codes.integer(F.col("m"))).alias("bits"))
    n = g.nodes.agg(F.count("*").cast("double").alias("vs"), F.countDistinct("label").cast("double").alias("t"))
    out = deg.groupBy("d").agg(F.count("*").alias("k"), F.sum("bits").alias("bits"), F.sum("d").alias("edges")).crossJoin(F.broadcast(n))  # one row
    out = out.agg(F.coalesce(F.sum(F.col("k") * log2_binomial(F.col("vs"), F.col("d")) + F.col("bits") + F.col("edges")), F.lit(0.0)).alias("own"))
    vs, t = F.col("vs"), F.col("t")
    each = F.log2(t) + 2 + 1 + 1 + F.log2(vs) + F.log2(vs)  # label, glyph, size, multiplicity, number of targets, which node
    printed = F.when(vs > 0, codes.integer(vs) + codes.integer(t) + vs * each + F.col("own")).otherwise(codes.integer(vs) + codes.integer(t))
    return n.crossJoin(F.broadcast(out)).select(printed.alias("printed"), (printed + F.when(vs > 0, vs * F.log2(vs)).otherwise(0.0)).alias("sound"))


def bits_before(g: PropertyGraph, codes: Codes = Codes()) -> dict[str, float]:
    """Totals of the graph described as its own summary."""
    if codes.charged:
        return ledgers(identity_summary(g), codes)
    return identity_bits(g, codes).first().asDict()
