"""Summaries: super-graph tables, expansion, corrections, exact rebuild, and queries."""

from __future__ import annotations

import json
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from glyphfold.session import BROADCAST_ROWS
from glyphfold.sources.graphs import PropertyGraph

SUPERNODES = "sid long, label string, size long, glyph string, m long, hub long, self_m long"
MEMBERS = "id long, sid long"
SUPEREDGES = "ssid long, dsid long, m long"
STARS = ("in_star", "out_star")


@dataclass(frozen=True)
class Summary:
    """A super-graph over ``graph``; a self super-edge is the row with ssid = dsid.

    supernodes(sid, label, size, glyph, m, hub, self_m), members(id, sid),
    superedges(ssid, dsid, m). A super-node's ``m`` stands for the edges of its
    glyph, ``self_m`` repeats the multiplicity of its self super-edge, if any.
    """

    graph: PropertyGraph
    supernodes: DataFrame
    members: DataFrame
    superedges: DataFrame

    def validate(self) -> DataFrame:
        """Rows (problem, id) for every broken rule; none for a sound summary."""
        m = self.members.join(self.graph.nodes, "id", "full_outer").select("id", "sid", F.col("label").alias("own"))
        sn = self.supernodes
        tagged = m.join(sn, "sid", "left")
        out = m.where("sid is null or own is null").select(F.lit("not a partition").alias("problem"), "id")
        twice = self.members.groupBy("id").count().where("count > 1").select(F.lit("in two super-nodes"), "id")
        mixed = tagged.where("label <> own").select(F.lit("label"), "id")
        sizes = self.members.groupBy("sid").count().join(sn, "sid", "full_outer").where("coalesce(count, 0) <> coalesce(size, 0)")
        hub = sn.join(self.members.select(F.col("id").alias("hub"), F.col("sid").alias("at")), "hub", "left").where(
            (F.col("glyph").isin(*STARS) & ~F.col("sid").eqNullSafe(F.col("at"))) | (~F.col("glyph").isin(*STARS) & F.col("hub").isNotNull())
        )
        return out.union(twice).union(mixed).union(sizes.select(F.lit("size"), "sid")).union(hub.select(F.lit("hub"), "sid"))


def identity_summary(g: PropertyGraph) -> Summary:
    """Every node a super-node, every edge a super-edge."""
    loops = g.edges.where("src = dst").select(F.col("src").alias("sid"), F.col("m").alias("self_m"))
    sn = g.nodes.select(F.col("id").alias("sid"), "label", F.lit(1).cast("long").alias("size"), F.lit("disconnected").alias("glyph"), F.lit(1).cast("long").alias("m"), F.lit(None).cast("long").alias("hub"))
    sn = sn.join(loops, "sid", "left")
    e = g.edges.select(F.col("src").alias("ssid"), F.col("dst").alias("dsid"), "m")
    return Summary(g, sn, g.nodes.select("id", F.col("id").alias("sid")), e)


# expansion


def ports(s: Summary) -> DataFrame:
    """(sid, id) through which super-edges attach: the hub of a star, else all members."""
    star = s.supernodes.where(F.col("glyph").isin(*STARS)).select("sid", F.col("hub").alias("id"))
    rest = s.members.join(s.supernodes.where(~F.col("glyph").isin(*STARS)).select("sid"), "sid")
    return star.unionByName(rest.select("sid", "id"))


def _oriented(df: DataFrame, directed: bool) -> DataFrame:
    return df if directed else df.withColumns({"src": F.least("src", "dst"), "dst": F.greatest("src", "dst")})


def expand_nodes(s: Summary) -> DataFrame:
    return s.members.join(s.supernodes.select("sid", "label"), "sid").select("id", "label")


def expand_glyphs(s: Summary) -> DataFrame:
    """Edges inside super-nodes: all pairs of a clique, spokes of a star."""
    kinds = s.supernodes.select("sid", "glyph", "m", "hub")
    mem = s.members.join(kinds, "sid")
    other = s.members.select(F.col("id").alias("dst"), "sid")
    pair = F.col("src") != F.col("dst") if s.graph.directed else F.col("src") < F.col("dst")
    clique = mem.where("glyph = 'clique'").select("sid", F.col("id").alias("src"), "m").join(other, "sid").where(pair).select("src", "dst", "m", F.col("sid").alias("a"))
    spokes = mem.where(F.col("glyph").isin(*STARS) & (F.col("id") != F.col("hub")))
    inward = F.col("glyph") == "in_star"
    star = spokes.select(F.when(inward, F.col("id")).otherwise(F.col("hub")).alias("src"), F.when(inward, F.col("hub")).otherwise(F.col("id")).alias("dst"), "m", F.col("sid").alias("a"))
    return clique.unionByName(_oriented(star, s.graph.directed)).select("src", "dst", "m", F.lit("glyph").alias("origin"), "a", F.col("a").alias("b"))


def expand_loops(s: Summary) -> DataFrame:
    selfs = s.superedges.where("ssid = dsid").select(F.col("ssid").alias("sid"), "m")
    return s.members.join(selfs, "sid").select(F.col("id").alias("src"), F.col("id").alias("dst"), "m", F.lit("loop").alias("origin"), F.col("sid").alias("a"), F.col("sid").alias("b"))


def expand_superedges(s: Summary) -> DataFrame:
    p = ports(s)
    if hasattr(s.members, "_settled_at") and s.members.count() <= BROADCAST_ROWS:
        p = F.broadcast(p)
    src, dst = p.select(F.col("sid").alias("ssid"), F.col("id").alias("src")), p.select(F.col("sid").alias("dsid"), F.col("id").alias("dst"))
    e = s.superedges.where("ssid <> dsid").join(src, "ssid").join(dst, "dsid")
    return _oriented(e.select("src", "dst", "m", F.lit("superedge").alias("origin"), F.col("ssid").alias("a"), F.col("dsid").alias("b")), s.graph.directed)


def decompress(s: Summary) -> DataFrame:
    """The approximate graph that the summary stands for. Quadratic in clique size: for checks and small outputs."""
    return expand_glyphs(s).unionByName(expand_loops(s)).unionByName(expand_superedges(s))


def corrections(s: Summary) -> DataFrame:
    """``(kind, src, dst, m, delta)`` that turn the approximation into the graph: add, drop, retune."""
    got = decompress(s).select("src", "dst", F.col("m").alias("rep"))
    both = s.graph.edges.join(got, ["src", "dst"], "full_outer")
    kind = F.when(F.col("rep").isNull(), "add").when(F.col("m").isNull(), "drop").when(F.col("m") != F.col("rep"), "retune")
    return both.select(kind.alias("kind"), "src", "dst", "m", (F.col("m") - F.col("rep")).alias("delta")).where("kind is not null")


def reconstruct(s: Summary, fixes: DataFrame | None = None) -> DataFrame:
    """The input's edges from the summary and its corrections alone."""
    fixes = corrections(s) if fixes is None else fixes
    base = decompress(s).select("src", "dst", F.col("m").alias("rep"))
    joined = base.join(fixes, ["src", "dst"], "full_outer").where("kind is null or kind <> 'drop'")
    m = F.when(F.col("kind") == "add", F.col("m")).otherwise(F.col("rep") + F.coalesce("delta", F.lit(0)))
    return joined.select("src", "dst", m.cast("long").alias("m"))


# queries answered from the summary


def neighbors(s: Summary, node: int, fixes: DataFrame | None = None) -> DataFrame:
    """Exact neighbours of one node; only its own super-node's rows are expanded."""
    one = local_summary(s, node)
    fixes = corrections(s) if fixes is None else fixes
    base = decompress(one).where((F.col("src") == node) | (F.col("dst") == node)).select("src", "dst", F.col("m").alias("rep"))
    own = fixes.where((F.col("src") == node) | (F.col("dst") == node))
    joined = base.join(own, ["src", "dst"], "full_outer").where("kind is null or kind <> 'drop'")
    m = F.when(F.col("kind") == "add", F.col("m")).otherwise(F.col("rep") + F.coalesce("delta", F.lit(0)))
    return joined.select("src", "dst", m.cast("long").alias("m"))


def local_summary(s: Summary, node: int) -> Summary:
    """The part of a summary around one node's super-node."""
    home = s.members.where(F.col("id") == node).select(F.col("sid").alias("home"))
    near = s.superedges.join(F.broadcast(home), (F.col("ssid") == F.col("home")) | (F.col("dsid") == F.col("home"))).drop("home")
    sids = near.select(F.col("ssid").alias("sid")).union(near.select("dsid")).union(home).distinct()
    return replace(s, supernodes=s.supernodes.join(sids, "sid", "left_semi"), members=s.members.join(sids, "sid", "left_semi"), superedges=near)


def degrees(s: Summary) -> DataFrame:
    """Exact in- and out-degrees, from the rebuilt edges."""
    e = reconstruct(s)
    out, inn = e.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("d_out")), e.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("d_in"))
    return s.members.select("id").join(out, "id", "left").join(inn, "id", "left").select("id", F.coalesce("d_in", F.lit(0)).alias("d_in"), F.coalesce("d_out", F.lit(0)).alias("d_out"))


def edge_multiplicity(s: Summary, src: int, dst: int) -> int:
    """Exact multiplicity of an edge, 0 if there is none."""
    row = neighbors(s, src).where((F.col("src") == src) & (F.col("dst") == dst)).first()
    return row.m if row else 0


def label_flow(s: Summary) -> DataFrame:
    """Total multiplicity from label to label, exact."""
    lab = expand_nodes(s)
    e = reconstruct(s)
    a, b = lab.select(F.col("id").alias("src"), F.col("label").alias("from")), lab.select(F.col("id").alias("dst"), F.col("label").alias("to"))
    return e.join(a, "src").join(b, "dst").groupBy("from", "to").agg(F.sum("m").alias("m"))


# sinks


def write_summary(s: Summary, path: str, run: dict | None = None) -> None:
    """One Parquet folder a table, and the run's settings."""
    for name, df in (("supernodes", s.supernodes), ("members", s.members), ("superedges", s.superedges), ("nodes", s.graph.nodes), ("edges", s.graph.edges), ("corrections", corrections(s))):
        df.write.mode("overwrite").parquet(f"{path}/{name}")
    spark = s.members.sparkSession
    info = json.dumps({"directed": s.graph.directed, "name": s.graph.name} | (run or {}))
    spark.createDataFrame([(info,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/run")


def read_summary(spark, path: str) -> Summary:
    t = {n: spark.read.parquet(f"{path}/{n}") for n in ("supernodes", "members", "superedges", "nodes", "edges")}
    info = json.loads(spark.read.text(f"{path}/run").first()[0])
    return Summary(PropertyGraph(t["nodes"], t["edges"], info["directed"], info["name"]), t["supernodes"], t["members"], t["superedges"])


SHAPES = {"clique": "box", "in_star": "invtriangle", "out_star": "triangle", "disconnected": "ellipse"}


def drawing_nodes(s: Summary, annotate: DataFrame | None = None) -> DataFrame:
    """Super-nodes with shape, colour index by label, and size; ``annotate(sid, note)`` adds scalars."""
    rank = s.supernodes.select("label").distinct()
    names = {r.label: i for i, r in enumerate(rank.orderBy("label").collect())}
    colour = F.lit(0)
    for label, i in names.items():
        colour = F.when(F.col("label").eqNullSafe(F.lit(label)), i).otherwise(colour)
    shape = F.element_at(F.create_map(*[F.lit(x) for kv in SHAPES.items() for x in kv]), F.col("glyph"))
    out = s.supernodes.select("sid", "label", "size", "glyph", shape.alias("shape"), colour.alias("colour"), "m")
    return out.join(annotate, "sid", "left") if annotate is not None else out


def to_dot(s: Summary) -> str:
    """Graphviz text of the summary (the summary only is collected)."""
    arrow, kind = ("->", "digraph") if s.graph.directed else ("--", "graph")
    lines = [f"{kind} summary {{"]
    for r in drawing_nodes(s).orderBy("sid").collect():
        lines.append(f'  {r.sid} [label="{r.label} x{r["size"]}", shape={r["shape"] if r["size"] > 1 else "point"}, colorscheme=paired12, color={r.colour % 12 + 1}];')
    lines += [f'  {r.ssid} {arrow} {r.dsid} [label="{r.m}"];' for r in s.superedges.orderBy("ssid", "dsid").collect()]
    return "\n".join([*lines, "}"])


def to_json(s: Summary) -> str:
    nodes = [r.asDict() for r in drawing_nodes(s).orderBy("sid").collect()]
    return json.dumps({"directed": s.graph.directed, "nodes": nodes, "links": [r.asDict() for r in s.superedges.orderBy("ssid", "dsid").collect()]})


def to_graphml(s: Summary) -> str:
    from xml.sax.saxutils import escape

    out = ['<?xml version="1.0"?><graphml xmlns="http://graphml.graphdrawing.org/xmlns">', '<key id="l" for="node" attr.name="label" attr.type="string"/>', '<key id="g" for="node" attr.name="glyph" attr.type="string"/>', '<key id="n" for="node" attr.name="size" attr.type="long"/>', '<key id="m" for="edge" attr.name="m" attr.type="long"/>', f'<graph edgedefault="{"directed" if s.graph.directed else "undirected"}">']
    for r in drawing_nodes(s).orderBy("sid").collect():
        out.append(f'<node id="n{r.sid}"><data key="l">{escape(str(r.label))}</data><data key="g">{r.glyph}</data><data key="n">{r["size"]}</data></node>')
    out += [f'<edge source="n{r.ssid}" target="n{r.dsid}"><data key="m">{r.m}</data></edge>' for r in s.superedges.orderBy("ssid", "dsid").collect()]
    return "".join([*out, "</graph></graphml>"])


def register_views(s: Summary, name: str) -> None:
    """Temporary views of all tables of a summary."""
    for part, df in (("nodes", s.graph.nodes), ("edges", s.graph.edges), ("supernodes", s.supernodes), ("superedges", s.superedges), ("members", s.members), ("corrections", corrections(s))):
        df.createOrReplaceTempView(f"{name}_{part}")
