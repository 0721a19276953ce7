"""Queries over summaries of given partitions: every part of the ledger, expansion, corrections and measures, each with its SQL twin."""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from glyphfold.operators import baselines, candidates, ledger, measures, merge, similarity, summary
from glyphfold.operators.summary import Summary
from glyphfold.plans import ledger_sql as ls
from glyphfold.plans import workloads as w
from glyphfold.plans.graph_sql import UNDIRECTED, with_graph
from glyphfold.sources.graphs import PropertyGraph

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

#: (partition, graph): stars stand for the key graph without labels.
GROUPS = (
    ("label", "trade_nation"), ("label", "acct_segment"), ("label", "event_states"), ("label", "handover"), ("label", "doc_cites"), ("label", "vote_sim"), ("label", "order_coitem"),
    ("duplicates", "acct_segment"), ("duplicates", "host_links"), ("duplicates", "doc_cites"), ("duplicates", "vote_sim"), ("duplicates", "order_coitem"), ("duplicates", "cust_supp"),
    ("random", "acct_segment"), ("random", "host_links"), ("random", "vote_sim"),
    ("stars", "fk_full"), ("stars", "fk_tree"),
)


def graph_of(s: SparkSession, d: str, name: str, key: str) -> PropertyGraph:
    g = w.built(s, d, name)
    return g.simplify({"L"}) if key == "stars" else g


def grouped(s: SparkSession, d: str, name: str, key: str, superedges: str = "rule") -> Summary:
    return baselines.group_summary(graph_of(s, d, name, key), key, superedges)


def twin(name: str, key: str, body: str, more: str = "", keep: str = "rule", code: str = "binomial") -> str:
    """SQL over the priced partition ``key`` of a graph."""
    directed = name not in UNDIRECTED
    ctes = ls.partition_ctes(ls.PARTITIONS[key](directed), directed, keep, code)
    sql = with_graph(name, body, f"{ctes}, {more}" if more else ctes)
    return sql.replace("v as (", "v as (select id, '*' as label from (", 1).replace("), mem as (", ")), mem as (", 1) if key == "stars" else sql


def bits_of(s: Summary, codes: ledger.Codes = ledger.Codes()) -> DataFrame:
    return ledger.total_bits(s, codes).select("part", "ledger", F.round("bits", 3).alias("bits"))


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


for _key, _g in GROUPS:
    add(f"group_{_key}_{_g}", lambda s, d, g=_g, k=_key: bits_of(grouped(s, d, g, k)), twin(_g, _key, ls.LEDGER))
for _key, _g in (("label", "trade_nation"), ("stars", "fk_full"), ("duplicates", "vote_sim")):
    add(f"ledger_all_superedges_{_g}", lambda s, d, g=_g, k=_key: bits_of(grouped(s, d, g, k, "all")), twin(_g, _key, ls.LEDGER, keep="all"))
    add(f"ledger_entropy_{_g}", lambda s, d, g=_g, k=_key: bits_of(grouped(s, d, g, k, "all"), ledger.Codes(code="entropy")), twin(_g, _key, ls.LEDGER, keep="all", code="entropy"))


def expansion(s: SparkSession, d: str, name: str, key: str) -> DataFrame:
    return summary.decompress(grouped(s, d, name, key)).select("src", "dst", "m")


def fixes(s: SparkSession, d: str, name: str, key: str) -> DataFrame:
    return summary.corrections(grouped(s, d, name, key)).na.fill(0, ["m", "delta"])


for _key, _g in (("label", "trade_nation"), ("label", "acct_segment"), ("stars", "fk_full"), ("duplicates", "host_links"), ("duplicates", "vote_sim")):
    _x = ls.expansion_sql(_g not in UNDIRECTED)
    add(f"expand_{_g}", lambda s, d, g=_g, k=_key: expansion(s, d, g, k), twin(_g, _key, "select src, dst, m from approx", _x))
    add(f"corrections_{_g}", lambda s, d, g=_g, k=_key: fixes(s, d, g, k), twin(_g, _key, ls.CORRECTIONS, _x))
for _key, _g in (("stars", "fk_full"), ("duplicates", "vote_sim"), ("duplicates", "order_coitem")):
    add(f"rebuild_{_key}_{_g}", lambda s, d, g=_g, k=_key: summary.reconstruct(grouped(s, d, g, k)), with_graph(_g, "select src, dst, m from e"))


def ratios(s: SparkSession, d: str, name: str, key: str) -> DataFrame:
    """Bits before and after, and the ratio, printed ledger."""
    made = grouped(s, d, name, key)
    before = ledger.bits_before(made.graph)["printed"]
    after = ledger.total_bits(made).where("ledger = 'printed'").agg(F.sum("bits").alias("after"))
    return after.select(F.lit(round(before, 3)).alias("before"), F.round("after", 3).alias("after"), F.round((F.lit(before) - F.col("after")) / F.lit(before), 6).alias("ratio"))


_RATIO = f"select round(p, 3) as before, round(a, 3) as after, round((p - a) / p, 6) as ratio from (select {ls.IDENTITY} as p, (select sum(bits)::double from parts where part <> 'location') as a)"
_SIZES = "select (select sum(n)::bigint from size) as nodes, (select count(*) from size) as supernodes, (select count(*) from e) as edges, (select count(*) from se) as superedges"
_REDUCTION = f"select *, nodes / supernodes::double as node_factor, edges / greatest(superedges, 1)::double as edge_factor from ({_SIZES})"
_KIND = "case when s.n = 1 then 'single' when glyph in ('in_star', 'out_star') then 'star' else glyph end"
_SHARES = ", ".join(f"round(coalesce(sum(n) filter (kind = '{k}'), 0) / sum(n), 6) as {k}" for k in ("clique", "disconnected", "star", "single"))
_BREAKDOWN = f"select label, sum(n)::bigint as n, {_SHARES} from (select label, s.n, {_KIND} as kind from size s join glyphs using (sid)) group by label"
_FLOW = """select size.sid, label, size.n as size, glyph, coalesce(o.m, 0)::bigint as out_m, coalesce(i.m, 0)::bigint as in_m from size join glyphs using (sid)
  left join (select sid, sum(rep) as m from se where sid <> other group by sid) o using (sid) left join (select other as sid, sum(rep) as m from se where sid <> other group by other) i using (sid)"""
_BRIDGES = """select count(*) as single, count(*) filter (k >= 2) as bridges from (select sid as u from size where n = 1 and label = 'mixed')
  left join (select u, count(distinct label) as k from (select src as u, dst as z from e union select dst, src from e) join v on v.id = z group by u) using (u)"""
for _key, _g in (("duplicates", "host_links"), ("duplicates", "doc_cites"), ("stars", "fk_full"), ("label", "acct_segment")):
    add(f"ratio_{_key}_{_g}", lambda s, d, g=_g, k=_key: ratios(s, d, g, k), twin(_g, _key, _RATIO))
for _key, _g in (("duplicates", "host_links"), ("duplicates", "order_coitem"), ("stars", "fk_full")):
    add(f"reduction_{_key}_{_g}", lambda s, d, g=_g, k=_key: measures.size_reduction(grouped(s, d, g, k)), twin(_g, _key, _REDUCTION))
    add(f"breakdown_{_key}_{_g}", lambda s, d, g=_g, k=_key: measures.glyph_breakdown(grouped(s, d, g, k)), twin(_g, _key, _BREAKDOWN))
    add(f"flow_{_key}_{_g}", lambda s, d, g=_g, k=_key: measures.group_flow(grouped(s, d, g, k)), twin(_g, _key, _FLOW))
add("bridges_duplicates_order_coitem", lambda s, d: measures.bridge_rate(grouped(s, d, "order_coitem", "duplicates")), twin("order_coitem", "duplicates", _BRIDGES))
add("validity_stars_fk_full", lambda s, d: grouped(s, d, "fk_full", "stars").validate(), "select 'x' as problem, 0::bigint as id where false")


def glyphs_of(s: SparkSession, d: str, name: str, key: str) -> DataFrame:
    """The glyph of every group, with its hub."""
    return grouped(s, d, name, key).supernodes.select("sid", "size", "glyph", F.coalesce("hub", F.lit(-1)).alias("hub"), "m")


for _key, _g in (("stars", "fk_full"), ("duplicates", "vote_sim"), ("label", "order_coitem")):
    add(f"glyphs_{_key}_{_g}", lambda s, d, g=_g, k=_key: glyphs_of(s, d, g, k), twin(_g, _key, "select sid, n as size, glyph, coalesce(hub, -1) as hub, coalesce(rep, 1)::bigint as m from glyphs left join grep using (sid)"))


def round_changes(s: SparkSession, d: str, name: str, form: str, undirected: bool = False) -> DataFrame:
    """Bits before, and what separates the rounds' summed changes from the difference of two ledgers."""
    g = w.built(s, d, name)
    cfg = merge.SummaryConfig(b=3, ledger=form, engine="rounds", isolation="neighbours")
    made, delta = merge.rounds(g, merge.candidates_of(g, cfg, cfg.b).table(s, cfg.b), cfg)
    before, after = ledger.bits_before(g)[form], ledger.ledgers(made)[form]
    return s.createDataFrame([(round(before, 3), abs(round(after - before - delta, 4)), after < before)], "before double, gap double, smaller boolean")


for _g, _form in (("host_links", "printed"), ("host_links", "sound"), ("vote_sim", "printed"), ("vote_sim", "sound")):
    _more = "0" if _form == "printed" else "(select count(*) * log2(count(*)) from v)"
    add(
        f"rounds_change_{_form}_{_g}",
        lambda s, d, g=_g, f=_form: round_changes(s, d, g, f).select("before", "gap"),
        with_graph(_g, f"select round({ls.IDENTITY} + {_more}, 3) as before, 0.0::double as gap"),
    )
add("rebuild_rounds_nodes_vote_sim", lambda s, d: summary.reconstruct(w.summary_of(s, d, "vote_sim", 3, engine="rounds", isolation="nodes")), with_graph("vote_sim", "select src, dst, m from e"))

# candidate sets that SQL can name: the buckets of the first bands -------------------------

P = candidates.PRIME


def bucket_sets(s: SparkSession, d: str, name: str, bands: int = 2) -> DataFrame:
    """``(cid, id)``: the buckets of the first bands as candidate sets, equal sets once; cid is the smallest band and member."""
    sig = candidates.minhash(w.built(s, d, name), 2, bands)
    out = None
    for band in range(bands):
        rows = candidates.buckets(sig, 2, band)
        low = rows.groupBy("key").agg(F.min("id").alias("first"))
        own = rows.join(low, "key").select((F.col("first") * bands + band).alias("cid"), "id")
        out = own if out is None else out.unionByName(own)
    return out


def bucket_quality(s: SparkSession, d: str, name: str) -> DataFrame:
    return similarity.set_quality(bucket_sets(s, d, name), similarity.exact_simpairs(w.built(s, d, name)))


def bucket_ranking(s: SparkSession, d: str, name: str, top: int | None = None) -> DataFrame:
    ranks = merge.rank_candidates(bucket_quality(s, d, name)).select("cid", "size", F.round("quality", 6).alias("quality"), "rank")
    return ranks.where(F.col("rank") <= top) if top else ranks


def bucket_redundancy(s: SparkSession, d: str, name: str) -> DataFrame:
    return similarity.redundant_sets(bucket_sets(s, d, name), bucket_quality(s, d, name)).select("cid", "inside")


def bucket_parts(s: SparkSession, d: str, name: str) -> DataFrame:
    return merge.split_by_label(bucket_sets(s, d, name), w.built(s, d, name).nodes).select("cid", "label", F.size("ids").alias("n"), F.element_at("ids", 1).alias("first"), F.element_at("ids", -1).alias("last"))


TOK = "tok as (select src as id, dst * 2 + 1 as t from e union all select dst, src * 2 from e)"
PAIR = """deg as (select id, count(*) as d from tok group by id),
  sh as (select x.id as a, y.id as b, count(*) as n from tok x join tok y on x.t = y.t and x.id < y.id group by 1, 2),
  jac as (select a, b, n / (p.d + q.d - n)::double as jd from sh join deg p on p.id = a join deg q on q.id = b)"""


def sig_cte(rows: int, seed: int = 42) -> str:
    mapped = ", ".join(f"(t % {P} * {a} + {c}) % {P} as y_{i}" for i in range(rows) for a, c in [candidates.affine(seed, i)])
    cols = ", ".join(f"min((y_{i} * y_{i} % {P} * {candidates.SECOND} + {candidates.affine(seed, i)[1]}) % {P})::bigint as h_{i}" for i in range(rows))
    return f"sig as (select id, count(*) as d, {cols} from (select id, {mapped} from tok) group by id)"


def set_ctes(bands: int = 2) -> str:
    per = " union all ".join(f"select min(id) over (partition by h_{2 * k}, h_{2 * k + 1}) * {bands} + {k} as cid, id from sig qualify count(*) over (partition by h_{2 * k}, h_{2 * k + 1}) > 1" for k in range(bands))
    return f"""{TOK}, {PAIR}, {sig_cte(2 * bands)}, sets as ({per}),
  sizes as (select cid, count(*) as size from sets group by cid),
  quality as (select x.cid, min(coalesce(jd, 0)) as q from sets x join sets y on x.cid = y.cid and x.id < y.id left join jac on a = x.id and b = y.id group by x.cid),
  scored as (select cid, size, q, row_number() over (order by size * q desc, size desc, cid) as rank from sizes join quality using (cid)),
  inside as (select x.cid, y.cid as inside, count(*) as n from sets x join sets y on x.id = y.id and x.cid <> y.cid group by 1, 2)"""


for _g in ("host_links", "acct_segment"):
    add(f"set_quality_{_g}", lambda s, d, g=_g: bucket_quality(s, d, g).select("cid", "size", F.round("quality", 6).alias("quality")), with_graph(_g, "select cid, size, round(q, 6) as quality from sizes join quality using (cid)", set_ctes()))
    add(f"set_redundant_{_g}", lambda s, d, g=_g: bucket_redundancy(s, d, g), with_graph(_g, "select i.cid, i.inside from inside i join scored x on x.cid = i.cid join scored y on y.cid = i.inside where i.n = x.size and y.size > x.size and y.q >= x.q", set_ctes()))
    add(f"set_ranking_{_g}", lambda s, d, g=_g: bucket_ranking(s, d, g), with_graph(_g, "select cid, size, round(q, 6) as quality, rank from scored", set_ctes()))
    add(f"set_top_k_{_g}", lambda s, d, g=_g: bucket_ranking(s, d, g, 10), with_graph(_g, "select cid, size, round(q, 6) as quality, rank from scored where rank <= 10", set_ctes()))
    add(f"set_label_parts_{_g}", lambda s, d, g=_g: bucket_parts(s, d, g), with_graph(_g, "select cid, label, count(*)::int as n, min(id) as first, max(id) as last from sets join v using (id) group by cid, label having count(*) > 1", set_ctes()))

# banding against all pairs -----------------------------------------------------------------


def cluster_ctes(bands: int, tag: str = "") -> str:
    """Components of the buckets of the first bands: ``cl{tag}(id, cluster)``."""
    keys = " union all ".join(f"select 'k{k}-' || h_{2 * k} || '-' || h_{2 * k + 1} as k, id from sig qualify count(*) over (partition by h_{2 * k}, h_{2 * k + 1}) > 1" for k in range(bands))
    return f"""bk{tag} as ({keys}), l{tag} as (select id, min(id) over (partition by k) as lo from bk{tag}), hop{tag} as (select id, lo from l{tag} union select lo, id from l{tag}),
  reach{tag}(id, root) as (select distinct id, id from bk{tag} union select r.id, x.lo from reach{tag} r join hop{tag} x on r.root = x.id), cl{tag} as (select id, min(root) as cluster from reach{tag} group by id)"""


def recursive(sql: str) -> str:
    return sql.replace("with ", "with recursive ", 1)


def lsh_measures(s: SparkSession, d: str, name: str, b: int) -> DataFrame:
    q = measures.lsh_quality(w.built(s, d, name), 2, b)
    return q.select("pairs", "found", "together", F.round("recall", 6).alias("recall"), F.round("false_alarms", 6).alias("false_alarms"))


_LSH = """select *, round(found / pairs::double, 6) as recall, round(1 - found / together, 6) as false_alarms from (
  select (select count(*) from jac where jd >= power(1.0 / {b}, 0.5)) as pairs, (select count(*) from jac join cl x on x.id = a join cl y on y.id = b and x.cluster = y.cluster where jd >= power(1.0 / {b}, 0.5)) as found,
    (select sum(n * (n - 1) / 2)::double from (select count(*) as n from cl group by cluster)) as together)"""
for _g, _b in (("host_links", 5), ("acct_segment", 3)):
    add(f"lsh_quality_{_g}", lambda s, d, g=_g, b=_b: lsh_measures(s, d, g, b), recursive(with_graph(_g, _LSH.format(b=_b), f"{TOK}, {PAIR}, {sig_cte(2 * _b)}, {cluster_ctes(_b)}")))


def collisions(s: SparkSession, d: str) -> DataFrame:
    rates = measures.collision_rate(w.built(s, d, "event_states"))
    return rates.groupBy(F.floor(F.col("jd") * 10 + 1e-9).cast("int").alias("tenth")).agg(F.count("*").alias("pairs"), F.round(F.avg("rate"), 6).alias("rate"))


_SAME = " + ".join(f"(x.h_{i} = y.h_{i})::int" for i in range(64))
add("collision_rate_event_states", collisions, with_graph("event_states", f"select floor(jd * 10 + 1e-9)::int as tenth, count(*) as pairs, round(avg(({_SAME}) / 64.0), 6) as rate from jac join sig x on x.id = a join sig y on y.id = b group by 1", f"{TOK}, {PAIR}, {sig_cte(64)}"))


def unfiltered(s: SparkSession, d: str, name: str, b: int) -> DataFrame:
    """Clusters that are new or have grown, round by round, as candidate sets."""
    return w.candidate_report(s, d, name, b, False).select("b", "sets", "largest", F.round("quality", 6).alias("quality"))


def unfiltered_sql(name: str, rounds: int) -> str:
    grown = []
    for k in range(1, rounds + 1):
        old = f"left join (select cluster, count(*) as had from cl{k - 1} group by cluster) using (cluster) where had is null or had < n" if k > 1 else ""
        grown.append(f"select {k} as b, count(*)::int as sets, coalesce(max(n), 0)::int as largest, case when count(*) > 0 then round(power(1.0 / {k}, 0.5), 6) end as quality from (select cluster, count(*) as n from cl{k} group by cluster) {old}")
    ctes = ", ".join([TOK, sig_cte(2 * rounds), *(cluster_ctes(k, str(k)) for k in range(1, rounds + 1))])
    return recursive(with_graph(name, " union all ".join(grown), ctes))


for _g in ("host_links", "trade_nation"):
    add(f"candidates_unfiltered_{_g}", lambda s, d, g=_g: unfiltered(s, d, g, 3), unfiltered_sql(_g, 3))


def paths_agree(s: SparkSession, d: str, name: str) -> DataFrame:
    """Whether tables and arrays, and small and large clusters, give the same candidate sets for both hash families."""
    rows, g = [], w.built(s, d, name)
    for family in ("affine31", "xx64"):
        want = None
        for local_edges, bound in ((10**9, 5000), (0, 4)):
            c = candidates.candidate_sets(g, 2, 2, family=family, local_edges=local_edges, max_cluster=bound)
            got = {b: sorted(own) for b, own in c.sets.items()}
            want = want or got
            rows.append((family, "arrays" if local_edges else "tables", bound, got == want))
    return s.createDataFrame(rows, "family string, path string, max_cluster int, same boolean")


add(
    "candidate_paths_trade_nation",
    lambda s, d: paths_agree(s, d, "trade_nation"),
    "select * from (select unnest(['affine31', 'xx64']) as family), (values ('arrays', 5000, true), ('tables', 4, true)) t(path, max_cluster, same)",
)


def overestimate(s: SparkSession, d: str) -> DataFrame:
    """Documents that are alike without directions, and how alike they are with them: one may cite what the other is cited by."""
    g = w.built(s, d, "doc_cites")
    plain = similarity.exact_simpairs(g, 0.2, "undirected").select("a", "b", F.col("jd").alias("undirected"))
    both = plain.join(similarity.exact_simpairs(g), ["a", "b"], "left")
    return both.select("a", "b", F.round("undirected", 6).alias("undirected"), F.round(F.coalesce("jd", F.lit(0.0)), 6).alias("directed"))


TOK_U = "tok as (select src as id, dst * 2 as t from e union select dst, src * 2 from e)"
_PLAIN = re.sub(r"\b(tok|deg|sh|jac)\b", r"\1_u", f"{TOK_U}, {PAIR}")
add(
    "overestimate_example",
    overestimate,
    with_graph("doc_cites", "select a, b, round(u.jd, 6) as undirected, round(coalesce(jac.jd, 0), 6) as directed from jac_u u left join jac using (a, b) where u.jd >= 0.2", f"{TOK}, {PAIR}, {_PLAIN}"),
)


def maximal_cliques(s: SparkSession, d: str) -> DataFrame:
    """Emerging cliques against all maximal cliques of the same similarity graph: each lies inside one."""
    pairs = similarity.exact_simpairs(w.built(s, d, "acct_segment"), 0.5)
    found = candidates.emerging_cliques(pairs, None)
    exact = [set(c) for c in candidates.maximal_cliques_exact([(r.a, r.b) for r in pairs.collect()])]
    rows = [(len(r.ids), any(set(r.ids) <= c for c in exact), any(set(r.ids) == c for c in exact)) for r in found.collect()]
    out = s.createDataFrame(rows, "size int, inside boolean, maximal boolean")
    return out.groupBy("size", "inside", "maximal").agg(F.count("*").alias("cliques"))


add("maximal_cliques_acct_segment", maximal_cliques)
