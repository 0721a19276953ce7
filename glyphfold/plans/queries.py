"""Named queries over a folder of tables, and their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from glyphfold.functions import bits
from glyphfold.operators import baselines, candidates, ledger, measures, merge, similarity, summary, synth
from glyphfold.plans import workloads as w
from glyphfold.plans import partition_queries
from glyphfold.plans.graph_sql import GRAPHS, UNDIRECTED, with_graph
from glyphfold.plans.ledger_sql import IDENTITY, chan, diff_sql, int_sql, log2c
from glyphfold.sources import graphs
from glyphfold.streaming import windows

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def graph(name: str, **kw) -> Callable:
    return lambda s, d: graphs.BUILDERS[name](s, d, **kw)


R6 = lambda c: F.round(c, 6)


# graphs ------------------------------------------------------------------------------

for _g in GRAPHS:
    add(f"edges_{_g}", lambda s, d, g=_g: graphs.BUILDERS[g](s, d).edges.select("src", "dst", F.col("m").cast("long").alias("m")), with_graph(_g, "select src, dst, m from e"))
    add(f"nodes_{_g}", lambda s, d, g=_g: graphs.BUILDERS[g](s, d).nodes, with_graph(_g, "select id, label from v"))
    add(
        f"w1_profile_{_g}",
        lambda s, d, g=_g: graphs.profile(graphs.BUILDERS[g](s, d)),
        with_graph(
            _g,
            f"""select '{_g}' as graph, (select count(*) from v) as v, (select count(distinct label) from v) as labels, count(*) as e, coalesce(sum(m), 0)::bigint as m_edges,
            count(*) filter (src = dst) as loops, coalesce(max(m), 0)::bigint as max_m, {str(_g not in UNDIRECTED).lower()} as directed from e""",
        ),
    )
    # closed form of both ledgers of the plain graph
    add(
        f"identity_bits_{_g}",
        lambda s, d, g=_g: ledger.identity_bits(graphs.BUILDERS[g](s, d)).select(F.round("printed", 3).alias("printed"), F.round("sound", 3).alias("sound")),
        with_graph(_g, f"select round(p, 3) as printed, round(p + vs * log2(vs), 3) as sound from (select {IDENTITY} as p, (select count(*)::double from v) as vs)"),
    )
    add(f"rebuild_group_{_g}", lambda s, d, g=_g: summary.reconstruct(baselines.group_summary(w.built(s, d, g), "duplicates")), with_graph(_g, "select src, dst, m from e"))
    add(f"rebuild_search_{_g}_b5", lambda s, d, g=_g: summary.reconstruct(w.summary_of(s, d, g, 5)), with_graph(_g, "select src, dst, m from e"))

for _g in ("trade_nation", "acct_segment", "event_states", "host_links", "doc_cites", "fk_tree", "order_coitem"):
    add(f"summary_{_g}", lambda s, d, g=_g: w.ratios_by_resolution(s, d, g))
    add(f"candidates_{_g}", lambda s, d, g=_g: w.candidate_report(s, d, g))
add("rebuild_search_trade_nation_b1", lambda s, d: summary.reconstruct(w.summary_of(s, d, "trade_nation", 1)), with_graph("trade_nation", "select src, dst, m from e"))
add("rebuild_search_host_links_b10", lambda s, d: summary.reconstruct(w.summary_of(s, d, "host_links", 10)), with_graph("host_links", "select src, dst, m from e"))
add("rebuild_rounds_host_links_b2", lambda s, d: summary.reconstruct(w.summary_of(s, d, "host_links", 2, engine="rounds")), with_graph("host_links", "select src, dst, m from e"))

# codes -------------------------------------------------------------------------------

def returned(s: SparkSession, d: str) -> DataFrame:
    """Subset sizes per supplier: k of n lines came back."""
    li = s.read.parquet(f"{d}/lineitem.parquet").groupBy(F.col("l_suppkey").alias("s"))
    return bits.subset_codes(li.agg(F.count("*").alias("n"), F.count_if(F.col("l_returnflag") == "R").alias("k")))


_returned = "from (select l_suppkey as s, count(*) as n, count(*) filter (l_returnflag = 'R') as k from lineitem group by 1)"
add("codes_int", lambda s, d: s.read.parquet(f"{d}/orders.parquet").select(F.col("o_orderkey").alias("k"), R6(bits.int_bits(F.col("o_orderkey"))).alias("bits")), f"select k, round({int_sql('k')}, 6) as bits from (select o_orderkey as k from orders)")
add("codes_binomial", lambda s, d: returned(s, d).select("s", "n", "k", R6(F.col("binomial")).alias("bits")), f"select s, n, k, round(abs({log2c('n', 'k')}), 6) as bits {_returned}")
add(
    "codes_entropy_gap",
    lambda s, d: returned(s, d).where("k > 0 and k < n").select("s", "n", "k", R6(F.col("entropy")).alias("entropy"), (F.col("entropy") >= F.col("binomial")).alias("holds")),
    f"select s, n, k, round(-k * log2(k / n::double) - (n - k) * log2((n - k) / n::double), 6) as entropy, true as holds {_returned} where k > 0 and k < n",
)
add(
    "codes_diff",
    lambda s, d: s.read.parquet(f"{d}/lineitem.parquet").groupBy((F.col("l_partkey") + 1).alias("m")).agg(F.count("*").alias("n")).select("m", "n", R6(bits.diff_bits(F.col("m"), F.lit(37))).alias("bits")),
    f"select m, n, round({diff_sql('m', '37')}, 6) as bits from (select l_partkey + 1 as m, count(*) as n from lineitem group by 1)",
)
add(
    "codes_uniform_multiplicity",
    lambda s, d: bits.uniform_multiplicity_bits(graphs.trade_nation(s, d).edges).select(F.round("bits", 3).alias("bits")),
    with_graph("trade_nation", "select round(count(*) * log2(max(m)), 3) as bits from e"),
)
add(
    "codes_bag",
    lambda s, d: bits.bag_diff_bits(graphs.trade_nation(s, d).edges.withColumn("rep", F.lit(96)), ["src"], "m", "rep").select("src", F.round("bits", 4).alias("bits")),
    with_graph("trade_nation", f"select src, round(sum({diff_sql('m', '96')}), 4) as bits from e group by src"),
)
# similarity --------------------------------------------------------------------------

TOK = "tok as (select src as id, dst * 2 + 1 as t from e union all select dst, src * 2 from e)"
TOK_U = "tok as (select src as id, dst * 2 as t from e union select dst, src * 2 from e)"
PAIR = """deg as (select id, count(*) as d from tok group by id),
  sh as (select x.id as a, y.id as b, count(*) as n from tok x join tok y on x.t = y.t and x.id < y.id group by 1, 2),
  jac as (select a, b, n / (p.d + q.d - n)::double as jd, p.d as da, q.d as db from sh join deg p on p.id = a join deg q on q.id = b)"""

add(
    "band_curve",
    lambda s, d: similarity.exact_simpairs(w.built(s, d, "acct_segment")).select(R6(F.col("jd")).alias("j")).distinct().crossJoin(s.range(1, 5).select(F.col("id").alias("r"))).crossJoin(s.range(1, 11).select(F.col("id").alias("b"))).select("j", "r", "b", R6(bits.band_curve(F.col("j"), F.col("r"), F.col("b"))).alias("p"), R6(bits.threshold(F.col("r"), F.col("b"))).alias("t")),
    with_graph(
        "acct_segment",
        "select j, r, b, round(1 - power(1 - power(j, r), b), 6) as p, round(power(1.0 / b, 1.0 / r), 6) as t from (select distinct round(jd, 6) as j from jac), (select unnest(range(1, 5)) as r), (select unnest(range(1, 11)) as b)",
        f"{TOK}, {PAIR}",
    ),
)
for _g in ("trade_nation", "acct_segment", "handover", "host_links", "doc_cites", "fk_tree"):
    if _g != "fk_tree":
        add(f"jaccard_directed_{_g}", lambda s, d, g=_g: similarity.exact_simpairs(w.built(s, d, g), 0.2).select("a", "b", R6(F.col("jd")).alias("jd")), with_graph(_g, "select a, b, round(jd, 6) as jd from jac where jd >= 0.2", f"{TOK}, {PAIR}"))
    # the filtered pairs of the candidate search, each with its exact similarity
for _g in ("host_links", "vote_sim", "order_coitem"):
    add(f"jaccard_undirected_{_g}", lambda s, d, g=_g: similarity.similar_pairs(w.built(s, d, g), 0.2, "undirected").select("a", "b", R6(F.col("jd")).alias("jd")), with_graph(_g, "select a, b, round(jd, 6) as jd from jac where jd >= 0.2", f"{TOK_U}, {PAIR}"))
for _g in ("trade_nation", "host_links"):
    add(
        f"simpairs_exact_{_g}",
        lambda s, d, g=_g: similarity.exact_simpairs(w.built(s, d, g), candidates.threshold(2, 10)).select("a", "b", R6(F.col("jd")).alias("jd"), candidates.entry_band(F.col("jd"), 2).alias("entry_b")),
        with_graph(_g, "select a, b, round(jd, 6) as jd, ceil(power(jd, -2) - 1e-9)::int as entry_b from jac where jd >= power(0.1, 0.5)", f"{TOK}, {PAIR}"),
    )


def _jaccard_given(s, d):
    g = w.built(s, d, "host_links")
    pairs = g.nodes.select(F.col("id").alias("a")).join(g.nodes.select(F.col("id").alias("b"), "label"), F.lit(True)).where("a < b and label = 'com'").select("a", "b")
    return similarity.jaccard_for(similarity.neighbor_tokens(g), pairs).where("jd > 0").select("a", "b", R6(F.col("jd")).alias("jd"))


add("jaccard_given_pairs", _jaccard_given, with_graph("host_links", "select a, b, round(jd, 6) as jd from jac join v on v.id = b where label = 'com'", f"{TOK}, {PAIR}"))
add(
    "size_bound_host_links",
    lambda s, d: (lambda t: similarity.exact_simpairs(w.built(s, d, "host_links")).join(t.select(F.col("id").alias("a"), F.col("d").alias("da")), "a").join(t.select(F.col("id").alias("b"), F.col("d").alias("db")), "b").select("a", "b", R6(similarity.size_bound(F.col("da"), F.col("db"))).alias("bound"), (F.col("jd") <= similarity.size_bound(F.col("da"), F.col("db")) + 1e-12).alias("holds")))(similarity.degrees(similarity.neighbor_tokens(w.built(s, d, "host_links")))),
    with_graph("host_links", "select a, b, round(least(da, db) / greatest(da, db)::double, 6) as bound, true as holds from jac", f"{TOK}, {PAIR}"),
)
add(
    "degree_window_host_links",
    lambda s, d: similarity.window_pairs(similarity.degrees(similarity.neighbor_tokens(w.built(s, d, "host_links"))).select(F.lit(0).alias("cluster"), "id", "d"), 0.5).select("a", "b"),
    with_graph("host_links", "select x.id as a, y.id as b from deg x join deg y on x.id < y.id and least(x.d, y.d) >= floor(greatest(x.d, y.d) * 0.5)", f"{TOK}, deg as (select id, count(*) as d from tok group by id)"),
)

# minhash -----------------------------------------------------------------------------

P, sig_sql = candidates.PRIME, partition_queries.sig_cte


def bucket_sql(band: int) -> str:
    return f"select h_{2 * band}::varchar || '-' || h_{2 * band + 1}::varchar as key, id from sig qualify count(*) over (partition by h_{2 * band}, h_{2 * band + 1}) > 1"


for _g in ("host_links", "trade_nation"):
    add(f"minhash_affine_{_g}", lambda s, d, g=_g: candidates.minhash(w.built(s, d, g), 2, 3), with_graph(_g, "select * from sig", f"{TOK}, {sig_sql(6)}"))
    add(f"buckets_{_g}", lambda s, d, g=_g: candidates.buckets(candidates.minhash(w.built(s, d, g), 2, 2), 2, 1), with_graph(_g, bucket_sql(1), f"{TOK}, {sig_sql(4)}"))


def _clusters(s, d):
    sig = candidates.minhash(w.built(s, d, "host_links"), 2, 3)
    c = None
    for band in range(3):
        c = candidates.grow_clusters(c, candidates.buckets(sig, 2, band))
    return c


_links = " union ".join(f"select 'k{i}' || key as k, id from ({bucket_sql(i)})" for i in range(3))
CLUSTER = f"""bk as ({_links}), low as (select k, min(id) as lo from bk group by k), l as (select id, lo from bk join low using (k) union select lo, id from bk join low using (k)),
  reach(id, root) as (select distinct id, id from bk union select reach.id, l.lo from reach join l on reach.root = l.id)"""
_cl = with_graph("host_links", "select id, min(root) as cluster from reach group by id", f"{TOK}, {sig_sql(6)}, {CLUSTER}").replace("with ", "with recursive ", 1)
add("clusters_incremental_host_links", _clusters, _cl)
add("clusters_plain_host_links", lambda s, d: candidates.lsh_clusters(candidates.minhash(w.built(s, d, "host_links"), 2, 3), 2, 3), _cl)


def _verified(s, d):
    g = w.built(s, d, "host_links")
    tok = similarity.neighbor_tokens(g)
    sig = candidates.minhash(g, 2, 3)
    before, out = None, None
    for band in range(3):
        now = candidates.grow_clusters(before, candidates.buckets(sig, 2, band))
        new = candidates.verify_new_pairs(before, now, tok, 2, candidates.threshold(2, 3))
        out = new if out is None else out.unionByName(new)
        before = now
    return out.select("a", "b", R6(F.col("jd")).alias("jd"), "entry_b")


add(
    "simpairs_verified_host_links",
    _verified,
    with_graph(
        "host_links",
        "select a, b, round(jd, 6) as jd, ceil(power(jd, -2) - 1e-9)::int as entry_b from jac join c x on x.id = a join c y on y.id = b and x.cluster = y.cluster where jd >= power(1.0 / 3, 0.5)",
        f"{TOK}, {PAIR}, {sig_sql(6)}, {CLUSTER}, c as (select id, min(root) as cluster from reach group by id)",
    ).replace("with ", "with recursive ", 1),
)

def _cliques(s, d):
    g = w.built(s, d, "host_links")
    return candidates.emerging_cliques(candidates.simgraph(similarity.exact_simpairs(g, 0.5).withColumn("entry_b", candidates.entry_band(F.col("jd"), 2)), 4), None).select("size", R6(F.col("quality")).alias("quality"), "ids")


add("cliques_host_links", _cliques)

# merging rules on the partition by label ----------------------------------------------

PART = "mem as (select id, min(id) over (partition by label) as sid from v), size as (select sid, count(*) as n from mem group by sid)"
INNER = "inn as (select x.sid, e.src, e.dst, e.m from e join mem x on x.id = e.src join mem y on y.id = e.dst and x.sid = y.sid where e.src <> e.dst)"
GLYPH = """deg as (select sid, max(d) filter (k = 'i') as d_in, max(d) filter (k = 'o') as d_out from (select sid, dst, 'i' as k, count(*) as d from inn group by 1, 2 union all select sid, src, 'o', count(*) from inn group by 1, 2) group by sid),
  gl as (select s.sid, s.n, (select count(*) from inn where inn.sid = s.sid) as e, coalesce(d_in, 0) as d_in, coalesce(d_out, 0) as d_out from size s left join deg using (sid)),
  gly as (select *, n - 1 + e - 2 * d_in as cost_in, n - 1 + e - 2 * d_out as cost_out from gl)"""
for _g in ("trade_nation", "acct_segment", "event_states", "doc_cites", "handover"):
    add(
        f"glyph_rule_{_g}",
        lambda s, d, g=_g: (lambda x: merge.decide_glyph(baselines.label_members(x).select(F.col("sid").alias("pid"), "id"), x.edges).drop("hub"))(w.built(s, d, g)),
        with_graph(
            _g,
            """select sid as pid, case when 2 * e >= n * (n - 1) then 'clique' when cost_in < e and cost_in <= cost_out then 'in_star' when cost_out < e then 'out_star' else 'disconnected' end as glyph,
            n, e, d_in, d_out, cost_in, cost_out from gly""",
            f"{PART}, {INNER}, {GLYPH}",
        ),
    )
BUNDLE = "bun as (select x.sid as a, y.sid as b, e.m from e join mem x on x.id = e.src join mem y on y.id = e.dst where x.sid <> y.sid)"
REP = """hist as (select a, b, m as x, count(*) as c from bun group by 1, 2, 3), tries as (select distinct a, b, x + k as rep from hist, (select unnest([-1, 0, 1]) as k) where x + k >= 1),
  cost as (select t.a, t.b, t.rep, round(sum(c * (case when x = rep then 1.0 else 2 * log2(abs(x - rep)) + 3 end)), 6) as bits from tries t join hist h on t.a = h.a and t.b = h.b group by 1, 2, 3),
  rep as (select a, b, arg_min(rep, (bits, rep)) as rep, min(bits) as bits from cost group by 1, 2)"""
for _g in ("trade_nation", "acct_segment", "host_links"):
    add(
        f"bundles_{_g}",
        lambda s, d, g=_g: (lambda x: x.edges.join(baselines.label_members(x).select(F.col("id").alias("src"), F.col("sid").alias("a")), "src").join(baselines.label_members(x).select(F.col("id").alias("dst"), F.col("sid").alias("b")), "dst").where("a <> b").groupBy("a", "b").agg(F.count("*").alias("n"), F.sum("m").alias("m")))(w.built(s, d, g)),
        with_graph(_g, "select a, b, count(*) as n, sum(m)::bigint as m from bun group by 1, 2", f"{PART}, {BUNDLE}"),
    )
    add(
        f"rep_exact_{_g}",
        lambda s, d, g=_g: (lambda x: merge.rep_exact_sql(x.edges.join(baselines.label_members(x).select(F.col("id").alias("src"), F.col("sid").alias("a")), "src").join(baselines.label_members(x).select(F.col("id").alias("dst"), F.col("sid").alias("b")), "dst").where("a <> b"), ["a", "b"]).select("a", "b", "rep", F.round("bits", 4).alias("bits")))(w.built(s, d, g)),
        with_graph(_g, "select a, b, rep, round(bits, 4) as bits from rep", f"{PART}, {BUNDLE}, {REP}"),
    )
WITH = f"{int_sql('rep.rep')} + {chan('n_a * n_b', 'n_a * n_b - bn.n')} + rep.bits"
WITHOUT = f"{chan('n_a * n_b', 'bn.n')} + bn.plain"
BN = f"bn as (select a, b, count(*) as n, sum({int_sql('m')}) as plain from bun group by 1, 2)"


def _rule(s, d, g):
    x = w.built(s, d, g)
    smr = baselines.group_summary(x, "label", "all")
    return baselines.decide_superedges(baselines.bundle_edges(smr.members, smr.supernodes, x.edges)).select("a", "b", F.round("with_bits", 3).alias("with_bits"), F.round("without_bits", 3).alias("without_bits"), "keep")


for _g in ("trade_nation", "acct_segment"):
    add(
        f"superedge_rule_{_g}",
        lambda s, d, g=_g: _rule(s, d, g),
        with_graph(
            _g,
            f"select a, b, round({WITH}, 3) as with_bits, round({WITHOUT}, 3) as without_bits, {WITH} < {WITHOUT} as keep from (select bn.*, p.n as n_a, q.n as n_b from bn join size p on p.sid = bn.a join size q on q.sid = bn.b) bn join rep using (a, b)",
            f"{PART}, {BUNDLE}, {REP}, {BN}",
        ),
    )

for _g in ("trade_nation", "acct_segment"):
    add(f"label_flow_{_g}", lambda s, d, g=_g: summary.label_flow(w.summary_of(s, d, g, 5)), with_graph(_g, 'select x.label as "from", y.label as "to", sum(m)::bigint as m from e join v x on x.id = src join v y on y.id = dst group by 1, 2'))
    add(
        f"degrees_{_g}",
        lambda s, d, g=_g: summary.degrees(w.summary_of(s, d, g, 5)),
        with_graph(_g, "select id, (select count(*) from e where dst = id) as d_in, (select count(*) from e where src = id) as d_out from v"),
    )
add("neighbors_trade_nation", lambda s, d: summary.neighbors(w.summary_of(s, d, "trade_nation", 5), 7), with_graph("trade_nation", "select src, dst, m from e where src = 7 or dst = 7"))
add("summary_validity", lambda s, d: w.summary_of(s, d, "doc_cites", 5).validate())
add("drawing_trade_nation", lambda s, d: summary.drawing_nodes(w.summary_of(s, d, "trade_nation", 5)))

# experiments ---------------------------------------------------------------------------

add("w2_dominance", w.dominance_case)
add("w3_reduction", w.coarse_case)
add("w3_top_hosts", w.top_single_hosts)
add("w4_breakdown", w.area_breakdown)
add("w4_bridges", w.area_bridges)
add("w5_two_resolutions", w.two_resolutions)
_H = "(case when p > 0 and p < 1 then -p * ln(p) - (1 - p) * ln(1 - p) else 0.0 end)"
_VOTE = f"with b as (select label::bigint as label, unnest(range(0, len(embedding)))::bigint as ballot, unnest(embedding) as x from embeddings), h as (select label, ballot, count(*) as n, avg((x > 0)::int) as p from b group by 1, 2), en as (select label, ballot, n, round({_H}, 6) as entropy from h)"
add("w6_vote_entropy", w.vote_entropies, f"{_VOTE} select label, ballot, n, entropy from en")
add(
    "w6_entropy_summary",
    lambda s, d: w.vote_entropy_summary(s, d).select("label", "median", "contested"),
    f"{_VOTE} select label, round(quantile_cont(entropy, 0.5), 6) as median, count(*) filter (entropy >= 0.68) as contested from en group by label",
)
for _g in ("trade_nation", "event_states", "acct_segment"):
    add(f"w7_labelling_{_g}", lambda s, d, g=_g: w.labelling_study(s, d, g))
for _g in ("vote_sim", "doc_cites", "order_coitem"):
    add(f"w8_tradeoff_{_g}", lambda s, d, g=_g: w.tradeoff_of(s, d, g, ("pairmerge",), "D" if g == "doc_cites" else ""))
for _g in ("trade_nation", "acct_segment", "event_states"):
    add(f"w9_tradeoff_{_g}", lambda s, d, g=_g: w.tradeoff_of(s, d, g, ("pairmerge",)))
add("w10_tradeoff_host_links", lambda s, d: w.tradeoff_of(s, d, "host_links", ("pairmerge", "vocab_plain", "vocab_top10", "vocab_top100", "vocab_greedy_forget"), "LMDS"))
for _g in ("part_copurchase", "cust_supp"):
    add(f"w10_tradeoff_{_g}", lambda s, d, g=_g: w.tradeoff_of(s, d, g, ("pairmerge", "vocab_top10"), "LMDS", (5,)))
add("w11_growth", lambda s, d: w.growth_scaling(s))
add("w11_slope", lambda s, d: w.growth_slopes(s))
add("w12_sampling", lambda s, d: w.sampling_scaling(s, d))
add("w13_planted", lambda s, d: w.planted_recall(s))
add(
    "gain_table",
    w.label_gains,
    with_graph(
        "trade_nation",
        """select labelling, round(actual, 6) as actual, round(by_chance, 6) as by_chance, round((actual - by_chance) / (1 - by_chance), 4) as gain from (
          select labelling, sum(m) filter (x = y)::double / sum(m) as actual,
            (select sum(o.m * i.m)::double from (select x as l, sum(m)::double as m from lab k where k.labelling = lab.labelling group by 1) o join (select y as l, sum(m)::double as m from lab k where k.labelling = lab.labelling group by 1) i using (l)) / (sum(m)::double * sum(m)) as by_chance
          from lab group by labelling)""",
        """lab as (select 'A' as labelling, p.label as x, q.label as y, m from e join v p on p.id = src join v q on q.id = dst
          union all select 'B', case when src % 2 = 0 then 'even' else 'odd' end, case when dst % 2 = 0 then 'even' else 'odd' end, m from e)""",
    ),
)
add("shuffle_histogram", w.shuffle_histogram, with_graph("trade_nation", "select label, count(*) as n from v group by label"))
_draw = f"((((src % {P}) * 48271 + (dst % {P}) * 16807 + 42 * 69621) % {P}) * 40692 % {P}) % 1000000"
for _f in (10, 50):
    add(f"sample_edges_{_f}", lambda s, d, f=_f: synth.sample_edges(graphs.order_coitem(s, d), f / 100).edges.select("src", "dst", "m"), with_graph("order_coitem", f"select src, dst, m from e where {_draw} < {_f * 10000}"))
add("kout_edges", lambda s, d: w.customer_growth(s, d))
add(
    "kout_degrees",
    lambda s, d: w.customer_growth(s, d).groupBy("src").agg(F.count("*").alias("k"), (F.max("dst") < F.col("src")).alias("earlier")),
    "select src, 10::bigint as k, true as earlier from (select row_number() over (order by c_custkey) - 1 as src from customer) where src > 0",
)


def vocab_bits(s: SparkSession, d: str, name: str) -> DataFrame:
    """Bits of the structure vocabulary by way of selection: the structures, all with the errors, and the plain error matrix."""
    g, rows = w.built(s, d, name).simplify({"L", "M", "D", "S"}), []
    for select in ("plain", "top10", "top100", "greedy_forget"):
        words = baselines.vocab_summary(g, select)
        rows.append((select, len(words), words.attrs["model"], words.attrs["bits"], words.attrs["before"]))
    return s.createDataFrame(rows, "selection string, structures int, model double, bits double, before double")


# baselines and ablations ----------------------------------------------------------------

add("pairmerge_randomized_host_links", lambda s, d: baselines.pairmerge_cost(baselines.pairmerge_randomized(w.built(s, d, "host_links"))))
add("pairmerge_greedy_host_links", lambda s, d: baselines.pairmerge_cost(baselines.pairmerge_greedy(w.built(s, d, "host_links"))))
add("pairmerge_rounds_host_links", lambda s, d: baselines.pairmerge_cost(baselines.pairmerge_rounds(w.built(s, d, "host_links"))))
add("pairmerge_rebuild_host_links", lambda s, d: summary.reconstruct(baselines.pairmerge_randomized(w.built(s, d, "host_links"))), with_graph("host_links", "select src, dst, m from e"))
for _sel in ("plain", "top10", "top100", "greedy_forget"):
    add(f"vocab_{_sel}_host_links", lambda s, d, k=_sel: s.createDataFrame(baselines.vocab_summary(w.built(s, d, "host_links").simplify({"L", "M", "D", "S"}), k), "kind string, size long, gain double"))
add("undirected_similarity_trade_nation", lambda s, d: measures.size_reduction(w.summary_of(s, d, "trade_nation", 5, similarity="undirected")))
add("ablation_rep", lambda s, d: measures.ablation_rep(graphs.trade_nation(s, d).edges.select(F.col("src").cast("string").alias("key"), "m")))
add("ablation_glyph", lambda s, d: s.createDataFrame(list(measures.ablation_glyph(w.built(s, d, "doc_cites")).items()), "rule string, ratio double"))
add("vocab_bits_host_links", lambda s, d: vocab_bits(s, d, "host_links"))
for _t in ("L", "M", "D", "S"):
    add(f"without_{_t}_doc_cites", lambda s, d, t=_t: measures.size_reduction(merge.summarize(w.built(s, d, "doc_cites").simplify({t}))))

# streams ----------------------------------------------------------------------------------

add(
    "stream_event_edges",
    lambda s, d: windows.fold_edges(windows.run_to_table(windows.successors(windows.read_events(s, f"{d}/events.parquet")), "edges")),
    with_graph("event_states", "select src, dst, m from e"),
)
add(
    "window_counts",
    lambda s, d: windows.window_counts(s.read.parquet(f"{d}/events.parquet")).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n"),
    "select strftime(ts, '%Y-%m-%d') as day, event_type, count(*) as n from events group by 1, 2",
)
add("session_counts", lambda s, d: windows.session_counts(s.read.parquet(f"{d}/events.parquet")).groupBy().agg(F.count("*").alias("sessions"), F.sum("n").alias("events")), """select count(*) as sessions, sum(n)::bigint as events from (select user_id, s, count(*) as n from (select user_id, sum(case when gap is null or gap > interval 6 hour then 1 else 0 end) over (partition by user_id order by ts, event_id) as s from (select *, ts - lag(ts) over (partition by user_id order by ts, event_id) as gap from events)) group by 1, 2)""")


QUERIES.update(partition_queries.QUERIES)
SQL.update(partition_queries.SQL)


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Super-nodes of the trade graph, with shape and colour."""
    return summary.drawing_nodes(w.summary_of(spark, d, "trade_nation", 5))
