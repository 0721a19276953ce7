"""DuckDB twins of the workload graphs: for each, SQL of ``e(src, dst, m)`` and ``v(id, label)``."""

KEY = "(('0x' || substr(md5({}), 1, 15))::bigint)"
LINES = """lines as (select c_nationkey::bigint as n, c_mktsegment as seg, s_nationkey::bigint as s, o_custkey as c, l_suppkey as k
  from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey)"""
ENDS = "(select src from e union select dst from e)"


def key(text: str) -> str:
    return KEY.format(text)


def fk(table: str, column: str) -> str:
    return f"({column}::bigint * 8 + {dict(region=0, nation=1, customer=2, orders=3, supplier=4)[table]})"


FK_EDGES = " union all ".join(
    f"select {fk(a, x)} as src, {fk(b, y)} as dst from {t}"
    for a, x, b, y, t in (
        ("region", "n_regionkey", "nation", "n_nationkey", "nation"),
        ("nation", "c_nationkey", "customer", "c_custkey", "customer"),
        ("customer", "o_custkey", "orders", "o_orderkey", "orders"),
        ("nation", "s_nationkey", "supplier", "s_suppkey", "supplier"),
    )
)
FK_NODES = " union all ".join(f"select {fk(t, k)} as id, '{t}' as label from {t}" for t, k in (("region", "r_regionkey"), ("nation", "n_nationkey"), ("customer", "c_custkey"), ("orders", "o_orderkey"), ("supplier", "s_suppkey")))
FOLD = "select src, dst, count(*)::bigint as m from ({}) group by 1, 2"

#: name: (common table expressions before e, e, v)
GRAPHS: dict[str, tuple[str, str, str]] = {
    "trade_nation": (LINES, "select n as src, s as dst, count(*)::bigint as m from lines group by 1, 2", "select n_nationkey::bigint as id, r_name as label from nation join region on n_regionkey = r_regionkey"),
    "acct_segment": (
        LINES,
        "select n * 10 + ascii(seg) % 10 as src, s * 10 + 9 as dst, count(*)::bigint as m from lines group by 1, 2",
        "select distinct n * 10 + ascii(seg) % 10 as id, seg as label from lines union select distinct s * 10 + 9, 'supplier' from lines",
    ),
    "event_states": (
        f"ev as (select *, {key('event_type || chr(64) || hour(ts)::varchar')} as s from events)",
        FOLD.format("select s as src, lead(s) over (partition by user_id order by ts, event_id) as dst from ev").replace("group by", "where dst is not null group by"),
        f"select distinct s as id, event_type as label from ev where s in {ENDS}",
    ),
    "handover": (
        "tot as (select user_id as id, sum(value) as t from events group by 1)",
        FOLD.format("select user_id as src, lead(user_id) over (partition by event_type order by ts, event_id) as dst from events").replace("group by", "where dst is not null group by"),
        f"select id, case when t > (select quantile_cont(t, 0.5) from tot) then 'heavy' else 'light' end as label from tot where id in {ENDS}",
    ),
    "vote_sim": (
        "x as (select vec_id, label, embedding::double[] as q from embeddings)",
        "select a.vec_id as src, b.vec_id as dst, 1::bigint as m from x a join x b on a.vec_id < b.vec_id and list_cosine_similarity(a.q, b.q) > 0.3",
        f"select vec_id as id, label::varchar as label from embeddings where vec_id in {ENDS}",
    ),
    "host_links": (
        """p as (select regexp_extract(url, '://([^/?#]*)', 1) as host, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) as path from pages)""",
        FOLD.format(f"select {key('chr(104) || chr(58) || host')} as src, {key('chr(112) || chr(58) || path')} as dst from p"),
        f"select distinct {key('chr(104) || chr(58) || host')} as id, split_part(host, '.', -1) as label from p union select distinct {key('chr(112) || chr(58) || path')}, 'path' from p",
    ),
    "order_coitem": (
        """li as (select distinct l_orderkey as o, l_partkey as p, l_suppkey as s from lineitem),
           kinds as (select o, min(p_type) as lo, max(p_type) as hi from li join part on p = p_partkey group by 1)""",
        "select distinct a.o as src, b.o as dst, 1::bigint as m from li a join li b on a.p = b.p and a.s = b.s and a.o < b.o",
        f"select o as id, case when lo = hi then lo else 'mixed' end as label from kinds where o in {ENDS}",
    ),
    "doc_cites": (
        """l0 as (select distinct doc_id, line from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where length(line) >= 20),
           l as (select doc_id, line from l0 where line in (select line from l0 group by 1 having count(*) between 2 and 50))""",
        "select a.doc_id as src, b.doc_id as dst, count(*)::bigint as m from l a join l b on a.line = b.line and a.doc_id > b.doc_id group by 1, 2",
        f"select doc_id as id, lang as label from documents where doc_id in {ENDS}",
    ),
    "part_copurchase": (
        "li as (select distinct l_orderkey as o, l_partkey as p from lineitem)",
        "select a.p as src, b.p as dst, count(*)::bigint as m from li a join li b on a.o = b.o and a.p < b.p group by 1, 2",
        f"select src as id, '*' as label from {ENDS}",
    ),
    "cust_supp": (LINES, "select c * 2 as src, k * 2 + 1 as dst, count(*)::bigint as m from lines group by 1, 2", f"select src as id, '*' as label from {ENDS}"),
    "fk_tree": ("", FOLD.format(FK_EDGES), FK_NODES),
    "fk_full": ("", FOLD.format(FK_EDGES + f" union all select {fk('orders', 'l_orderkey')}, {fk('supplier', 'l_suppkey')} from lineitem"), FK_NODES),
    "user_kinds": (
        f"ev as (select {key('chr(117) || chr(58) || user_id::varchar')} as u, {key('chr(107) || chr(58) || event_type || chr(46) || json_extract_string(props, chr(36) || chr(46) || chr(107))')} as k from events)",
        FOLD.format("select u as src, k as dst from ev"),
        "select distinct u as id, 'user' as label from ev union select distinct k, 'kind' from ev",
    ),
    "turn_flow": (
        f"c as (select conv_id, turn, role, {key('role || chr(58) || text')} as s from conversations)",
        FOLD.format("select s as src, lead(s) over (partition by conv_id order by turn) as dst from c").replace("group by", "where dst is not null group by"),
        f"select distinct s as id, role as label from c where s in {ENDS}",
    ),
}
UNDIRECTED = ("vote_sim", "order_coitem", "part_copurchase")


def with_graph(name: str, body: str, more: str = "") -> str:
    """``body`` over the tables e(src, dst, m) and v(id, label) of a graph."""
    before, e, v = GRAPHS[name]
    parts = [x for x in (before, f"e as ({e})", f"v as ({v})", more) if x]
    return f"with {', '.join(parts)} {body}"
