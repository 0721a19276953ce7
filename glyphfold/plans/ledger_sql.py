"""DuckDB twins of the ledger: SQL that prices any partition of a graph, stars and loose bundles included.

Written from the definitions, not from the Spark plans: it starts from the tables e(src,
dst, m) and v(id, label) of a graph and a partition mem(id, sid).
"""

from __future__ import annotations

LOG2C = "((lgamma({n} + 1) - lgamma({k} + 1) - lgamma({n} - {k} + 1)) / ln(2))"
INT = "(case when {k} = 0 then 3.0 else 2 * log2({k}) + 1 end)"


def log2c(n: str, k: str) -> str:
    return LOG2C.format(n=f"({n})", k=f"({k})")


def int_sql(k: str) -> str:
    return INT.format(k=f"({k})")


def entropy(n: str, k: str) -> str:
    part = "(case when {x} > 0 then -{x} * log2({x} / ({n})::double) else 0.0 end)"
    return f"({part.format(x=f'({k})', n=n)} + {part.format(x=f'(({n}) - ({k}))', n=n)})"


def chan(n: str, k: str, code: str = "binomial") -> str:
    which = log2c(n, k) if code == "binomial" else entropy(n, k)
    return f"(case when ({n}) <= 0 then 0.0 else {int_sql(k)} + {which} end)"


def diff_sql(a: str, b: str) -> str:
    return f"(case when {a} = {b} then 1.0 else 2 * log2(abs({a} - {b})) + 3 end)"


def rep_ctes(name: str, rows: str, keys: str) -> str:
    """``name``: the cheapest representative of each bag of multiplicities, and the bits of the bag against it."""
    x, t = ", ".join(f"h.{k}" for k in keys.split(", ")), " and ".join(f"t.{k} = h.{k}" for k in keys.split(", "))
    return f"""{name}_h as (select {keys}, m as x, count(*) as c from {rows} group by all),
  {name}_t as (select distinct {keys}, x + d as rep from {name}_h, (select unnest([-1, 0, 1]) as d) where x + d >= 1),
  {name}_c as (select {x}, t.rep, round(sum(c * {diff_sql('x', 't.rep')}), 6) as bits from {name}_t t join {name}_h h on {t} group by all),
  {name} as (select {keys}, arg_min(rep, (bits, rep)) as rep, min(bits) as bits from {name}_c group by {keys})"""


def partition_ctes(mem: str, directed: bool = True, keep: str = "rule", code: str = "binomial") -> str:
    """Common table expressions from ``mem`` to the bundles; keep: which super-edges there are (rule, all)."""
    if directed:
        ends = "select sid, dst as x, 1 as way from inn union all select sid, src, 2 from inn"
        glyph = "case when n = 1 then 'disconnected' when 2 * e >= n * (n - 1) then 'clique' when cost_in < e and cost_in <= cost_out then 'in_star' when cost_out < e then 'out_star' else 'disconnected' end"
        spoke = "(glyph = 'in_star' and dst = hub) or (glyph = 'out_star' and src = hub)"
        pairs = "n * (n - 1)"
        flip = "select x.sid as a, y.sid as b, src, dst, m"
    else:
        ends = "select sid, dst as x, 1 as way from inn union all select sid, src, 1 from inn"
        glyph = "case when n = 1 then 'disconnected' when 4 * e >= n * (n - 1) then 'clique' when cost_in < e then 'out_star' else 'disconnected' end"
        spoke = "glyph = 'out_star' and (dst = hub or src = hub)"
        pairs = "(n * (n - 1) / 2)::bigint"
        flip = "select least(x.sid, y.sid) as a, greatest(x.sid, y.sid) as b, case when x.sid < y.sid then src else dst end as src, case when x.sid < y.sid then dst else src end as dst, m"
    star = "glyph in ('in_star', 'out_star')"
    chan_ = lambda n, k: chan(n, k, code)
    with_ = f"{int_sql('rep')} + {chan_('cover', 'cover - hit')} + {chan_('total - cover', 'k - hit')} + covered + plain - plain_hit"
    without = f"{chan_('total', 'k')} + plain"
    verdict = {"rule": f"hit > 0 and {with_} < {without}", "all": "hit > 0"}[keep]
    return f"""mem as ({mem}), size as (select sid, count(*) as n, min(label) as label from mem join v using (id) group by sid),
  both_ends as ({flip} from e join mem x on x.id = e.src join mem y on y.id = e.dst),
  inn as (select a as sid, src, dst, m from both_ends where a = b and src <> dst), lps as (select a as sid, m from both_ends where a = b and src = dst),
  deg as (select sid, way, x, count(*) as d from ({ends}) group by all),
  hubs as (select sid, max(d) filter (way = 1) as d_in, max(d) filter (way = 2) as d_out, arg_min(x, (-d, x)) filter (way = 1) as h_in, arg_min(x, (-d, x)) filter (way = 2) as h_out from deg group by sid),
  costs as (select s.sid, s.n, coalesce(i.e, 0) as e, coalesce(d_in, 0) as d_in, coalesce(d_out, 0) as d_out, n - 1 + coalesce(i.e, 0) - 2 * coalesce(d_in, 0) as cost_in, n - 1 + coalesce(i.e, 0) - 2 * coalesce(d_out, 0) as cost_out, h_in, h_out
    from size s left join (select sid, count(*) as e from inn group by sid) i using (sid) left join hubs using (sid)),
  glyphs as (select *, {glyph} as glyph, case when ({glyph}) = 'in_star' then h_in when ({glyph}) = 'out_star' then {'h_out' if directed else 'h_in'} end as hub, {pairs} as pairs from costs),
  marked as (select i.*, glyph = 'clique' or {spoke} as hit from inn i join glyphs using (sid)),
  {rep_ctes('grep', '(select * from marked where hit)', 'sid')}, {rep_ctes('lrep', 'lps', 'sid')},
  links as (select o.*, (p.glyph not in ('in_star', 'out_star') or src = p.hub) and (q.glyph not in ('in_star', 'out_star') or dst = q.hub) as hit, p.n * q.n as total,
    (case when p.{star} then 1 else p.n end) * (case when q.{star} then 1 else q.n end) as cover from both_ends o join glyphs p on p.sid = a join glyphs q on q.sid = b where a <> b),
  {rep_ctes('brep', '(select * from links where hit)', 'a, b')},
  bundles as (select a, b, any_value(total) as total, any_value(cover) as cover, count(*) as k, count(*) filter (hit) as hit, any_value(rep) as rep, coalesce(any_value(bits), 0) as covered,
    sum({int_sql('m')}) as plain, coalesce(sum({int_sql('m')}) filter (hit), 0) as plain_hit from links left join brep using (a, b) group by a, b),
  judged as (select *, coalesce(total = 1 or ({verdict}), false) as keep from bundles),
  se as (select a as sid, b as other, rep from judged where keep union all select sid, sid, rep from lrep),
  outs as (select sid, count(*) as d, sum({int_sql('rep')}) as bits from se group by sid),
  loose as (select a as sid, count(*) as d from judged where not keep group by a),
  vs as (select count(*)::double as vs, sum(n)::double as nv, count(distinct label)::double as nt from size),
  inside as (select g.*, coalesce(h.hits, 0) as hits, coalesce(h.rest, 0) as rest, coalesce(l.k, 0) as k, case when glyph = 'clique' then pairs when {star} then n - 1 else 0 end as cover
    from glyphs g left join (select sid, count(*) filter (hit) as hits, count(*) filter (not hit) as rest from marked group by sid) h using (sid) left join (select sid, count(*) as k from lps group by sid) l using (sid)),
  parts as (
    select 'model' as part, (select {int_sql('vs')} + {int_sql('nt')} from vs) + sum(log2(nt) + 2 + {int_sql('n')} + {int_sql('coalesce(grep.rep, 1)')} + log2(vs) + {log2c('vs', 'coalesce(outs.d, 0)')} + coalesce(outs.bits, 0)) as bits from glyphs cross join vs left join grep using (sid) left join outs using (sid)
    union all select 'mapping', sum({log2c('nv', 'n')} + case when {star} then log2(n) else 0 end) from glyphs cross join vs
    union all select 'glyph_topology', sum(case when n = 1 then 0 else (case when cover > 0 then {chan_('cover', 'cover - hits')} else 0 end) + {chan_('pairs + (case when k > 0 then 0 else n end) - cover', 'rest')} end) from inside
    union all select 'loop_topology', coalesce(sum(case when n = 1 or k = 0 then 0 else {chan_('n', 'n - k')} end), 0) from inside
    union all select 'superedge_topology', coalesce(sum(case when total = 1 then 0 else {chan_('cover', 'cover - hit')} + {chan_('total - cover', 'k - hit')} end), 0) from judged where keep
    union all select 'loose_topology', coalesce(sum({chan_('total', 'k')}), 0) from judged where not keep
    union all select 'multiplicity', (select coalesce(sum(bits), 0) from grep) + (select coalesce(sum(bits), 0) from lrep) + (select coalesce(sum({int_sql('m')}), 0) from marked where not hit)
      + (select coalesce(sum(case when keep then covered + plain - plain_hit else plain end), 0) from judged)
    union all select 'location', sum(log2(vs) + {log2c('vs', 'coalesce(loose.d, 0)')}) from size cross join vs left join loose using (sid))"""


#: Partitions: each label, equal neighbour lists of one label, and stars of the key graph.
BY_LABEL = "select id, min(id) over (partition by label) as sid from v"
TOKENS = {
    True: "select src as id, dst * 2 + 1 as t from e union all select dst, src * 2 from e",
    False: "select src as id, dst * 2 as t from e union select dst, src * 2 from e",
}


def by_duplicates(directed: bool = True) -> str:
    lists = f"select id, string_agg(t::varchar, ',' order by t) as k from ({TOKENS[directed]}) group by id"
    return f"select id, min(id) over (partition by label, coalesce(k, 'alone ' || id)) as sid from v left join ({lists}) using (id)"


def draw_sql(x: str, seed: int = 42) -> str:
    """A repeatable draw per node (the hash of ``synth.node_draw``)."""
    return f"((({x}) % 2147483647 * 48271 + {seed} * 69621) % 2147483647 * 40692 % 2147483647)"


def by_random(directed: bool = True) -> str:
    """The sizes of ``by_duplicates``, filled at random within each label."""
    return f"""select x.id, min(x.id) over (partition by y.sid) as sid from (select id, row_number() over (order by label, {draw_sql('id')}, id) as r from v) x
    join (select d.sid, row_number() over (order by label, d.sid, id) as r from ({by_duplicates(directed)}) d join v using (id)) y using (r)"""


#: Orders (code 3) join their customer; the others stay alone.
BY_STAR = "select id, coalesce(c, id) as sid from v left join (select dst as id, min(src) as c from e where dst % 8 = 3 group by dst) using (id)"
PARTITIONS = {"label": lambda d: BY_LABEL, "duplicates": by_duplicates, "random": by_random, "stars": lambda d: BY_STAR}
LEDGER = "select part, case when part = 'location' then 'sound' else 'printed' end as ledger, round(bits::double, 3) as bits from parts"
#: Bits of the graph as its own summary, printed ledger.
IDENTITY = f"""(select {int_sql('n.vs')} + {int_sql('n.t')} + n.vs * (log2(n.t) + 2 + 1 + 1 + log2(n.vs)) + o.s + me.s + n.vs * log2(n.vs) + me.n
  from (select count(*)::double as vs, count(distinct label)::double as t from v) n,
    (select sum({log2c('(select count(*) from v)', 'd')}) as s from (select id, count(src) as d from v left join e on id = src group by id)) o,
    (select coalesce(sum({int_sql('m')}), 0) as s, count(*) as n from e) me)"""


def expansion_sql(directed: bool = True) -> str:
    """The approximate graph ``approx(src, dst, m)`` that a priced partition stands for."""
    order = "{a} as src, {b} as dst" if directed else "least({a}, {b}) as src, greatest({a}, {b}) as dst"
    spoke = order.format(a="case when glyph = 'in_star' then id else hub end", b="case when glyph = 'in_star' then hub else id end")
    return f"""ports as (select sid, hub as id from glyphs where glyph in ('in_star', 'out_star') union all select sid, id from mem join glyphs using (sid) where glyph in ('clique', 'disconnected')),
  approx as (select i.id as src, j.id as dst, coalesce(rep, 1)::bigint as m from mem i join mem j using (sid) join glyphs using (sid) left join grep using (sid) where glyph = 'clique' and i.id {'<>' if directed else '<'} j.id
    union all select {spoke}, coalesce(rep, 1)::bigint from mem join glyphs using (sid) left join grep using (sid) where glyph in ('in_star', 'out_star') and id <> hub
    union all select id, id, rep::bigint from mem join lrep using (sid)
    union all select {order.format(a='p.id', b='q.id')}, rep::bigint from se join ports p on p.sid = se.sid join ports q on q.sid = other where se.sid <> other)"""


CORRECTIONS = """select case when x.m is null then 'add' when e.m is null then 'drop' else 'retune' end as kind, coalesce(e.src, x.src) as src, coalesce(e.dst, x.dst) as dst, coalesce(e.m, 0) as m, coalesce(e.m - x.m, 0) as delta
  from e full join approx x on e.src = x.src and e.dst = x.dst where e.m is distinct from x.m"""
