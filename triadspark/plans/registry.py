"""Registered census queries and their oracle SQL, derived another way: wedges by centre or all triples, never the closed form."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codes import FOLD, LABELS, TYPES, type_table  # noqa: F401
from ..operators import census as C
from ..operators import graph as G
from ..operators import measures as M
from ..operators import temporal as T
from ..sources import workloads as W

# ---------------------------------------------------------------- SQL

ARCS = {
    "citation": "select o_orderkey as src, lag(o_orderkey) over (partition by l_partkey order by o_orderdate, o_orderkey) as dst from (select distinct l_orderkey, l_partkey from lineitem) join orders on l_orderkey = o_orderkey",
    "social": "select o_custkey as src, lead(o_custkey) over (partition by l_partkey order by o_orderdate, l_orderkey, l_linenumber) as dst from lineitem join orders on l_orderkey = o_orderkey",
    "traffic": "select user_id as src, json_extract(props, '$.k')::bigint as dst from events",
    "day1": "select user_id as src, json_extract(props, '$.k')::bigint as dst from events where ts::date = date '2024-01-01'",
    "trade": "select case when l_returnflag = 'R' then 2 * l_suppkey + 1 else 2 * o_custkey end as src, case when l_returnflag = 'R' then 2 * o_custkey else 2 * l_suppkey + 1 end as dst from lineitem join orders on l_orderkey = o_orderkey",
    "nation": """select f.i as src, f.j as dst from flow f left join flow r on r.i = f.j and r.j = f.i where f.i <> f.j and f.q > 0 and f.q >= coalesce(r.q, 0)""",
    "web": """select src, dst from (select 'p' || page_id as src, unnest(l) as dst from links union all select unnest(l[1:len(l) - 1]), unnest(l[2:len(l)]) from links)""",
}
BEFORE = {
    "nation": "flow as (select s_nationkey as i, c_nationkey as j, sum(l_quantity)::bigint as q from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey group by 1, 2), ",
    "web": """links as (select page_id, regexp_extract_all(html, 'href="([^"]*)"', 1) as l from pages), """,
}
VERTICES = {
    "citation": "select o_orderkey as id from orders", "social": "select c_custkey as id from customer", "trade": "select 2 * c_custkey as id from customer union select 2 * s_suppkey + 1 from supplier", "nation": "select n_nationkey as id from nation",
    "traffic": "select user_id as id from events union select json_extract(props, '$.k')::bigint from events", "day1": "select user_id as id from events union select json_extract(props, '$.k')::bigint from events",
    "web": "select src as id from a0 union select dst from a0 union select 'p' || page_id from pages",
}
_FOLD = "(values " + ", ".join(f"({c}, {FOLD[c]})" for c in range(64)) + ") as fold(code, no)"
_LABEL = "(values " + ", ".join(f"({i + 1}, '{x}')" for i, x in enumerate(LABELS)) + ") as lab(no, triad_type)"


def wedge_sql(arcs: str, vertices: str, before: str = "", key: str = "", fixed_n: bool = True, sizes: str = "") -> str:
    """Census by all wedges; key: a further column of arcs that every step is grouped by; sizes: SQL of (key, n)."""
    k, ks, on = (f"{key}, ", f"s.{key}, ", f" and s.{key} = r.{key}") if key else ("", "", "")
    ond = f" and d.{key} = s.{key}" if key else ""
    using = f"using ({key})" if key else "on true"
    n = f"nn as (select {key}, count(*) as n from (select {key}, src as id from a where true union select {key}, dst from a) group by 1)" if key and not fixed_n else (f"nn as (select {key}, (select count(*) from v) as n from (select distinct {key} from a0))" if key else "nn as (select count(*) as n from v)")
    n = f"nn as ({sizes})" if sizes else n
    tail = f"""cells as (select {k}no, sum(c) as c from (select {k}no, count(*) as c from codes join fold using (code) group by {k}no union all select {k}no, sum(c) from dy group by {k}no) group by {k}no),
full_ as (select {k}nn.n, lab.no, lab.triad_type from nn, lab),
r16 as (select {('full_.' + key + ', ') if key else ''}full_.n, full_.no, triad_type, coalesce(c, 0) as c from full_ left join cells on cells.no = full_.no{f' and cells.{key} = full_.{key}' if key else ''})
select {k}triad_type, no as triad_no, (case when no = 1 then n::hugeint * (n - 1) * (n - 2) // 6 - (sum(c) over ({'partition by ' + key if key else ''}))::hugeint else c end)::bigint as n_triads from r16"""
    return f"""with {before}a0 as ({arcs}), v as ({vertices}), a as (select * from a0 where dst is not null), {n},
fold as (select * from {_FOLD}), lab as (select * from {_LABEL}),
d as (select {k}least(src, dst) as lo, greatest(src, dst) as hi, bit_or(case when src < dst then 1 else 2 end) as dir from a where src <> dst group by {k}lo, hi),
s as (select {k}lo as id, hi as nbr, dir as code from d union all select {k}hi, lo, case dir when 1 then 2 when 2 then 1 else 3 end from d),
w as (select {ks}s.id as k, s.nbr as i, r.nbr as j, s.code as ci, r.code as cj from s join s r on s.id = r.id and s.nbr < r.nbr{on}),
x as (select w.*, coalesce(d.dir, 0) as cij from w left join d on d.lo = w.i and d.hi = w.j{f' and d.{key} = w.{key}' if key else ''}),
f as (select *, case ci when 1 then 2 when 2 then 1 else 3 end as fi, case cj when 1 then 2 when 2 then 1 else 3 end as fj from x),
codes as (select {k}case when k < i then ci + 4 * cj + 16 * cij when k < j then fi + 4 * cij + 16 * cj else cij + 4 * fi + 16 * fj end as code from f where cij = 0 or k < i),
cm as (select {k}i as lo, j as hi, count(*) as common from x where cij > 0 group by {k}lo, hi),
dg as (select {k}id, count(*) as dd from s group by {k}id),
dy as (select {'d.' + key + ', ' if key else ''}case when d.dir = 3 then 3 else 2 end as no, nn.n - a1.dd - a2.dd + coalesce(common, 0) as c from d join dg a1 on a1.id = d.lo{f' and a1.{key} = d.{key}' if key else ''} join dg a2 on a2.id = d.hi{f' and a2.{key} = d.{key}' if key else ''}
  left join cm on cm.lo = d.lo and cm.hi = d.hi{f' and cm.{key} = d.{key}' if key else ''} join nn {f'on nn.{key} = d.{key}' if key else 'on true'}),
{tail}"""


def triple_sql(name: str, states: bool = False) -> str:
    """Census of a small graph by all triples, no algebra."""
    head = f"""with {BEFORE.get(name, '')}a0 as ({ARCS[name]}), v as ({VERTICES[name]}),
d as (select least(src, dst) as lo, greatest(src, dst) as hi, bit_or(case when src < dst then 1 else 2 end) as dir from a0 where dst is not null and src <> dst group by 1, 2),
t as (select coalesce(p.dir, 0) + 4 * coalesce(q.dir, 0) + 16 * coalesce(r.dir, 0) as code from v a join v b on a.id < b.id join v c on b.id < c.id
  left join d p on p.lo = a.id and p.hi = b.id left join d q on q.lo = a.id and q.hi = c.id left join d r on r.lo = b.id and r.hi = c.id),
g as (select code, count(*) as c from t group by 1), fold as (select * from {_FOLD}), lab as (select * from {_LABEL})
"""
    if states:
        return head + "select fold.code::integer as code, coalesce(c, 0)::bigint as n_triads from fold left join g using (code)"
    return head + "select triad_type, lab.no as triad_no, coalesce(sum(c), 0)::bigint as n_triads from lab left join fold using (no) left join g using (code) group by 1, 2"


def _wedge(name: str) -> str:
    return wedge_sql(ARCS[name], VERTICES[name], BEFORE.get(name, ""))


# ---------------------------------------------------------------- queries

GRAPHS = {"citation": W.citation_graph, "social": W.social_graph, "web": W.web_graph, "trade": W.trade_graph, "traffic": W.traffic_graph, "nation": W.nation_graph, "day1": lambda s, d: W.traffic_graph(s, d, "2024-01-01")}


def _long(df: DataFrame) -> DataFrame:
    return df.withColumn("n_triads", F.col("n_triads").cast("long"))


def _exact(g, method=C.census) -> DataFrame:
    """A graph's census with 64-bit counts, or with DECIMAL(38,0) ones if all its triads are more than 64 bits hold (3.8 million vertices)."""
    n = g.sizes.agg(F.max("n").alias("n")).first().n or 0  # one row
    return _long(method(g)) if n * (n - 1) * (n - 2) // 6 < 1 << 63 else method(g)


def _daily(s, d):
    n = W.traffic_vertices(s, d).agg(F.count("*").alias("n"))
    return T.census_by_interval(W.traffic_arcs(s, d), n=n)


QUERIES, SQL = {}, {}


def _add(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


for _n in ("citation", "social", "web", "trade", "traffic"):
    _add(f"triad_census_{_n}", lambda s, d, b=GRAPHS[_n]: _exact(b(s, d), C.census_scalable), _wedge(_n))
_add("triad_census_nation", lambda s, d: _long(C.census(W.nation_graph(s, d))), triple_sql("nation"))
_add("triad_census_traffic_day1", lambda s, d: _long(C.census(GRAPHS["day1"](s, d))), triple_sql("day1"))
_add("triad_census_words", lambda s, d: _exact(W.word_graph(s, d)))
_add("census_naive_nation", lambda s, d: _long(C.census_naive(W.nation_graph(s, d))), triple_sql("nation"))
_add("census_matrix_traffic", lambda s, d: _long(C.census_matrix(W.traffic_graph(s, d))), _wedge("traffic"))
for _u in ("set", "merge", "join"):
    _add(f"census_edge_{_u}_traffic", lambda s, d, u=_u: _long(C.census_edge_driven(W.traffic_graph(s, d), union=u)), _wedge("traffic"))
_add("census_edge_join_social", lambda s, d: _long(C.census_edge_driven(W.social_graph(s, d), union="join")), _wedge("social"))
_add("census_edge_outer_traffic", lambda s, d: _long(C.census_edge_driven(W.traffic_graph(s, d), union="merge", balance="outer", slots=1)), _wedge("traffic"))
for _n in ("nation", "day1"):
    _add(f"census64_{_n}", lambda s, d, b=GRAPHS[_n]: _long(C.census64(b(s, d))), triple_sql(_n, states=True))
_add("census64_folded_social", lambda s, d: _long(C.condense(C.census64(W.social_graph(s, d)))), _wedge("social"))
_D = "d as (select least(src, dst) as lo, greatest(src, dst) as hi, bit_or(case when src < dst then 1 else 2 end)::integer as dir from a0 where dst is not null and src <> dst group by 1, 2)"
_S = "s as (select lo as id, hi as nbr, dir as code from d union all select hi, lo, case dir when 1 then 2 when 2 then 1 else 3 end from d)"
_head = lambda n: f"with {BEFORE.get(n, '')}a0 as ({ARCS[n]}), {_D}, {_S} "
_add("dyads_traffic", lambda s, d: W.traffic_graph(s, d).dyads, _head("traffic") + "select lo, hi, dir from d")
_add("dyad_census_social", lambda s, d: M.dyad_census(W.social_graph(s, d)), _head("social") + "select count(*) filter (dir = 3) as mutual, count(*) filter (dir < 3) as asym, (select count(*) * (count(*) - 1) // 2 from customer)::bigint - count(*) as nulls from d")
_add("packed_adjacency_nation", lambda s, d: G.packed_adjacency(W.nation_graph(s, d)).select("id", "deg", F.array_join(F.transform("packed", lambda x: x.cast("string")), ",").alias("packed")),
     _head("nation") + "select id::bigint as id, count(*)::integer as deg, string_agg((nbr * 4 + code)::varchar, ',' order by nbr) as packed from s group by id")
_add("csr_nation", lambda s, d: G.to_csr(W.nation_graph(s, d))[0], _head("nation") + "select id::bigint as id, (sum(deg) over (order by id) - deg)::bigint as start, deg from (select id, count(*)::integer as deg from s group by id)")
_add("isolated_orders", lambda s, d: G.isolated(W.citation_graph(s, d)), _head("citation") + "select o_orderkey as id from orders where o_orderkey not in (select id from s)")
for _n in ("citation", "social", "traffic"):
    _h = _head(_n) + ", h as (select degree, count(*) as n_vertices from (select id, count(*) filter (code in (1, 3)) as degree from s group by id) group by degree) "
    _add(f"outdegree_hist_{_n}", lambda s, d, b=GRAPHS[_n]: M.degree_histogram(b(s, d)), _h + "select degree, n_vertices from h")
    _add(f"powerlaw_{_n}", lambda s, d, b=GRAPHS[_n]: M.power_law_exponent(M.degree_histogram(b(s, d))), _h + "select round(-regr_slope(ln(n_vertices), ln(degree)), 6) as loglog, round(1 + sum(n_vertices) / sum(n_vertices * ln(degree / 0.5)), 6) as mle from h where degree >= 1")
_add("powerlaw_web", lambda s, d: M.power_law_exponent(M.degree_histogram(W.web_graph(s, d))))
_add("top_hubs_social", lambda s, d: M.top_hubs(W.social_graph(s, d)), _head("social") + "select id, count(*) as d from s group by id order by d desc, id limit 10")
_add("cost_model_social", lambda s, d: C.cost_model(W.social_graph(s, d)))
for _u in ("pair", "outer"):
    _g = "select lo, hi, x.c + y.c as w from d join dg x on x.id = lo join dg y on y.id = hi"
    _g = _g if _u == "pair" else f"select lo, sum(w) as w from ({_g}) group by lo"
    _add(f"work_by_{_u}_social", lambda s, d, u=_u: M.work_per_unit(W.social_graph(s, d), u), _head("social") + f", dg as (select id, count(*) as c from s group by id) select count(*) as units, sum(w)::bigint as total, max(w)::bigint as top, round(max(w) / avg(w), 6) as mean_ratio from ({_g})")
_add("slot_uniformity_social", lambda s, d: M.slot_uniformity(W.social_graph(s, d)))
_add("properties_social", lambda s, d: M.census_properties(C.census(W.social_graph(s, d))))
_add("local_clustering_social", lambda s, d: (lambda g: M.local_clustering(g, C.triangles(g)))(W.social_graph(s, d)),
     _head("social") + ", t as (select a.id, count(*) as c from s a join s b on a.id = b.id and a.nbr < b.nbr join d on d.lo = a.nbr and d.hi = b.nbr group by a.id) select s.id, count(*) as d, coalesce(any_value(t.c), 0) as closed, case when count(*) > 1 then round(2 * coalesce(any_value(t.c), 0) / (count(*) * (count(*) - 1)), 6) else 0.0 end as clustering from s left join t on t.id = s.id group by s.id")
_add("list_cycles_nation", lambda s, d: C.list_triads(W.nation_graph(s, d), ["030C"]), _head("nation") + "select a.lo::bigint as u, a.hi::bigint as v, b.hi::bigint as w, '030C' as triad_type from d a join d b on b.lo = a.hi join d c on c.lo = a.lo and c.hi = b.hi where a.dir + 4 * c.dir + 16 * b.dir in (25, 38)")
_TRAFFIC_DAY = "select date_trunc('day', ts)::timestamp as win_start, user_id as src, json_extract(props, '$.k')::bigint as dst from events"
_series = wedge_sql(_TRAFFIC_DAY, VERTICES["traffic"], key="win_start")
_add("daily_census_traffic", lambda s, d: _long(_daily(s, d)), _series)
_shares = f"sh as (select *, (sum(case when triad_no > 1 then n_triads else 0 end) over (partition by win_start))::double as total from ({_series})), s2 as (select *, case when total > 0 then round((case when triad_no > 1 then n_triads else 0 end) / total, 9) else 0.0 end as share from sh)"
_add("daily_shares_traffic", lambda s, d: T.census_shares(_long(_daily(s, d))), f"with {_shares} select * from s2")
_add("daily_drift_traffic", lambda s, d: T.census_drift(T.census_shares(_long(_daily(s, d)))).select("win_start", "triad_type", "share", "change", "history", "z"))
_add("pattern_scores_traffic", lambda s, d: T.pattern_scores(T.census_drift(T.census_shares(_long(_daily(s, d))))).select("win_start", "pattern", "score", "history"))
_add("alerts_traffic", lambda s, d: T.alerts(T.pattern_scores(T.census_drift(T.census_shares(_long(_daily(s, d)))), combine="any")))
_add("census_by_event_type", lambda s, d: _long(T.census_by_slice(W.traffic_arcs(s, d), "event_type")), wedge_sql("select event_type, user_id as src, json_extract(props, '$.k')::bigint as dst from events", VERTICES["traffic"], key="event_type", fixed_n=False))
_add("type_table", lambda s, d: type_table(s).select("code", "triad_no", "triad_type").join(_long(C.census64(GRAPHS["day1"](s, d))), "code"),
     f"select code, no as triad_no, triad_type, n_triads from ({triple_sql('day1', states=True)}) join (select * from {_FOLD}) using (code) join (select * from {_LABEL}) using (no)")
