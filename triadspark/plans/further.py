"""Registered queries on hash-free ranks of names, gaps in a series, look-ups, vectors and frames, with oracles on their own paths."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.codes import find_dir
from ..operators import blocks as B
from ..operators import census as C
from ..operators import graph as G
from ..operators import measures as M
from ..operators import temporal as T
from ..sources import workloads as W
from . import registry as base
from .extras import _universe
from .registry import _FOLD, _LABEL, ARCS, BEFORE, VERTICES, _daily, _head, _long, _series, _wedge, wedge_sql

QUERIES, SQL = {}, {}


def _add(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


# ---------------------------------------------------------------- graphs of names

for _u in ("set", "merge"):
    _add(f"census_edge_{_u}_web", lambda s, d, u=_u: _long(C.census_edge_driven(W.web_graph(s, d), union=u)), _wedge("web"))
_add("census_edge_pieces_web", lambda s, d: _long(C.census_edge_driven(W.web_graph(s, d), union="merge", piece=16)), _wedge("web"))
_add("census_matrix_social", lambda s, d: _long(C.census_matrix(W.social_graph(s, d))), _wedge("social"))
_ranked = _head("web") + f", v as ({VERTICES['web']}), rk as (select id, row_number() over (order by id) - 1 as r from v) "
_add("packed_adjacency_web", lambda s, d: G.packed_adjacency(W.web_graph(s, d)).select("id", "deg", F.array_join(F.transform("packed", lambda x: x.cast("string")), ",").alias("packed")),
     _ranked + "select x.r as id, count(*)::integer as deg, string_agg((y.r * 4 + code)::varchar, ',' order by y.r) as packed from s join rk x on x.id = s.id join rk y on y.id = s.nbr group by x.r")
_add("csr_web", lambda s, d: G.to_csr(W.web_graph(s, d))[0], _ranked + "select r as id, (sum(deg) over (order by r) - deg)::bigint as start, deg from (select x.r, count(*)::integer as deg from s join rk x on x.id = s.id group by x.r)")


def _named_transitive(s, d):
    g, names = W.named_graph(*W.web_arcs(s, d))
    return G.with_labels(C.list_triads(g, ["030T"]), names, ["u", "v", "w"]).select("u", "v", "w", "triad_type")


_add("list_transitive_web_named", _named_transitive, _head("web") + "select a.lo as u, a.hi as v, b.hi as w, '030T' as triad_type from d a join d b on b.lo = a.hi join d c on c.lo = a.lo and c.hi = b.hi where a.dir + 4 * c.dir + 16 * b.dir in (21, 22, 26, 37, 41, 42)")
_add("list_first_cycles_traffic", lambda s, d: C.list_triads(W.traffic_graph(s, d), ["030C"], limit=25), _head("traffic") + "select a.lo as u, a.hi as v, b.hi as w, '030C' as triad_type from d a join d b on b.lo = a.hi join d c on c.lo = a.lo and c.hi = b.hi where a.dir + 4 * c.dir + 16 * b.dir in (25, 38) order by 1, 2, 3 limit 25")


def _lookups(s, d):
    x = G.packed_adjacency(W.traffic_graph(s, d)).select("id", "packed", F.explode(F.sequence(F.lit(0), F.lit(9))).alias("nbr"))
    return x.select("id", F.col("nbr").cast("long").alias("nbr"), find_dir(F.col("packed"), F.col("nbr")).alias("code"))


_add("edge_lookup_traffic", _lookups, _head("traffic") + "select x.id, w.nbr, coalesce(s.code, 0)::integer as code from (select distinct id from s) x cross join (select unnest(range(10)) as nbr) w left join s on s.id = x.id and s.nbr = w.nbr")

# words: the closed form in SQL, since all wedges of this graph are too many for a check
_WORD_ARCS = r"""select src, dst from (select unnest(w[1:len(w) - 1]) as src, unnest(w[2:len(w)]) as dst from (select regexp_split_to_array(lower(text), '[^\p{L}]+') as w from documents where text is not null)) where src <> '' and dst <> ''"""
SQL["triad_census_words"] = f"""with a0 as ({_WORD_ARCS}), nm as (select id, row_number() over () as k from (select src as id from a0 union select dst from a0)),
d as (select least(p.k, q.k) as lo, greatest(p.k, q.k) as hi, bit_or(case when p.k < q.k then 1 else 2 end) as dir from (select distinct src, dst from a0 where src <> dst) a join nm p on p.id = a.src join nm q on q.id = a.dst group by 1, 2),
s as (select lo as id, hi as nbr, dir as code from d union all select hi, lo, case dir when 1 then 2 when 2 then 1 else 3 end from d),
g as (select id, count(*)::hugeint as d, count(*) filter (code = 1)::hugeint as a, count(*) filter (code = 2)::hugeint as b, count(*) filter (code = 3)::hugeint as m from s group by id),
o as (select s.id as t, s.nbr as h, s.code from s join g x on x.id = s.id join g y on y.id = s.nbr where (x.d, x.id) < (y.d, y.id)),
tr as (select no, count(*)::hugeint as c from (select p.code + 4 * q.code + 16 * d.dir as code from o p join o q on p.t = q.t and p.h < q.h join d on d.lo = p.h and d.hi = q.h) join (select * from {_FOLD}) using (code) group by no),
n as (select count(*)::hugeint as n from nm), k as (select coalesce(sum(c) filter (no = 9), 0) as t30t, coalesce(sum(c) filter (no = 10), 0) as t30c, coalesce(sum(c) filter (no = 12), 0) as t20d, coalesce(sum(c) filter (no = 13), 0) as t20u, coalesce(sum(c) filter (no = 14), 0) as t20c, coalesce(sum(c) filter (no = 15), 0) as t210, coalesce(sum(c) filter (no = 16), 0) as t300 from tr),
w as (select sum(a * (a - 1) // 2) as dd, sum(b * (b - 1) // 2) as uu, sum(a * b) as cc, sum(m * b) as mi, sum(m * a) as mo, sum(m * (m - 1) // 2) as mm, sum(d * (a + b)) as da, sum(d * m) as dm from g),
p as (select count(*) filter (dir < 3)::hugeint as pa, count(*) filter (dir = 3)::hugeint as pm from d),
e as (select unnest([2, 3, 4, 5, 6, 7, 8, 11, 9, 10, 12, 13, 14, 15, 16]) as no, unnest([n * pa - da + 3 * (t30t + t30c) + 2 * (t20d + t20u + t20c) + t210, n * pm - dm + t20d + t20u + t20c + 2 * t210 + 3 * t300, dd - t30t - t20d, uu - t30t - t20u,
  cc - t30t - 3 * t30c - t20c, mi - 2 * t20d - t20c - t210, mo - 2 * t20u - t20c - t210, mm - t210 - 3 * t300, t30t, t30c, t20d, t20u, t20c, t210, t300]) as c from n, k, w, p),
f as (select no, c from e union all select 1, (select n * (n - 1) * (n - 2) // 6 from n) - sum(c) from e)
select triad_type, no as triad_no, c::bigint as n_triads from f join (select * from {_LABEL}) using (no)"""

# ---------------------------------------------------------------- series with gaps, many small graphs, vectors

_GAP = ("2024-01-05", "2024-01-07")
_gap_arcs = lambda s, d: W.traffic_arcs(s, d).where((F.col("ts") < F.lit(_GAP[0]).cast("timestamp_ntz")) | (F.col("ts") >= F.lit(_GAP[1]).cast("timestamp_ntz")))
_GAP_ARCS = base._TRAFFIC_DAY + f" where ts < timestamp '{_GAP[0]}' or ts >= timestamp '{_GAP[1]}'"
_DAYS = "select unnest(generate_series((select min(win_start) from a), (select max(win_start) from a), interval 1 day)) as win_start"
_add("daily_census_gap", lambda s, d: _long(T.census_by_interval(_gap_arcs(s, d), n=_universe(s, d))), wedge_sql(_GAP_ARCS, VERTICES["traffic"], key="win_start", sizes=f"select win_start, (select count(*) from v) as n from ({_DAYS})"))
_add("daily_census_gap_active", lambda s, d: _long(T.census_by_interval(_gap_arcs(s, d))), wedge_sql(_GAP_ARCS, VERTICES["traffic"], key="win_start", sizes=f"select win_start, coalesce(c.n, 0) as n from ({_DAYS}) left join (select win_start, count(*) as n from (select win_start, src as id from a union select win_start, dst from a) group by 1) c using (win_start)"))


def _kernel_days(s, d):
    w = W.traffic_arcs(s, d).select(F.window("ts", "1 day").start.alias("win_start"), "src", "dst")
    return _long(B.small_graph_census(G.as_digraph(w, keys=["win_start"], sizes=w.select("win_start").distinct().crossJoin(F.broadcast(_universe(s, d)))), most=150))


_add("daily_census_kernel", _kernel_days, _series)
_add("merged_vectors_traffic", lambda s, d: C.census_merge(C.census_vector(_daily(s, d), ["win_start"])).select(F.array_join(F.transform("counts", lambda x: x.cast("string")), ",").alias("counts")),
     f"select string_agg(n::bigint::varchar, ',' order by triad_no) as counts from (select triad_no, sum(n_triads) as n from ({_series}) group by 1)")
_connected = lambda s, d: C.connected_counts(W.social_graph(s, d))
_add("private_vectors_sum_social", lambda s, d: C.accumulate(_connected(s, d), keep_slots=True).groupBy("triad_no").agg(F.sum("c").alias("c")), f"select triad_no, n_triads as c from ({_wedge('social')}) where triad_no > 3 and n_triads > 0")
_add("slot_contention_social", lambda s, d: M.slot_contention(_connected(s, d)))
_add("slot_rows_social", lambda s, d: M.slot_contention(_connected(s, d)).agg(F.sum("n_rows").alias("n_rows")), f"select sum(n_triads)::bigint as n_rows from ({_wedge('social')}) where triad_no > 3")

# ---------------------------------------------------------------- frames, ranks, quantiles, time ranges

_add("type_ranks_traffic", lambda s, d: (lambda w: _long(_daily(s, d)).select("win_start", "triad_type", F.rank().over(w.orderBy(F.desc("n_triads"))).alias("place"), F.ntile(4).over(w.orderBy(F.desc("n_triads"), "triad_no")).alias("quarter")))(Window.partitionBy("win_start")),
     f"select win_start, triad_type, rank() over (partition by win_start order by n_triads desc)::integer as place, ntile(4) over (partition by win_start order by n_triads desc, triad_no)::integer as quarter from ({_series})")
_add("trailing_arcs", lambda s, d: W.traffic_arcs(s, d).select("src", "ts", F.count("*").over(Window.partitionBy("src").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-6 * 3600 * 10**6, 0)).alias("n")),
     "select user_id as src, ts, count(*) over (partition by user_id order by ts range between interval 6 hours preceding and current row) as n from events where json_extract(props, '$.k')::bigint is not null")
_add("series_quantiles_traffic", lambda s, d: T.series_quantiles(_long(_daily(s, d))).select("triad_type", "q50", "q90", "busiest"),
     f"select triad_type, round(quantile_cont(n_triads::double, 0.5), 6) as q50, round(quantile_cont(n_triads::double, 0.9), 6) as q90, max_by(win_start, (n_triads, win_start)) as busiest from ({_series}) group by 1")
_add("loglog_fit_social", lambda s, d: M.degree_histogram(W.social_graph(s, d), "all").agg(F.round(F.regr_r2(F.ln("n_vertices"), F.ln("degree")), 6).alias("r2")), _head("social") + "select round(regr_r2(ln(n), ln(k)), 6) as r2 from (select k, count(*) as n from (select id, count(*) as k from s group by id) group by k)")
_add("census_wide_long", lambda s, d: T.census_long(T.census_wide(_long(_daily(s, d)))), f"select win_start, triad_type, n_triads from ({_series})")
_add("two_days_of_arcs", lambda s, d: W.by_event_type(W.between_times(W.traffic_arcs(s, d), "2024-01-03", "2024-01-05"), ["click", "view"]).groupBy("event_type").agg(F.count("*").alias("n")),
     "select event_type, count(*) as n from events where ts >= timestamp '2024-01-03' and ts < timestamp '2024-01-05' and event_type in ('click', 'view') and json_extract(props, '$.k')::bigint is not null group by 1")
