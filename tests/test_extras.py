"""Kernels against brute force, roles, layouts, stores, stream, and the oracles of the further queries."""

import json
import math
import random

import pytest
from conftest import rows
from test_census import brute, fold, got16, graph

from triadspark.operators import blocks as B
from triadspark.operators import census as C
from triadspark.operators import layout as L
from triadspark.operators import measures as M
from triadspark.operators import participation as P
from triadspark.operators import relations as R
from triadspark.operators.graph import as_digraph
from triadspark.plans import extras as X
from triadspark.plans import registry as base
from triadspark.sources import store as S
from triadspark.streaming import monitor as live


@pytest.fixture(scope="module")
def mixed(spark):
    r = random.Random(9)
    arcs = [(a, b) for a in range(14) for b in range(14) if r.random() < 0.3]
    return graph(spark, 14, arcs), brute(14, arcs)


def test_kernels_agree_with_brute_force(mixed):
    g, want = mixed
    for f in (lambda: B.census_matrix_blocks(g, 4), lambda: B.census_matrix_blocks(g, 64), lambda: B.census_colour_blocks(g, 1), lambda: B.census_colour_blocks(g, 5), lambda: C.census_edge_driven(g, "merge", balance="weighted"), lambda: B.census_sampled(g, 1.0)):
        assert got16(f()) == fold(want)


def test_kernels_on_graphs_without_arcs(spark):
    g = graph(spark, 4, [])
    for f in (B.census_matrix_blocks, B.census_colour_blocks, lambda g: C.census_edge_driven(g, "merge", balance="weighted")):
        assert got16(f(g)) == [4] + [0] * 15


def test_roles_sum_to_the_census(mixed):
    g, want = mixed
    by = {}
    for r in P.triad_participation(g).collect():
        by[r.triad_type, r.role] = by.get((r.triad_type, r.role), 0) + r.n
    census = dict(zip(C.LABELS, fold(want), strict=True))
    for t in C.LABELS[3:]:
        if t in C.CLOSED:
            assert by.get((t, "corner"), 0) == 3 * census[t]
        else:
            assert (by.get((t, "centre"), 0), by.get((t, "end"), 0)) == (census[t], 2 * census[t])


def test_sampling_is_near(spark):
    r = random.Random(3)
    arcs = [(a, b) for a in range(60) for b in range(60) if a != b and r.random() < 0.3]
    g = graph(spark, 60, arcs)
    exact, near = got16(C.census(g)), got16(B.census_sampled(g, 0.7))
    assert sum(near) == sum(exact)
    assert abs(near[8] - exact[8]) < 0.25 * exact[8]


def test_running_totals_and_chunks(spark):
    r = random.Random(1)
    vals = [(k, r.randint(0, 9)) for k in r.sample(range(10**6), 300)]
    got = {x.k: x.before_v for x in L.running_totals(spark.createDataFrame(vals, "k long, v long"), "k", ["v"]).collect()}
    at = 0
    for k, v in sorted(vals):
        assert got[k] == at
        at += v
    cuts = L.guided_cuts(1000, 4, 16)
    assert cuts[0] == 0 and cuts[1] == math.ceil(1000 / 8) and all(b - a >= 16 for a, b in zip(cuts, cuts[1:], strict=False))


def test_weighted_units_are_even(spark):
    pairs = spark.range(1000).selectExpr("id % 37 as lo", "id as hi", "id % 11 + 1 as c")
    from pyspark.sql import functions as F

    got = [r.w for r in L.weighted_units(pairs, 8, ["lo"], "hi", F.col("c")).groupBy("unit").agg(F.sum("c").alias("w")).collect()]
    assert len(got) == 8 and max(got) - min(got) <= 22


def test_ranges_as_of_and_changes(spark):
    a = spark.sql("select * from values (1L, 2L, timestamp_ntz'2024-01-01 10:00:00'), (1L, 3L, timestamp_ntz'2024-01-05 00:00:00') as t(src, dst, ts)")
    spans = spark.sql("select * from values ('p', timestamp_ntz'2024-01-01 00:00:00', timestamp_ntz'2024-01-05 00:00:00'), ('q', timestamp_ntz'2024-01-01 10:00:00', timestamp_ntz'2024-01-09 00:00:00') as t(span, start, end)")
    assert sorted((r.span, r.dst) for r in R.assign_intervals(a, spans).collect()) == [("p", 2), ("q", 2), ("q", 3)]
    left = spark.createDataFrame([(1, 5), (1, 9), (2, 5)], "k int, at int")
    right = spark.createDataFrame([(1, 5, "x"), (1, 7, "y"), (2, 6, "z")], "k int, at int, v string")
    assert sorted(((r.k, r.at), r.v) for r in R.latest_before(left, right, "k", "at", "v").collect()) == [((1, 5), None), ((1, 9), "y"), ((2, 5), None)]


def test_graph_store_and_source(spark, mixed, tmp_path):
    g, want = mixed
    S.save_graph(g, str(tmp_path / "g"), 3)
    assert got16(C.census(S.open_graph(spark, str(tmp_path / "g")))) == fold(want)
    S.register_sources(spark)
    read = lambda: sorted(map(tuple, spark.read.format("digraph").options(n=50, m=101, seed=3, parts=4).load().collect()))
    x = read()
    assert len(x) == 101 and x == read() and all(0 <= a < 50 and 0 <= b < 50 for a, b in x)


def test_generated_exponent(spark, sf):
    law = X.generated_law(spark, sf)
    assert law.inputFiles() and abs(law.collect()[0].mle - 2.5) < 0.15


def test_type_table_reads_a_table(spark, sf):
    assert base.QUERIES["type_table"](spark, sf).inputFiles()


def test_counts_beyond_64_bits(spark, monkeypatch):
    arcs = spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long")
    for n in (5, 9_000_000):
        got = base._exact(as_digraph(arcs, spark.range(5), sizes=spark.range(1).selectExpr(f"{n}L as n")), C.census_scalable)
        assert sum(int(r.n_triads) for r in got.collect()) == n * (n - 1) * (n - 2) // 6 and dict(got.dtypes)["n_triads"] == ("bigint" if n == 5 else "decimal(38,0)")
    monkeypatch.setattr(X.W, "load", lambda s, d, name: s.range(4_000_000))
    assert {int(r.n_triads) for r in X.QUERIES["triad_total_all"](spark, "").collect()} == {4_000_000 * 3_999_999 * 3_999_998 // 6}


def test_crossover_and_event_log(spark, tmp_path):
    runs = spark.createDataFrame([("w", m, c, t) for m, ts in (("a", (9.0, 5.0, 4.0)), ("b", (12.0, 6.0, 3.0))) for c, t in zip((1, 2, 4), ts, strict=True)], "workload string, method string, cores int, seconds double")
    assert M.crossover(runs, "a", "b").collect()[0].cores == 4
    task = {"Event": "SparkListenerTaskEnd", "Task Info": {"Launch Time": 5000, "Finish Time": 15000}, "Task Metrics": {"Executor CPU Time": 8_000_000_000}}
    (tmp_path / "log").write_text(json.dumps(task) + "\n" + json.dumps({"Event": "Other"}) + "\n")
    got = sorted((r["at"], round(r.cpu_seconds, 6), round(r.utilisation, 6)) for r in S.event_log_utilisation(spark, str(tmp_path / "log"), 2).collect())
    assert got == [(0, 4.0, 0.2), (10, 4.0, 0.2)]


def test_monitor_finds_a_planted_burst(spark, tmp_path):
    r = random.Random(4)
    arcs = [(f"2024-03-{d:02d} {r.randrange(24):02d}:00:00", r.randrange(60), r.randrange(60)) for d in range(1, 22) for _ in range(80)]
    arcs += [("2024-03-15 12:00:00", 7, t) for t in range(60)]
    df = spark.createDataFrame(arcs, "ts string, src long, dst long").selectExpr("cast(ts as timestamp) as ts", "src", "dst")
    df.coalesce(1).write.parquet(str(tmp_path / "in"))
    out = str(tmp_path / "out")
    live.monitor_stream(live.read_interactions(spark, str(tmp_path / "in"), df.schema), out, n=spark.range(60).groupBy().count().toDF("n"), threshold=6.0).awaitTermination()
    hot = {(str(a.win_start)[:10], a.pattern) for a in live.stored_alerts(spark, out).collect()}
    assert ("2024-03-15", "fanout") in hot
    assert {d for d, p in hot if p == "fanout"} == {"2024-03-15"}
    series = live.stored_series(spark, out)
    assert series.select("win_start").distinct().count() == 20  # the last day is open
    want = got16(C.census(as_digraph(df.where("to_date(ts) = '2024-03-02'").select("src", "dst"), spark.range(60))))
    assert got16(series.where("to_date(win_start) = '2024-03-02'")) == want


@pytest.mark.parametrize("name", sorted(X.SQL))
def test_oracle(spark, sf, duck, name):
    run = X.QUERIES.get(name) or base.QUERIES[name]
    got, want = run(spark, sf).toPandas(), duck.execute(X.SQL[name]).df()
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols
    assert rows(got, cols) == rows(want, cols)
