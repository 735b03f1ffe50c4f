"""Ids of any size, plans without nested loops, gaps, state of the monitor, error columns, planner, vectors; oracles of the queries in plans/further.py."""

import random

import pytest
from conftest import rows
from pyspark.sql import functions as F
from test_census import brute, fold, got16, graph

from triadspark.operators import blocks as B
from triadspark.operators import census as C
from triadspark.operators import graph as G
from triadspark.operators import layout as L
from triadspark.operators import temporal as T
from triadspark.plans import further as X
from triadspark.plans import registry as base
from triadspark.sources import workloads as W
from triadspark.streaming import monitor as live


@pytest.fixture(scope="module")
def wide(spark):
    """The same graph on small ids and on negative and 64-bit ones."""
    r = random.Random(12)
    n = 12
    arcs = [(a, b) for a in range(n) for b in range(n) if r.random() < 0.25]
    far = lambda a: a * (1 << 59) - (1 << 62) - (a % 2)
    g = G.as_digraph(spark.createDataFrame([(far(a), far(b)) for a, b in arcs], "src long, dst long"), spark.createDataFrame([(far(a),) for a in range(n)], "id long"))
    return graph(spark, n, arcs), g, brute(n, arcs)


def test_every_form_on_far_ids(wide):
    _, g, want = wide
    for f in (lambda g: C.census_edge_driven(g, "set"), lambda g: C.census_edge_driven(g, "merge"), lambda g: C.census_edge_driven(g, "merge", piece=3), lambda g: C.census_edge_driven(g, "merge", balance="weighted", piece=2), C.census_matrix, C.census_scalable):
        assert got16(f(g)) == fold(want)
    assert [int(x.n_triads) for x in sorted(C.census64(g).collect(), key=lambda x: x.code)] == want


def test_packing_refuses_far_ids(wide):
    near, far, _ = wide
    assert G.fits_packing(near) and not G.fits_packing(far)
    with pytest.raises(Exception, match="62 bits"):
        G.packed_adjacency(far).collect()
    d, names = G.dense(far)
    back = G.with_labels(d.dyads, names, ["lo", "hi"]).select("lo", "hi", "dir")
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, far.dyads.select("lo", "hi", "dir").collect()))


def test_names_never_meet(spark):
    arcs = spark.createDataFrame([("a", "b"), ("b", "c"), ("c", "a"), ("é", "a")], "src string, dst string")
    g, names = W.named_graph(arcs, spark.createDataFrame([("z",)], "id string"))
    assert [r.id for r in names.orderBy("rank").collect()] == ["a", "b", "c", "z", "é"]
    assert got16(C.census_scalable(g))[C.LABELS.index("030C")] == 1


def test_plans_have_no_nested_loop(spark, wide):
    near, _, _ = wide
    for df in (G.relabel(near.vertices), L.running_totals(spark.range(50).selectExpr("id as k", "id as v"), "k", ["v"]), C.triangles(near), C.ordered_triangles(near), G.to_csr(near)[0]):
        assert "NestedLoop" not in df._jdf.queryExecution().executedPlan().toString() and "Cartesian" not in df._jdf.queryExecution().executedPlan().toString()


def test_state_of_the_monitor_equals_the_batch_form(spark, sf, tmp_path):
    shares = T.census_shares(base._long(base._daily(spark, sf))).withColumn("win_start", F.col("win_start").cast("timestamp")).select("win_start", "triad_type", "n_triads", "total", "share")
    days = sorted({r.win_start for r in shares.select("win_start").distinct().collect()})
    for part in (days[:11], days[11:]):
        shares.where(F.col("win_start").isin(part)).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    q = live.drift_stream(live.read_interactions(spark, str(tmp_path / "in"), shares.schema, 1)).writeStream.format("memory").queryName("drift_state").option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = {(r.win_start, r.triad_type): r for r in spark.table("drift_state").collect()}
    batch = T.census_drift(T.census_shares(base._long(base._daily(spark, sf)))).withColumn("win_start", F.col("win_start").cast("timestamp")).collect()
    assert len(got) == len(batch)
    for r in batch:
        x = got[r.win_start, r.triad_type]
        assert (x.history, x.change) == (r.history, pytest.approx(r.change)) and x.z == pytest.approx(r.z, abs=1e-5)


def test_late_rows_are_counted_and_intervals_may_overlap(spark, tmp_path):
    rows_of = lambda xs: spark.createDataFrame(xs, "ts string, src long, dst long").selectExpr("cast(ts as timestamp) as ts", "src", "dst").coalesce(1)
    first = rows_of([(f"2024-03-0{d} 12:00:00", 1, d) for d in range(1, 8)])
    for part in (first, rows_of([("2024-03-07 13:00:00", 1, 2)]), rows_of([("2024-03-01 10:00:00", 8, 9), ("2024-03-09 10:00:00", 8, 9)])):
        part.write.mode("append").parquet(str(tmp_path / "in"))
    q = live.monitor_stream(live.read_interactions(spark, str(tmp_path / "in"), first.schema, 1), str(tmp_path / "out"), every="2 days", slide="1 day")
    q.awaitTermination()
    assert live.late_rows(q) >= 1
    starts = sorted(str(r.win_start)[:10] for r in live.stored_series(spark, str(tmp_path / "out")).select("win_start").distinct().collect())
    assert starts[:3] == ["2024-02-29", "2024-03-01", "2024-03-02"]


def test_sampled_errors_cover_the_truth(spark):
    r = random.Random(8)
    arcs = [(a, b) for a in range(50) for b in range(50) if a != b and r.random() < 0.3]
    g = graph(spark, 50, arcs)
    exact = dict(zip(C.LABELS, got16(C.census(g)), strict=True))
    near = {x.triad_type: x for x in B.census_sampled(g, 0.7).collect()}
    assert all(x.std_error >= 0 for x in near.values()) and near["030T"].std_error > 0
    assert all(abs(int(near[t].n_triads) - exact[t]) <= 5 * near[t].std_error + 1 for t in C.LABELS)
    assert all(x.std_error == 0 for x in B.census_sampled(g, 1.0).collect())


def test_planner_and_small_graphs(spark, wide):
    near, _, want = wide
    assert C.planned_method(near) == "scalable" and C.planned_method(near, wedges_a_pair=0) == "colour_blocks" and C.planned_method(near, least_n=1, dense_share=0.01) == "matrix_blocks"
    assert got16(C.census(near)) == got16(C.census(near, "matrix_blocks")) == got16(C.census(near, "colour_blocks")) == fold(want)
    vectors = spark.createDataFrame([([1, 2], "a"), ([10, 20], "a"), ([5, 5], "b")], "counts array<bigint>, k string")
    assert {r.k: [int(x) for x in r.counts] for r in C.census_merge(vectors, ["k"]).collect()} == {"a": [11, 22], "b": [5, 5]}


@pytest.mark.parametrize("name", sorted(X.SQL))
def test_oracle(spark, sf, duck, name):
    run = X.QUERIES.get(name) or base.QUERIES[name]
    got, want = run(spark, sf).toPandas(), duck.execute(X.SQL[name]).df()
    cols = sorted(want.columns)
    assert sorted(got.columns) == cols
    assert rows(got, cols) == rows(want, cols)


def test_edge_driven_forms_ship_no_hub(spark):
    """Two hubs with 400 leaves each: whole runs of all pairs' ends would be some 320,000 entries, all paths some 160,000 rows."""
    r = random.Random(21)
    arcs = [(h, x) if r.random() < 0.7 else (x, h) for h in (3, 200) for x in range(400) if x != h] + [(r.randrange(400), r.randrange(400)) for _ in range(300)]
    g, deg = G.settled(graph(spark, 410, arcs))
    want = got16(C.census_scalable(g))
    for f in (lambda: C.census_edge_driven(g, "join"), lambda: C.census_edge_driven(g, "set"), lambda: C.census_edge_driven(g, "merge", balance="weighted"), lambda: C.census_edge_driven(g, "merge", piece=16)):
        assert got16(f()) == want
    shipped = C._both_runs(g, C._out_runs(g, deg)).agg(F.sum(F.size("pu") + F.size("pv"))).first()[0]
    assert shipped < 10 * g.dyads.count()
    by = lambda x: sorted(map(tuple, x.collect()))
    listed = C.connected_triads(g).select("u", "v", C.fold_code(F.col("code")).alias("triad_no"), F.lit(1).cast("long").alias("c"))
    assert by(C.accumulate(listed, keep_slots=True)) == by(C.accumulate(C.connected_counts(g), keep_slots=True))
    assert not [j for j in C.connected_counts(g)._jdf.queryExecution().optimizedPlan().toString().split("\n") if "LeftOuter" in j]


def test_nearest_of_a_block_are_found_at_once():
    import numpy as np
    import pyarrow as pa

    r = np.random.default_rng(5)
    a, b = r.integers(-1, 2, (40, 4)).astype(float), r.integers(-1, 2, (60, 4)).astype(float)
    batch = pa.RecordBatch.from_pydict({"ia": [list(range(40))], "va": [a.tolist()], "ib": [list(range(30, 90))], "vb": [b.tolist()]})
    got = list(W._nearest(3)([batch]))
    assert len(got) == 1
    unit = lambda m: m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)
    cos = np.round(unit(a) @ unit(b).T, 9)
    want = [(i, 30 + j) for i in range(40) for j in sorted((j for j in range(60) if 30 + j != i), key=lambda j: (-cos[i, j], j))[:3]]
    assert list(zip(got[0]["src"].to_pylist(), got[0]["dst"].to_pylist(), strict=True)) == want
