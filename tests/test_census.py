"""Worked graphs, method agreement, invariants, oracles."""

import itertools
import random

import pytest
from conftest import rows

from triadspark.functions.codes import FOLD, LABELS, TYPES, triad_total
from triadspark.operators import census as C
from triadspark.operators import measures as M
from triadspark.operators.graph import as_digraph
from triadspark.plans import registry as R


def brute(n, arcs):
    s = {(a, b) for a, b in arcs if a != b}
    d = lambda a, b: ((a, b) in s) + 2 * ((b, a) in s)
    out = [0] * 64
    for a, b, c in itertools.combinations(range(n), 3):
        out[d(a, b) + 4 * d(a, c) + 16 * d(b, c)] += 1
    return out


def graph(spark, n, arcs):
    return as_digraph(spark.createDataFrame(arcs, "src long, dst long"), spark.range(n))


def got16(df):
    return [int(r.n_triads) for r in sorted(df.collect(), key=lambda r: r.triad_no)]


def fold(states):
    out = [0] * 16
    for c, x in enumerate(states):
        out[FOLD[c] - 1] += x
    return out


def test_types_cover_all_states():
    assert sorted(c for t in TYPES for c in t[8]) == list(range(64))


@pytest.mark.parametrize("density", [0.1, 0.4])
def test_all_methods_agree_with_brute_force(spark, density):
    r = random.Random(int(density * 10))
    n = 11
    arcs = [(a, b) for a in range(n) for b in range(n) if r.random() < density] + [(3, 3), (1, 2), (1, 2)]
    want = brute(n, arcs)
    g = graph(spark, n, arcs)
    for f in (C.census_scalable, C.census_naive, C.census_matrix, lambda g: C.census_edge_driven(g, "join"), lambda g: C.census_edge_driven(g, "set", slots=1), lambda g: C.census_edge_driven(g, "merge", slots=7), lambda g: C.census_edge_driven(g, "merge", balance="outer")):
        assert got16(f(g)) == fold(want)
    c64 = C.census64(g)
    assert [int(x.n_triads) for x in sorted(c64.collect(), key=lambda x: x.code)] == want
    assert got16(C.condense(c64)) == fold(want)


def test_small_graphs(spark):
    for n in (0, 1, 2, 4):
        assert sum(got16(C.census(graph(spark, n, [])))) == n * (n - 1) * (n - 2) // 6
    k5 = [(a, b) for a in range(5) for b in range(5) if a != b]
    assert got16(C.census(graph(spark, 5, k5))) == [0] * 15 + [10]
    tail = [(0, 1), (1, 2), (2, 0), (2, 3)]  # a literal union of neighbours would undercount the dyadic types here
    assert got16(C.census_edge_driven(graph(spark, 6, tail), "merge")) == fold(brute(6, tail))


def test_reversal_swaps_types(spark):
    r = random.Random(5)
    arcs = [(a, b) for a in range(9) for b in range(9) if a != b and r.random() < 0.3]
    x = dict(zip(LABELS, got16(C.census(graph(spark, 9, arcs))), strict=True))
    y = dict(zip(LABELS, got16(C.census(graph(spark, 9, [(b, a) for a, b in arcs]))), strict=True))
    for a, b in (("021D", "021U"), ("111D", "111U"), ("120D", "120U")):
        assert (x[a], x[b]) == (y[b], y[a])


def test_total_is_exact_beyond_64_bits(spark):
    from pyspark.sql import functions as F

    assert int(spark.range(1).select(triad_total(F.lit(105200000))).collect()[0][0]) == 194042095799813368400000


def test_schedules():
    assert M.schedule_makespan([1] * 16, 4, "static")[0] == M.schedule_makespan([1] * 16, 4, "dynamic")[0] == 4
    heavy = [50] + [1] * 50
    assert M.schedule_makespan(heavy, 2, "dynamic")[0] <= M.schedule_makespan(heavy, 2, "static")[0]


@pytest.mark.parametrize("name", sorted(R.SQL))
def test_oracle(spark, sf, duck, name):
    got, want = R.QUERIES[name](spark, sf).toPandas(), duck.execute(R.SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    cols = sorted(want.columns)
    assert rows(got, cols) == rows(want, cols)


def test_word_census_reads_all_documents(spark, sf):
    import re

    from triadspark.operators.census import census
    from triadspark.sources.workloads import word_graph

    names, arcs = set(), set()
    for r in spark.read.parquet(f"{sf}/documents.parquet").select("text").collect():
        w = re.split(r"[\W\d_]+", (r.text or "").lower())
        pairs = [(a, b) for a, b in zip(w, w[1:]) if a and b]
        names |= {x for p in pairs for x in p}
        arcs |= {p for p in pairs if p[0] != p[1]}
    near = {x: set() for x in names}
    for a, b in arcs:
        near[a].add(b)
        near[b].add(a)
    closed = mutual = 0
    for a in names:
        for b in near[a]:
            if a < b:
                third = [c for c in near[a] & near[b] if b < c]
                closed += len(third)
                mutual += sum(all((x, y) in arcs and (y, x) in arcs for x, y in ((a, b), (b, c), (a, c))) for c in third)
    got = {r[0]: int(r[2]) for r in census(word_graph(spark, sf)).collect()}
    n = len(names)
    assert sum(got.values()) == n * (n - 1) * (n - 2) // 6
    assert sum(got[x] for x in ("030T", "030C", "120D", "120U", "120C", "210", "300")) == closed and got["300"] == mutual


def test_words_write_pairs_once_and_leave_no_step_behind(spark, sf):
    from triadspark.operators import census as C
    from triadspark.operators import graph as G
    from triadspark.operators import keep as K
    from triadspark.sources import workloads as W

    K.clear_kept(spark)
    g = W.word_graph(spark, sf)
    assert sum("/dyads-" in p for p in K._KEPT) == 1  # not those under words, nor those half renamed
    assert C.planned_method(g) and G.settled(g)[0] is g
    assert sum("/dyads-" in p for p in K._KEPT) == 1
    t = spark.createDataFrame([("b", "a"), ("a", "b"), ("c", "a"), ("b", "d")], "src string, dst string")
    x, names = W.named_graph(t, steps=True)
    y, same = W.named_graph(t)
    assert sorted(map(tuple, x.dyads.collect())) == sorted(map(tuple, y.dyads.collect())) == [(0, 1, 3), (0, 2, 2), (1, 3, 1)]
    assert sorted(map(tuple, names.collect())) == sorted(map(tuple, same.collect())) == [("a", 0), ("b", 1), ("c", 2), ("d", 3)]


def test_colour_blocks_ship_a_pair_once_a_round(spark, monkeypatch):
    from triadspark.operators import blocks as B
    from triadspark.operators import census as C
    from triadspark.operators.graph import as_digraph

    n = 120  # a complete graph: (n - 2) / 3 wedges from the lesser end a pair
    g = as_digraph(spark.range(n).toDF("src").crossJoin(spark.range(n).toDF("dst")).where("src < dst"))
    assert C.planned_method(g, least_n=n + 1) == "colour_blocks"
    seen = []
    whole = type(spark.range(1)).groupBy

    def noted(self, *by):
        if by == ("c1", "c2", "c3"):
            seen.append(self.count())
        return whole(self, *by)

    monkeypatch.setattr(type(spark.range(1)), "groupBy", noted)
    got = {r.no: r.c for r in B.colour_counts(g, 4).collect()}
    assert got == {9: n * (n - 1) * (n - 2) // 6}
    assert seen == [n * (n - 1) // 2] * 4
