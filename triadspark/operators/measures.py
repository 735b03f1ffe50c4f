"""Degree laws, census properties, speed-up tables, balance of layouts and schedules."""

from __future__ import annotations

import heapq
import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codes import TYPES
from .graph import Digraph, degrees


def degree_histogram(g: Digraph, kind: str = "out") -> DataFrame:
    col = {"out": F.col("a") + F.col("m"), "in": F.col("b") + F.col("m"), "all": F.col("d")}[kind]
    return degrees(g).groupBy(col.alias("degree")).agg(F.count("*").alias("n_vertices"))


def power_law_exponent(hist: DataFrame, kmin: int = 1) -> DataFrame:
    """(loglog, mle): least squares on the log-log histogram, and maximum likelihood."""
    h = hist.where(F.col("degree") >= kmin)
    return h.agg(F.round(-F.regr_slope(F.ln("n_vertices"), F.ln("degree")), 6).alias("loglog"), F.round(1 + F.sum("n_vertices") / F.sum(F.col("n_vertices") * F.ln(F.col("degree") / (kmin - 0.5))), 6).alias("mle"))


def census_properties(census: DataFrame) -> DataFrame:
    """(mutual_pairs_share, transitivity, cyclic) from the 16 counts."""
    w = lambda i: sum((F.sum(F.when(F.col("triad_no") == t[0], F.col("n_triads").cast("double") * t[i])) for t in TYPES[1:]), F.sum(F.when(F.col("triad_no") == 1, 0.0)))
    return census.agg(F.round(w(2) / (w(2) + w(3)), 6).alias("reciprocity"), F.round(w(5) / (w(5) + w(6)), 6).alias("transitivity"), w(7).cast("long").alias("cycles"))


def dyad_census(g: Digraph) -> DataFrame:
    x = g.dyads.agg(F.count_if(F.col("dir") == 3).alias("mutual"), F.count_if(F.col("dir") < 3).alias("asym"))
    return x.crossJoin(F.broadcast(g.sizes)).select("mutual", "asym", (F.col("n") * (F.col("n") - 1) / 2 - F.col("mutual") - F.col("asym")).cast("long").alias("nulls"))


def work_per_unit(g: Digraph, unit: str = "pair") -> DataFrame:
    """(units, total, top, mean_ratio): predicted d_u + d_v per task unit, pair (collapsed) or smaller vertex (outer)."""
    d = degrees(g).select("id", "d")
    x = g.dyads.join(d.toDF("lo", "dl"), "lo").join(d.toDF("hi", "dh"), "hi").select("lo", "hi", (F.col("dl") + F.col("dh")).alias("w"))
    x = x if unit == "pair" else x.groupBy("lo").agg(F.sum("w").alias("w"))
    return x.agg(F.count("*").alias("units"), F.sum("w").alias("total"), F.max("w").alias("top"), F.round(F.max("w") / F.avg("w"), 6).alias("mean_ratio"))


def slot_uniformity(g: Digraph, slots: int = 64) -> DataFrame:
    """(slot, n_pairs) of the private-vector hash."""
    return g.dyads.groupBy(F.pmod(F.xxhash64("lo", "hi"), F.lit(slots)).cast("int").alias("slot")).agg(F.count("*").alias("n_pairs"))


def slot_contention(rows: DataFrame, slots: int = 64) -> DataFrame:
    """(slot, n_rows, n_shuffled) of rows(u, v, triad_no, c): triads added to each private vector, and the partial counts that reach the shuffle for it, one a task
    and type.  slots=1 is the single shared vector."""
    x = rows.select(F.pmod(F.xxhash64("u", "v"), F.lit(slots)).cast("int").alias("slot"), "triad_no", "c", F.spark_partition_id().alias("task"))
    return x.groupBy("slot", "triad_no", "task").agg(F.sum("c").alias("c")).groupBy("slot").agg(F.sum("c").alias("n_rows"), F.count("*").alias("n_shuffled"))


def local_clustering(g: Digraph, tri: DataFrame) -> DataFrame:
    t = tri.select(F.explode(F.array("t", "x", "y")).alias("id")).groupBy("id").agg(F.count("*").alias("closed"))
    d = F.col("d")
    return degrees(g).join(t, "id", "left").select("id", d, F.coalesce("closed", F.lit(0)).alias("closed"), F.when(d > 1, F.round(2 * F.coalesce("closed", F.lit(0)) / (d * (d - 1)), 6)).otherwise(0.0).alias("clustering"))


def top_hubs(g: Digraph, k: int = 10) -> DataFrame:
    return degrees(g).select("id", "d").orderBy(F.desc("d"), "id").limit(k)


def speedup(runs: DataFrame) -> DataFrame:
    """runs(workload, method, cores, seconds): adds speed-up and efficiency to the smallest core count."""
    w = Window.partitionBy("workload", "method").orderBy("cores")
    base, c0 = F.first("seconds").over(w), F.first("cores").over(w)
    return runs.withColumn("speedup", base / F.col("seconds")).withColumn("efficiency", base * c0 / (F.col("seconds") * F.col("cores")))


def schedule_makespan(work: list[int], cores: int, policy: str, chunk: int = 1) -> tuple[int, float]:
    """(makespan, efficiency) of static, dynamic or guided chunking; work is one number per unit, in order."""
    n = len(work)
    sums = [0]
    for w in work:
        sums.append(sums[-1] + w)
    cuts, at = [], 0
    while at < n:
        size = {"static": math.ceil(n / cores), "dynamic": chunk, "guided": max(chunk, math.ceil((n - at) / (2 * cores)))}[policy]
        cuts.append(sums[min(n, at + size)] - sums[at])
        at += size
    free = [0] * cores
    for c in cuts:
        heapq.heapreplace(free, free[0] + c)
    span = max(free)
    return span, sums[-1] / (cores * span) if span else 1.0


def crossover(runs: DataFrame, a: str, b: str) -> DataFrame:
    """(workload, cores): the smallest core count from which method b is faster than a, where it was not at the count before."""
    w = Window.partitionBy("workload").orderBy("cores")
    x = runs.where(F.col("method").isin(a, b)).groupBy("workload", "cores").pivot("method", [a, b]).agg(F.min("seconds"))
    x = x.withColumn("ahead", F.col(b) < F.col(a)).withColumn("was", F.coalesce(F.lag("ahead").over(w), F.lit(False)))
    return x.where("ahead and not was").groupBy("workload").agg(F.min("cores").alias("cores"))


def graph_profile(g: Digraph) -> DataFrame:
    """(n, arcs, pairs, mutual, isolated, max_degree) of a graph without keys."""
    d = degrees(g).agg(F.count("*").alias("touched"), F.max("d").alias("max_degree"))
    p = g.dyads.agg(F.count("*").alias("pairs"), F.count_if(F.col("dir") == 3).alias("mutual"))
    x = g.sizes.crossJoin(F.broadcast(d)).crossJoin(F.broadcast(p))
    return x.select("n", (F.col("pairs") + F.col("mutual")).alias("arcs"), "pairs", "mutual", (F.col("n") - F.col("touched")).alias("isolated"), F.coalesce("max_degree", F.lit(0)).alias("max_degree"))


def compactness(g: Digraph) -> DataFrame:
    """(layout, bytes_per_pair): one packed long an end against an id and a separate direction byte, list heads included."""
    x = g.dyads.agg(F.count("*").alias("p")).crossJoin(F.broadcast(degrees(g).agg(F.count("*").alias("v"))))
    rows = F.array(*(F.struct(F.lit(k).alias("layout"), F.round((F.col("p") * 2 * w + F.col("v") * 12) / F.col("p"), 6).alias("bytes_per_pair")) for k, w in (("packed", 8), ("separate", 9), ("two arc lists", 16))))
    return x.where("p > 0").select(F.explode(rows).alias("r")).select("r.*")


def schedule_table(chunks: dict[str, list[int]], cores: int) -> list[tuple[str, int, float]]:
    """(policy, makespan, efficiency) of chunk works handed out in order to the earliest free core."""
    return [(policy, *schedule_makespan(work, cores, "dynamic", 1)) for policy, work in chunks.items()]
