"""Task layouts of the pair space: running positions and work without a global window, chunks of three schedules, equal-work units."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .keep import keep


def running_totals(df: DataFrame, key: str, values: list[str], parts: int | None = None) -> DataFrame:
    """(key, before_<value>..): sums of all smaller keys; keys are unique.  Ranges of keys first, then one offset a range."""
    n = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = keep(df.select(key, *values).repartitionByRange(n, key).withColumn("_part", F.spark_partition_id()), "ranges")
    tot = ranged.groupBy("_part").agg(*(F.sum(v).alias(f"_t_{v}") for v in values))
    ahead = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # one row a range
    off = tot.select("_part", *(F.coalesce(F.sum(f"_t_{v}").over(ahead), F.lit(0)).alias(f"_o_{v}") for v in values))
    placed = ranged.join(F.broadcast(off), "_part")
    inner = Window.partitionBy("_part").orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    return placed.select(key, *((F.col(f"_o_{v}") + F.coalesce(F.sum(v).over(inner), F.lit(0))).alias(f"before_{v}") for v in values))


def placed_pairs(pairs: DataFrame, outer: str, inner: str, work: Column) -> DataFrame:
    """Adds w, pos and before (work of all earlier pairs) in the order (outer, inner)."""
    x = pairs.withColumn("w", work.cast("long"))
    base = running_totals(x.groupBy(outer).agg(F.count("*").alias("c"), F.sum("w").alias("w")), outer, ["c", "w"])
    o = Window.partitionBy(outer).orderBy(inner)
    ahead = o.rowsBetween(Window.unboundedPreceding, -1)
    return (x.join(base, outer).withColumn("pos", F.col("before_c") + F.row_number().over(o) - 1)
            .withColumn("before", F.col("before_w") + F.coalesce(F.sum("w").over(ahead), F.lit(0))).drop("before_c", "before_w"))


def weighted_units(pairs: DataFrame, units: int, outer: list[str], inner: str, work: Column) -> DataFrame:
    """Adds unit 0..units-1: contiguous runs of pairs of nearly equal work."""
    x = placed_pairs(pairs, outer[0], inner, work)
    total = x.agg(F.greatest(F.sum("w"), F.lit(1)).alias("_total"))
    return x.crossJoin(F.broadcast(total)).withColumn("unit", F.least(F.lit(units - 1), F.floor(F.col("before") * units / F.col("_total"))).cast("int")).drop("w", "pos", "before", "_total")


def guided_cuts(n: int, cores: int, chunk: int) -> list[int]:
    """First positions of guided chunks; about 2 cores ln(n / cores) of them."""
    cuts, at = [], 0
    while at < n:
        cuts.append(at)
        at += max(chunk, math.ceil((n - at) / (2 * cores)))
    return cuts


def chunk_plan(placed: DataFrame, policy: str, cores: int = 32, chunk: int = 16) -> DataFrame:
    """(chunk_id, n_pairs, work) of static, dynamic or guided hand-out over placed(pos, w)."""
    if policy == "dynamic":
        x = placed.withColumn("chunk_id", F.floor(F.col("pos") / chunk))
    else:
        n = placed.count()
        if policy == "static":
            x = placed.withColumn("chunk_id", F.floor(F.col("pos") / max(1, math.ceil(n / cores))))
        else:
            cuts = guided_cuts(n, cores, chunk) or [0]
            spans = placed.sparkSession.createDataFrame([(i, a, b) for i, (a, b) in enumerate(zip(cuts, [*cuts[1:], n], strict=True))], "chunk_id long, a long, b long")
            x = placed.join(F.broadcast(spans), (F.col("pos") >= F.col("a")) & (F.col("pos") < F.col("b")))
    return x.groupBy("chunk_id").agg(F.count("*").alias("n_pairs"), F.sum("w").alias("work"))
