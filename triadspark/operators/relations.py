"""Joins and set operators on arcs: uneven intervals, as-of, salted, and changes between two graphs or censuses."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def _bucket(at: Column, days: int) -> Column:
    return F.floor(F.date_diff(F.to_date(at), F.lit("1970-01-01").cast("date")) / days)


def assign_intervals(arcs: DataFrame, spans: DataFrame, days: int = 1) -> DataFrame:
    """arcs(ts, ..) with every span(span, start, end) that holds ts, start <= ts < end: spans are repeated once a bucket of days, so the
    join is an equi-join on buckets with the bounds as residue."""
    held = spans.withColumn("bucket", F.explode(F.sequence(_bucket(F.col("start"), days), _bucket(F.col("end"), days))))
    return arcs.withColumn("bucket", _bucket(F.col("ts"), days)).join(held, "bucket").where("ts >= start and ts < end").drop("bucket", "start", "end")


def latest_before(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """left(key, at, ..) with the value of right's last row of the same key strictly before at; null where there is none.  One shuffle by
    key and one running window over both sides, no pairs."""
    both = left.withColumns({"_side": F.lit(0), "_value": F.lit(None).cast(right.schema[value].dataType)}).unionByName(
        right.select(key, at, F.lit(1).alias("_side"), F.col(value).alias("_value")), allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, -1)
    return both.withColumn(value, F.last("_value", ignorenulls=True).over(w)).where("_side = 0").drop("_side", "_value")


def salted_join(a: DataFrame, b: DataFrame, key: list[str], salts: int = 16) -> DataFrame:
    """Equi-join whose left rows of one key are dealt to several tasks; the right side is repeated once a salt."""
    x = a.withColumn("_salt", F.pmod(F.xxhash64(*a.columns), F.lit(salts)).cast("int"))
    y = b.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return x.join(y, [*key, "_salt"]).drop("_salt")


def compare_census(a: DataFrame, b: DataFrame) -> DataFrame:
    """(triad_type, n_left, n_right, diff); a type that one side lacks counts as 0."""
    z = lambda c: F.coalesce(F.col(c), F.lit(0))
    x = a.select("triad_type", F.col("n_triads").alias("n_left")).join(b.select("triad_type", F.col("n_triads").alias("n_right")), "triad_type", "full")
    return x.select("triad_type", z("n_left").alias("n_left"), z("n_right").alias("n_right"), (z("n_right") - z("n_left")).alias("diff"))


def dyad_changes(before: DataFrame, after: DataFrame) -> DataFrame:
    """(lo, hi, was, is_now): pairs whose direction code differs, 0 for not adjacent."""
    x = before.select("lo", "hi", F.col("dir").alias("was")).join(after.select("lo", "hi", F.col("dir").alias("is_now")), ["lo", "hi"], "full")
    return x.select("lo", "hi", F.coalesce("was", F.lit(0)).alias("was"), F.coalesce("is_now", F.lit(0)).alias("is_now")).where("was <> is_now")


def persistent_arcs(before: DataFrame, after: DataFrame) -> DataFrame:
    return before.select("src", "dst").intersect(after.select("src", "dst"))


def new_arcs(before: DataFrame, after: DataFrame) -> DataFrame:
    return after.select("src", "dst").subtract(before.select("src", "dst"))


def sender_sessions(arcs: DataFrame, gap: str = "6 hours") -> DataFrame:
    """(src, start, end, n_arcs): bursts of a sender, parted by pauses of at least gap."""
    x = arcs.groupBy("src", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n_arcs"))
    return x.select("src", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n_arcs")


def split_hubs(degrees: DataFrame, limit: int) -> tuple[DataFrame, DataFrame]:
    """(hubs, others) of a degree frame."""
    return degrees.where(F.col("d") > limit), degrees.where(F.col("d") <= limit)
