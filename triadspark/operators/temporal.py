"""Censuses per time interval, their shares, drift, pattern scores and alerts: one job for all intervals."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codes import LABELS
from .census import census_scalable
from .graph import Digraph, as_digraph

#: own choice of default patterns: pattern, type, direction, member; types of one member stand in for each other
PATTERNS = [("fanout", "021D", "up", "021D"), ("fanin", "021U", "up", "021U"), ("relay", "021C", "up", "021C"), ("relay", "030T", "up", "030T"),
            ("mutual_cluster", "102", "up", "102"), ("mutual_cluster", "201", "up", "201"), ("mutual_cluster", "300", "up", "300 or 210"), ("mutual_cluster", "210", "up", "300 or 210")]


def census_by_interval(arcs: DataFrame, every: str = "1 day", slide: str | None = None, n: DataFrame | None = None, fill: bool = True) -> DataFrame:
    """(win_start, triad_type, triad_no, n_triads) for each interval; n: one-row frame with the fixed universe's size, else the
    interval's own active vertices.  fill: intervals without arcs between the first and the last are there too, with null triads alone under
    the fixed universe and with none under the active one."""
    w = arcs.select(F.window("ts", every, slide).start.alias("win_start"), "src", "dst")
    g = as_digraph(w, keys=["win_start"])
    if fill:
        ends = w.agg(F.min("win_start").alias("a"), F.max("win_start").alias("b")).where("a is not null")
        there = ends.select(F.explode(F.sequence("a", "b", F.expr(f"interval {slide or every}"))).alias("win_start"))
    else:
        there = w.select("win_start").distinct()
    if n is not None:
        sizes = there.crossJoin(F.broadcast(n))
    else:
        sizes = there.join(g.sizes, "win_start", "left").select("win_start", F.coalesce("n", F.lit(0)).alias("n"))
    return census_scalable(Digraph(g.dyads, sizes, g.keys, g.vertices))


def census_by_slice(arcs: DataFrame, key: str) -> DataFrame:
    """One census per value of a column (a census of a union is not a sum of censuses)."""
    return census_scalable(as_digraph(arcs.select(key, "src", "dst"), keys=[key]))


def census_shares(series: DataFrame, over: str = "nonnull") -> DataFrame:
    """Adds share: of all, non-null or connected triads of the interval."""
    counts = {"all": F.lit(True), "nonnull": F.col("triad_no") > 1, "connected": F.col("triad_no") > 3}[over]
    part = F.when(counts, F.col("n_triads")).otherwise(0)
    tot = F.sum(part).over(Window.partitionBy("win_start"))
    return series.withColumn("total", tot.cast("double")).withColumn("share", F.when(F.col("total") > 0, F.round(part.cast("double") / F.col("total"), 9)).otherwise(0.0))


def census_drift(shares: DataFrame, lookback: int = 7) -> DataFrame:
    """Change to the interval before, trailing mean and deviation without the present one, z with a counting-noise floor."""
    o = Window.partitionBy("triad_type").orderBy("win_start")
    t = o.rowsBetween(-lookback, -1)
    x = shares.withColumns({"change": F.round(F.col("share") - F.lag("share").over(o), 9), "mean": F.avg("share").over(t), "dev": F.stddev_samp("share").over(t), "history": F.count("share").over(t), "mean_n": F.avg(F.col("n_triads").cast("double")).over(t)})
    floor = F.sqrt(F.greatest(F.col("mean_n"), F.lit(1.0))) / F.greatest("total", F.lit(1.0))
    return x.withColumn("z", F.round((F.col("share") - F.col("mean")) / F.greatest(F.coalesce("dev", F.lit(0.0)), floor), 6))


def pattern_scores(drift: DataFrame, patterns: DataFrame | None = None, combine: str = "all") -> DataFrame:
    """(win_start, pattern, score, history, members): all = least, any = greatest, mean = average of the members' signed z.  Of types that stand
    in for each other (same value of the optional column member) the greatest counts."""
    spark = drift.sparkSession
    p = patterns if patterns is not None else spark.createDataFrame(PATTERNS, "pattern string, triad_type string, direction string, member string")
    if "member" not in p.columns:
        p = p.withColumn("member", F.col("triad_type"))
    x = drift.join(F.broadcast(p), "triad_type").withColumn("s", F.when(F.col("direction") == "down", -F.col("z")).otherwise(F.col("z")))
    agg = {"all": F.min, "any": F.max, "mean": F.avg}[combine]
    each = x.groupBy("win_start", "pattern", "member").agg(F.max("s").alias("s"), F.min("history").alias("history"), F.collect_list(F.struct("triad_type", "z")).alias("ms"))
    return each.groupBy("win_start", "pattern").agg(F.round(agg("s"), 6).alias("score"), F.min("history").alias("history"), F.sort_array(F.flatten(F.collect_list("ms"))).alias("members"))


def alerts(scores: DataFrame, threshold: float = 3.0, min_history: int = 5, combos: dict[str, list[str]] | None = None) -> DataFrame:
    """Patterns beyond the threshold, and named combinations of patterns of one interval."""
    hot = scores.where((F.col("history") >= min_history) & (F.col("score") >= threshold))
    out = hot.select("win_start", "pattern", "score")
    if combos:
        held = hot.groupBy("win_start").agg(F.collect_set("pattern").alias("ps"), F.min("score").alias("score"))
        for name, need in combos.items():
            out = out.unionByName(held.where(F.size(F.array_intersect("ps", F.array(*map(F.lit, need)))) == len(need)).select("win_start", F.lit(name).alias("pattern"), "score"))
    return out


def census_wide(series: DataFrame) -> DataFrame:
    return series.groupBy("win_start").pivot("triad_type", LABELS).agg(F.first("n_triads"))


def census_long(wide: DataFrame) -> DataFrame:
    """The inverse of census_wide: (win_start, triad_type, n_triads)."""
    return wide.unpivot("win_start", [f"`{x}`" for x in LABELS], "triad_type", "n_triads")


def series_quantiles(series: DataFrame, shares: tuple[float, ...] = (0.5, 0.9)) -> DataFrame:
    """(triad_type, q<percent>.., skew, busiest): exact percentiles and skewness of each type's counts, and the interval that has most."""
    n = F.col("n_triads").cast("double")
    return series.groupBy("triad_type").agg(*(F.round(F.percentile(n, q), 6).alias(f"q{round(100 * q)}") for q in shares), F.round(F.skewness(n), 6).alias("skew"),
                                            F.max_by("win_start", F.struct(n, "win_start")).alias("busiest"))


def top_movers(drift: DataFrame, k: int = 10) -> DataFrame:
    """The k largest changes of share between neighbouring intervals."""
    return drift.where("change is not null").select("win_start", "triad_type", "change").orderBy(F.desc(F.abs("change")), "win_start", "triad_type").limit(k)


def census_ratios(series: DataFrame, pairs: list[tuple[str, str]]) -> DataFrame:
    """(win_start, above, below, ratio) of two types' counts; null where the lower count is 0."""
    wide = census_wide(series)
    cells = [F.struct(F.lit(a).alias("above"), F.lit(b).alias("below"), F.when(F.col(f"`{b}`") > 0, F.round(F.col(f"`{a}`").cast("double") / F.col(f"`{b}`").cast("double"), 6)).alias("ratio")) for a, b in pairs]
    return wide.select("win_start", F.explode(F.array(*cells)).alias("r")).select("win_start", "r.*")
