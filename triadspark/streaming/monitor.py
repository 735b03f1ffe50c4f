"""The live monitor: interactions in, one census a closed interval, drift and alerts against the stored series out."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.census import census_scalable
from ..operators.graph import as_digraph
from ..operators.temporal import alerts, census_drift, census_shares, pattern_scores

SERIES = "win_start timestamp, triad_type string, triad_no int, n_triads decimal(38,0), batch long"


def read_interactions(spark: SparkSession, path: str, schema, max_files: int | None = None) -> DataFrame:
    """A file stream over a landing folder."""
    r = spark.readStream.schema(schema)
    return (r.option("maxFilesPerTrigger", max_files) if max_files else r).parquet(path)


def closed_arcs(stream: DataFrame, every: str, delay: str, slide: str | None = None) -> DataFrame:
    """(win_start, src, dst, n) of a stream(ts, src, dst): each distinct arc of an interval once, when the watermark closes the interval.
    Rows behind the watermark are dropped and counted by the engine (numRowsDroppedByWatermark)."""
    x = stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    return x.groupBy(F.window("ts", every, slide).alias("w"), "src", "dst").agg(F.count("*").alias("n")).select(F.col("w.start").alias("win_start"), "src", "dst", "n")


def monitor_stream(stream: DataFrame, out: str, every: str = "1 day", delay: str = "1 hour", n: DataFrame | None = None, lookback: int = 7,
                   threshold: float = 3.0, min_history: int = 5, trigger: dict | None = None, slide: str | None = None) -> StreamingQuery:
    """With slide, intervals overlap.  Writes out/series (censuses of closed intervals) and out/alerts, in one folder a batch that a repeated batch overwrites.

    n: one-row frame with the fixed universe's size; else the interval's active vertices.  Drift reads only the stored 16-row censuses, of
    batches before this one."""

    def on_batch(rows: DataFrame, batch: int) -> None:
        spark = rows.sparkSession
        arcs = rows.select("win_start", "src", "dst").persist()  # read for pairs, degrees and sizes
        sizes = None if n is None else arcs.select("win_start").distinct().crossJoin(F.broadcast(n))
        census = census_scalable(as_digraph(arcs, keys=["win_start"], sizes=sizes))
        census.write.mode("overwrite").parquet(f"{out}/series/batch={batch}")
        arcs.unpersist()
        series = spark.read.schema(SERIES).parquet(f"{out}/series").where(F.col("batch") <= batch).select("win_start", "triad_type", "triad_no", "n_triads")
        hot = alerts(pattern_scores(census_drift(census_shares(series), lookback)), threshold, min_history)
        now = spark.read.parquet(f"{out}/series/batch={batch}").select("win_start").distinct()
        hot.join(now, "win_start", "left_semi").write.mode("overwrite").parquet(f"{out}/alerts/batch={batch}")

    w = closed_arcs(stream, every, delay, slide).writeStream.outputMode("append").option("checkpointLocation", f"{out}/checkpoint").foreachBatch(on_batch)
    return w.trigger(**(trigger or {"availableNow": True})).start()


def late_rows(query: StreamingQuery) -> int:
    """Rows that came behind the watermark and were dropped, over the batches that the query still remembers."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])


DRIFT = "win_start timestamp, triad_type string, share double, change double, history long, z double"


class PatternState:
    """Per type, the shares and counts of its last `lookback` intervals: the rolling baseline of the live monitor, kept by the stream itself."""

    SCHEMA = "shares array<double>, counts array<double>"

    def __init__(self, lookback: int = 7):
        self.lookback = lookback

    def __call__(self, key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        shares, counts = map(list, state.get) if state.exists else ([], [])
        new, rows = pd.concat(list(frames)).sort_values("win_start"), []
        for r in new.itertuples():
            k, total = len(shares), max(float(r.total), 1.0)
            change = round(r.share - shares[-1], 9) if k else None
            z = None
            if k:
                mean = sum(shares) / k
                dev = (sum((x - mean) ** 2 for x in shares) / (k - 1)) ** 0.5 if k > 1 else 0.0
                z = round((r.share - mean) / max(dev, max(sum(counts) / k, 1.0) ** 0.5 / total), 6)
            rows.append((r.win_start, key[0], r.share, change, k, z))
            shares, counts = (shares + [r.share])[-self.lookback :], (counts + [float(r.n_triads)])[-self.lookback :]
        state.update((shares, counts))
        yield pd.DataFrame(rows, columns=["win_start", "triad_type", "share", "change", "history", "z"])


def drift_stream(shares: DataFrame, lookback: int = 7) -> DataFrame:
    """The drift of a stream of shares(win_start, triad_type, n_triads, total, share), intervals in order; equal to the batch form."""
    return shares.groupBy("triad_type").applyInPandasWithState(PatternState(lookback), DRIFT, PatternState.SCHEMA, "append", GroupStateTimeout.NoTimeout)


def stored_series(spark: SparkSession, out: str) -> DataFrame:
    return spark.read.schema(SERIES).parquet(f"{out}/series").drop("batch")


def stored_alerts(spark: SparkSession, out: str) -> DataFrame:
    return spark.read.schema("win_start timestamp, pattern string, score double, batch long").parquet(f"{out}/alerts").drop("batch")
