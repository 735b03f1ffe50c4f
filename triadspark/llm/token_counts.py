"""Exact histogram of encoded lengths and what it answers.

Every text is encoded once; only (length, count) leaves the tasks.  Suffix sums over the histogram give, for each context limit,
documents and tokens at or beyond it, tokens when longer documents are truncated, and quantiles.  The sums run in two levels (blocks
of lengths, then inside a block), so no window spans all rows.

Edge cases: null or empty text has length 0.  An empty table gives an empty histogram.  Rows count as often as they occur; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import slim, stored, table
from .encoding import library_cache
from .textkernel import pieces

SPAN = 4096


def _lengths(path: str):
    def run(batches):
        held: dict[int, int] = {}
        for batch in batches:
            for t in pieces(batch, "text"):
                cache = library_cache(path)
                chunk, counts = cache.chunks(t["text"])
                sums = np.concatenate(([0], np.cumsum(cache.size[chunk])))
                ends = np.cumsum(counts)
                for k, n in zip(*np.unique(sums[ends] - sums[ends - counts], return_counts=True), strict=True):
                    held[int(k)] = held.get(int(k), 0) + int(n)
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int64()), pa.array(list(held.values()), pa.int64())], names=["n_tokens", "n_docs"])

    return run


def length_histogram(docs: DataFrame, tokenizer: str) -> DataFrame:
    """(n_tokens, n_docs), one row a length that occurs."""
    return slim(docs).mapInArrow(_lengths(tokenizer), "n_tokens long, n_docs long").groupBy("n_tokens").agg(F.sum("n_docs").alias("n_docs"))


def context_answers(hist: DataFrame) -> DataFrame:
    """Suffix sums for each length L: docs_from and tokens_from (documents of L tokens or more), truncated_tokens (all documents cut at
    L), docs_upto_share (which quantile L is)."""
    h = hist.withColumn("span", F.floor(F.col("n_tokens") / SPAN))
    tot = h.groupBy("span").agg(F.sum("n_docs").alias("d"), F.sum(F.col("n_docs") * F.col("n_tokens")).alias("t"))
    after = Window.orderBy(F.desc("span")).rowsBetween(Window.unboundedPreceding, -1)
    all_ = Window.partitionBy()
    spans = tot.select("span", F.coalesce(F.sum("d").over(after), F.lit(0)).alias("d_after"), F.coalesce(F.sum("t").over(after), F.lit(0)).alias("t_after"), F.sum("d").over(all_).alias("n_all"), F.sum("t").over(all_).alias("t_all"))
    inside = Window.partitionBy("span").orderBy(F.desc("n_tokens")).rowsBetween(Window.unboundedPreceding, 0)
    x = h.join(F.broadcast(spans), "span").select("n_tokens", "n_docs", (F.sum("n_docs").over(inside) + F.col("d_after")).alias("docs_from"),
                                     (F.sum(F.col("n_docs") * F.col("n_tokens")).over(inside) + F.col("t_after")).alias("tokens_from"), "n_all", "t_all")
    return x.select("n_tokens", "n_docs", "docs_from", "tokens_from", (F.col("t_all") - F.col("tokens_from") + F.col("n_tokens") * F.col("docs_from")).alias("truncated_tokens"),
                    F.round((F.col("n_all") - F.col("docs_from") + F.col("n_docs")) / F.col("n_all"), 9).alias("docs_upto_share"))


def length_quantile(hist: DataFrame, q: float) -> DataFrame:
    """Smallest length that at least a share q of the documents doesn't exceed."""
    return context_answers(hist).where(F.col("docs_upto_share") >= q).agg(F.min("n_tokens").alias("n_tokens"))


def totals_at(hist: DataFrame, limits: list[int]) -> DataFrame:
    """(limit, docs_beyond, truncated_tokens) for any context limits, occurring lengths or not."""
    if not limits:
        return hist.sparkSession.createDataFrame([], "context_limit long, docs_beyond long, truncated_tokens long")
    each = hist.select("n_tokens", "n_docs", F.explode(F.array(*(F.lit(int(x)).cast("long") for x in limits))).alias("context_limit"))
    return each.groupBy("context_limit").agg(F.sum(F.when(F.col("n_tokens") > F.col("context_limit"), F.col("n_docs")).otherwise(0)).alias("docs_beyond"),
                                             F.sum(F.least("n_tokens", "context_limit") * F.col("n_docs")).alias("truncated_tokens"))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return context_answers(stored(length_histogram(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json")), "length-histogram"))


QUERIES = {"op5_token_counts": op5_token_counts}
