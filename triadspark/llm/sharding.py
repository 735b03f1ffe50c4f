"""Balanced shards by global byte-size prefix sums.

Rows are dealt by ranges of doc_id; each range's total goes through one small prefix sum, rows add their own sum inside the range.
The 40 (or n) cuts lie at equal byte targets, a row goes where its middle byte lies, so shards are contiguous in doc_id and differ by at most
about one row's size from their target.  Only (doc_id, size, checksum) is moved.

Edge cases: null text has no bytes, only the fixed cost of a row.  A null doc_id sorts first.  Rows of one doc_id are ordered by checksum and size; equal
rows are interchangeable.  Equal texts are not kept together: the law is about bytes.  An empty table gives no rows; shards may be empty
when there are fewer rows than shards.  Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import slim, stored, table


def byte_shards(docs: DataFrame, shards: int = 40, row_cost: int = 16) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every row of docs."""
    raw = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    small = slim(docs).select("doc_id", (F.octet_length(raw) + row_cost).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"))
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = stored(small.repartitionByRange(n, "doc_id").withColumn("part", F.spark_partition_id()), "shard-ranges")
    tot = ranged.groupBy("part").agg(F.sum("size").alias("bytes"), F.count("*").alias("rows"))
    before, all_ = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    base = tot.select("part", F.coalesce(F.sum("bytes").over(before), F.lit(0)).alias("b0"), F.coalesce(F.sum("rows").over(before), F.lit(0)).alias("r0"), F.sum("bytes").over(all_).alias("total"))
    inside = Window.partitionBy("part").orderBy("doc_id", "text_crc32", "size").rowsBetween(Window.unboundedPreceding, 0)
    placed = (ranged.withColumn("upto", F.sum("size").over(inside)).withColumn("no", F.row_number().over(Window.partitionBy("part").orderBy("doc_id", "text_crc32", "size")))
              .join(base, "part").select("doc_id", "size", "text_crc32", (F.col("r0") + F.col("no") - 1).alias("row"),
                                         F.expr(f"cast(least({shards - 1}, ((2 * (b0 + upto) - size) * {shards}) div (2 * total)) as int)").alias("shard")))
    placed = stored(placed, "shard-rows")
    first = placed.groupBy("shard").agg(F.min("row").alias("first"))  # at most `shards` rows
    return placed.join(F.broadcast(first), "shard").select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("row") - F.col("first")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def write_shards(docs: DataFrame, path: str, shards: int = 40) -> None:
    """Writes the documents as one folder a shard."""
    where = byte_shards(docs, shards).select("doc_id", "shard")
    docs.join(where, "doc_id").repartition(shards, "shard").write.partitionBy("shard").parquet(path)


def op9_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_shards(table(spark, sf_dir, "documents"))


QUERIES = {"op9_sharding": op9_sharding}
