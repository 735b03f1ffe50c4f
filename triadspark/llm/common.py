"""Session helpers of the corpus operators: tables, shared folder, sizes."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir.  Where none is set, an own one if there is no cluster, else an error."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not at:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        at = held.get() if held.isDefined() else None
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        at = "/tmp/checkpoints"
    return at.rstrip("/")


def stored(df: DataFrame, what: str, paths: list[str] | None = None) -> DataFrame:
    """Cuts the lineage: written once as Parquet in the shared folder, read back with the known schema; its place is added to `paths`."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if paths is not None:
        paths.append(path)
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def shuffles_removed(spark: SparkSession, key: str = "spark.sql.classic.shuffleDependency.fileCleanup.enabled") -> Iterator[None]:
    """Each query inside leaves no shuffle files once it has ended; else they stay until the driver happens to collect its garbage."""
    was = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.unset(key) if was is None else spark.conf.set(key, was)


def drop(spark: SparkSession, paths: list[str]) -> None:
    """Deletes stored tables that nothing reads any more."""
    for path in paths:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    paths.clear()


def narrowed(df: DataFrame, needed: DataFrame, key: str = "doc_id", n: int | None = None, words: int = 1 << 20) -> DataFrame:
    """The rows of df whose key may be among the needed ones, before they are shuffled: keys hash to bits, and a bitmap of the needed ones is
    broadcast, `words` words of 64 bits at most whatever the tables' size, fewer where only `n` keys are needed (32 to 64 bits a key then).  It travels as at most 1,024 rows,
    so the driver holds little more than the bits.  A full bitmap lets everything pass, and a join on the key itself has to follow."""
    words = words if n is None else min(words, max(1024, 1 << (n // 2).bit_length()))
    page = words // 1024
    if page >= 128:  # rows with what Spark puts around their bits fill a power of 2 of bytes, to which their table on the driver and on executors is doubled
        page -= 6 + page // 64
    slot = F.pmod(F.xxhash64(key), F.lit(64 * 1024 * page))
    word = F.shiftright(slot, 6)
    place = [F.floor(word / page).alias("_page"), F.pmod(word, F.lit(page)).cast("int").alias("_word"), slot.bitwiseAND(F.lit(63)).cast("int").alias("_bit")]
    few = needed.select(*place).groupBy("_page", "_word").agg(F.bit_or(F.expr("shiftleft(1L, _bit)")).alias("_bits"))
    # each page's words in order, gaps filled with zeros
    pages = few.groupBy("_page").agg(F.sort_array(F.collect_list(F.struct("_word", "_bits"))).alias("_w")).select("_page", F.expr(
        "flatten(transform(_w, (x, i) -> concat(array_repeat(0L, x._word - if(i = 0, -1, _w[greatest(i - 1, 0)]._word) - 1), array(x._bits))))").alias("_bits"))
    return df.select("*", *place).join(F.broadcast(pages), "_page").where(F.expr("(shiftright(get(_bits, _word), _bit) & 1) = 1")).drop("_page", "_word", "_bit", "_bits")


def hot_keys(df: DataFrame, keys: list[str], rows: int, per: int = 256) -> DataFrame:
    """(keys, c, s): keys with more than `per` rows and more than a thousandth of all `rows`, so a thousand of them at most, which may be
    broadcast; s is the number of shares to deal such a key's rows to."""
    per = max(per, -(-rows // 1000))
    return df.groupBy(*keys).agg(F.count("*").alias("c")).where(F.col("c") > per).withColumn("s", F.ceil(F.col("c") / per).cast("int"))


def input_bytes(df: DataFrame) -> int | None:
    """Catalyst's estimate for the scan under df, None where it has none."""
    n = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return n if n < 1 << 58 else None


def parts(df: DataFrame, per_part: int, least: int = 1) -> int:
    """How many buckets of about `per_part` input bytes each; follows the input, never below the session's partitions."""
    base = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    n = input_bytes(df)
    return max(least, base, -(-n // per_part) if n else 0)


def slim(docs: DataFrame, *names: str) -> DataFrame:
    """Only doc_id (long) and text (string), whatever else the table carries."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *names)
