"""Saved graphs and censuses, the shared folder, and a Python data source of random digraphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.graph import Digraph
from ..operators.keep import temp_path


def save_graph(g: Digraph, path: str, parts: int = 64) -> None:
    """Pairs in hash parts of their smaller end, sorted inside; vertices and sizes beside them."""
    g.dyads.repartition(parts, *g.keys, "lo").sortWithinPartitions(*g.keys, "lo", "hi").write.mode("overwrite").parquet(f"{path}/dyads")
    g.sizes.write.mode("overwrite").parquet(f"{path}/sizes")
    if g.vertices is not None:
        g.vertices.write.mode("overwrite").parquet(f"{path}/vertices")


def open_graph(spark: SparkSession, path: str, keys: list[str] | None = None, with_vertices: bool = True) -> Digraph:
    read = lambda x: spark.read.parquet(f"{path}/{x}")
    return Digraph(read("dyads"), read("sizes"), keys or [], read("vertices") if with_vertices else None)


def save_bucketed(g: Digraph, name: str, buckets: int = 64) -> None:
    """Pairs as a table bucketed by the smaller end: later joins on lo need no shuffle of this side."""
    g.dyads.write.mode("overwrite").bucketBy(buckets, "lo").sortBy("lo", "hi").saveAsTable(name)


def save_census(census: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite") -> None:
    census.write.mode(mode).format(fmt).save(path)


class DigraphSource(DataSource):
    """spark.read.format("digraph"): options n, m, exponent (of out-degrees; none = uniform), seed, parts; repeatable per part."""

    @classmethod
    def name(cls) -> str:
        return "digraph"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> DigraphReader:
        return DigraphReader(self.options)


class DigraphReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.m = int(options["n"]), int(options["m"])
        self.exponent = float(options["exponent"]) if options.get("exponent") else None
        self.seed, self.parts = int(options.get("seed", 42)), max(1, int(options.get("parts", 8)))

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa

        i = partition.value
        left = self.m * (i + 1) // self.parts - self.m * i // self.parts
        r = np.random.default_rng([self.seed, i])
        while left > 0:
            k = min(left, 1 << 16)
            u = r.random(k)
            if self.exponent is None:
                src = np.floor(u * self.n)
            else:  # rank weights r^(-1/(exponent-1)) give that exponent of degrees
                t = 1 - 1 / (self.exponent - 1)
                src = np.minimum(self.n - 1, np.floor((u * ((self.n + 1) ** t - 1) + 1) ** (1 / t)) - 1)
            yield pa.RecordBatch.from_arrays([pa.array(src.astype(np.int64)), pa.array(r.integers(0, self.n, k))], names=["src", "dst"])
            left -= k


def register_sources(spark: SparkSession) -> None:
    spark.dataSource.register(DigraphSource)


def event_log_utilisation(spark: SparkSession, path: str, cores: int, every: int = 10) -> DataFrame:
    """(at, cpu_seconds, utilisation) per interval of seconds: executor CPU time of finished tasks, spread evenly over their run."""
    t = spark.read.text(path).where(F.get_json_object("value", "$.Event") == "SparkListenerTaskEnd")
    num = lambda p: F.get_json_object("value", p).cast("long")
    t = t.select((num("$['Task Info']['Launch Time']") / 1000).alias("a"), (num("$['Task Info']['Finish Time']") / 1000).alias("b"), (num("$['Task Metrics']['Executor CPU Time']") / 1e9).alias("cpu")).where("cpu is not null")
    x = t.withColumn("at", F.explode(F.sequence(F.floor(F.col("a") / every) * every, F.floor(F.col("b") / every) * every, F.lit(every).cast("long"))))
    share = F.when(F.col("b") > F.col("a"), (F.least("b", F.col("at") + every) - F.greatest("a", F.col("at"))) / (F.col("b") - F.col("a"))).otherwise(1.0)
    return x.groupBy("at").agg(F.sum(F.col("cpu") * share).alias("cpu_seconds")).withColumn("utilisation", F.col("cpu_seconds") / (cores * every))
