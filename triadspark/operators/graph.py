"""Digraphs as DataFrames: one row per adjacent pair, keyed so that many graphs (intervals, slices) go through one job."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codes import MOST, flip_dir, pack
from .keep import drop_kept, keep, shuffles_removed


@dataclass
class Digraph:
    """dyads(keys, lo, hi, dir) with lo<hi; sizes(keys, n); vertices(keys, id) or None; on_disk: dyads are a kept table already."""

    dyads: DataFrame
    sizes: DataFrame
    keys: list[str] = field(default_factory=list)
    vertices: DataFrame | None = None
    on_disk: bool = False


def as_dyads(arcs: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Loops go, parallel arcs merge, opposite arcs make code 3; map-side bit_or keeps the shuffle at one row per pair and task."""
    keys = keys or []
    code = F.when(F.col("src") < F.col("dst"), 1).otherwise(2)
    return (arcs.where("src <> dst").select(*keys, F.least("src", "dst").alias("lo"), F.greatest("src", "dst").alias("hi"), code.alias("c"))
            .groupBy(*keys, "lo", "hi").agg(F.bit_or("c").cast("int").alias("dir")))


def as_digraph(arcs: DataFrame, vertices: DataFrame | None = None, keys: list[str] | None = None, sizes: DataFrame | None = None) -> Digraph:
    """arcs(keys, src, dst); vertices(keys, id) default to the arcs' ends; sizes(keys, n) override counting."""
    keys = keys or []
    if vertices is None:
        vertices = arcs.select(*keys, F.explode(F.array("src", "dst")).alias("id")).distinct()
    if sizes is None:
        sizes = vertices.groupBy(*keys).agg(F.count("*").alias("n"))
    return Digraph(as_dyads(arcs, keys), sizes, keys, vertices)


def dropped_arcs(arcs: DataFrame) -> DataFrame:
    """(n_arcs, n_loops, n_repeats)."""
    per = arcs.groupBy("src", "dst").agg(F.count("*").alias("c"))
    return per.agg(F.sum("c").alias("n_arcs"), F.sum(F.when(F.col("src") == F.col("dst"), F.col("c")).otherwise(0)).alias("n_loops"), F.sum(F.when(F.col("src") != F.col("dst"), F.col("c") - 1).otherwise(0)).alias("n_repeats"))


def both_ways(g: Digraph) -> DataFrame:
    """(keys, id, nbr, code): every pair from both ends, code seen from id."""
    ends = F.array(F.struct(F.col("lo").alias("id"), F.col("hi").alias("nbr"), F.col("dir").alias("code")), F.struct(F.col("hi").alias("id"), F.col("lo").alias("nbr"), flip_dir(F.col("dir")).alias("code")))
    return g.dyads.select(*g.keys, F.explode(ends).alias("e")).select(*g.keys, "e.*")


def degrees(g: Digraph) -> DataFrame:
    """(keys, id, a, b, m, d): out-only, in-only, mutual neighbours and all."""
    c = F.col("code")
    return both_ways(g).groupBy(*g.keys, "id").agg(F.count_if(c == 1).alias("a"), F.count_if(c == 2).alias("b"), F.count_if(c == 3).alias("m"), F.count("*").alias("d"))


def kept(g: Digraph) -> Digraph:
    """The graph with its pairs written, once only."""
    return g if g.on_disk else Digraph(keep(g.dyads, "dyads"), g.sizes, g.keys, g.vertices, True)


def settled(g: Digraph) -> tuple[Digraph, DataFrame]:
    """The graph with its pairs written once, and its degrees, written too: forms that use both several times read the sources once."""
    g = kept(g)
    return g, keep(degrees(g), "degrees")


def packed_adjacency(g: Digraph) -> DataFrame:
    """(keys, id, deg, packed): sorted neighbours with two direction bits each.  Ids beyond 62 bits raise an error: see `dense`."""
    return both_ways(g).groupBy(*g.keys, "id").agg(F.count("*").cast("int").alias("deg"), F.sort_array(F.collect_list(pack(F.col("nbr"), F.col("code")))).alias("packed"))


def relabel(vertices: DataFrame, parts: int | None = None) -> DataFrame:
    """(id, rank): dense 0-based ranks in the order of ids of any kind; ranges first, then one offset a range, so no window spans all vertices."""
    n = parts or int(vertices.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    r = keep(vertices.select("id").distinct().repartitionByRange(n, "id").withColumn("part", F.spark_partition_id()), "ranges")
    off = r.groupBy("part").agg(F.count("*").alias("c")).select("part", (F.sum("c").over(Window.orderBy("part")) - F.col("c")).alias("off"))  # one row a range
    return r.join(F.broadcast(off), "part").select("id", (F.col("off") + F.row_number().over(Window.partitionBy("part").orderBy("id")) - 1).cast("long").alias("rank"))


def dense(g: Digraph) -> tuple[Digraph, DataFrame]:
    """The graph on ranks instead of ids (in the same order), and the names (id, rank)."""
    names = keep(relabel(g.vertices), "names")
    d = _ranked(_ranked(g.dyads, names, "lo"), names, "hi")
    return Digraph(d.select("lo", "hi", "dir"), g.sizes, [], names.select(F.col("rank").alias("id"))), names


def _ranked(dyads: DataFrame, names: DataFrame, end: str) -> DataFrame:
    return dyads.join(names.toDF(end, "_rank"), end).withColumn(end, F.col("_rank")).drop("_rank")


def dense_in_steps(g: Digraph) -> tuple[Digraph, DataFrame]:
    """`dense` for graphs whose pairs fill the disk: pairs are written after each step, and what a step has read is deleted, so no two shuffles of pairs are there at once."""
    spark, before, d = g.dyads.sparkSession, [], g.dyads
    with shuffles_removed(spark):
        names = keep(relabel(g.vertices), "names")
        for step in (lambda x: x, lambda x: _ranked(x, names, "lo"), lambda x: _ranked(x, names, "hi").select("lo", "hi", "dir")):
            d = keep(step(d), "dyads", now := [])
            for path in before:
                drop_kept(spark, path)
            before = now
    return Digraph(d, g.sizes, [], names.select(F.col("rank").alias("id")), True), names


def with_labels(df: DataFrame, names: DataFrame, columns: list[str]) -> DataFrame:
    """df with the ranks in `columns` replaced by the ids they stand for."""
    for c in columns:
        df = df.join(names.select(F.col("rank").alias(c), F.col("id").alias("_id")), c).withColumn(c, F.col("_id")).drop("_id")
    return df


def fits_packing(g: Digraph) -> bool:
    """Whether all ids are integers that two direction bits can be added to."""
    if dict(g.dyads.dtypes)["lo"] not in ("tinyint", "smallint", "int", "bigint"):
        return False
    r = g.dyads.agg(F.min("lo").alias("a"), F.max("hi").alias("b")).first()  # one row
    return r.a is None or (r.a >= -MOST and r.b < MOST)


def packable(g: Digraph) -> Digraph:
    """The graph itself if its ids can be packed, else the graph on ranks: for results that name no vertex."""
    return g if fits_packing(g) else dense(g)[0]


def to_csr(g: Digraph) -> tuple[DataFrame, DataFrame]:
    """(offsets(id, start, deg), edges(pos, packed)): the flat two-array layout."""
    adj = packed_adjacency(g).select("id", "deg", "packed")
    order = relabel(adj.select("id")).join(adj, "id")
    span = 1024
    block = order.withColumn("block", F.floor(F.col("rank") / span))
    tot = block.groupBy("block").agg(F.sum("deg").alias("t"))
    base = tot.select("block", (F.sum("t").over(Window.orderBy("block")) - F.col("t")).alias("b"))
    starts = block.join(base, "block").select("id", (F.col("b") + F.sum("deg").over(Window.partitionBy("block").orderBy("rank")) - F.col("deg")).alias("start"), "deg", "packed")
    edges = starts.select("start", F.posexplode("packed")).select((F.col("start") + F.col("pos")).alias("pos"), F.col("col").alias("packed"))
    return starts.select("id", "start", "deg"), edges


def induced(g: Digraph, subset: DataFrame) -> Digraph:
    """The sub-graph on the ids of subset."""
    s = subset.select("id").distinct()
    d = g.dyads.join(s.withColumnRenamed("id", "lo"), "lo", "left_semi").join(s.withColumnRenamed("id", "hi"), "hi", "left_semi")
    return Digraph(d, s.agg(F.count("*").alias("n")), [], s)


def isolated(g: Digraph) -> DataFrame:
    return g.vertices.join(both_ways(g).select(*g.keys, "id").distinct(), [*g.keys, "id"], "left_anti")
