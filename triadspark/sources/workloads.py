"""Experiment graphs on the given tables: arcs (src, dst[, ts]) and vertex sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.graph import Digraph, as_digraph, dense, dense_in_steps


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_arcs(spark: SparkSession, path: str, fmt: str = "csv", sep: str = "\t", src: str = "_c0", dst: str = "_c1") -> DataFrame:
    """Edge lists in text, CSV, JSON, ORC or Parquet."""
    r = spark.read.option("sep", sep).option("comment", "#") if fmt == "csv" else spark.read
    return r.format(fmt).load(path).select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))


def random_digraph(spark: SparkSession, n: int, m: int, exponent: float | None = None, seed: int = 42) -> DataFrame:
    """m arcs over n ids; with an exponent (above 1, not 2), out-degrees follow that power law: the sender of rank r is drawn with weight
    r^(-1/(exponent-1)), by inverse distribution function."""
    u = F.rand(seed)
    if exponent is None:
        src = F.floor(u * n)
    else:
        t = 1 - 1 / (exponent - 1)
        src = F.least(F.lit(n - 1), F.floor(F.pow(u * ((n + 1) ** t - 1) + 1, F.lit(1 / t))) - 1)
    return spark.range(m).select(src.cast("long").alias("src"), F.floor(F.rand(seed + 1) * n).cast("long").alias("dst"))


def lineitem_arcs(spark, d, exponent: float) -> DataFrame:
    """An arc a row of lineitem to a receiver of its own, from one of a tenth as many senders whose out-degrees follow a power law as in `random_digraph`;
    a row's key, multiplied into 32 bits, stands for its random number."""
    x = load(spark, d, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).cast("long").alias("k"))
    n, t = F.col("n"), 1 - 1 / (exponent - 1)
    u = (F.pmod(F.pmod("k", F.lit(2147483647)) * F.lit(2654435761), F.lit(4294967296)) + F.lit(0.5).cast("double")) / F.lit(4294967296)
    src = F.least(n - 1, F.floor(F.pow(u * (F.pow(n + 1, F.lit(t)) - 1) + 1, F.lit(1 / t))) - 1)
    return x.crossJoin(F.broadcast(x.agg(F.floor(F.count("*") / 10).alias("n")))).select(src.cast("long").alias("src"), (n + F.col("k")).alias("dst"))


def citation_arcs(spark, d):
    o, l = load(spark, d, "orders"), load(spark, d, "lineitem")
    x = l.select("l_orderkey", "l_partkey").distinct().join(o.select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    w = Window.partitionBy("l_partkey").orderBy("o_orderdate", "o_orderkey")
    return x.select(F.col("o_orderkey").alias("src"), F.lag("o_orderkey").over(w).alias("dst")).where("dst is not null")


def citation_graph(spark, d) -> Digraph:
    return as_digraph(citation_arcs(spark, d), load(spark, d, "orders").select(F.col("o_orderkey").alias("id")))


def social_arcs(spark, d):
    o, l = load(spark, d, "orders"), load(spark, d, "lineitem")
    x = l.select("l_orderkey", "l_partkey", "l_linenumber").join(o.select("o_orderkey", "o_orderdate", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    w = Window.partitionBy("l_partkey").orderBy("o_orderdate", "l_orderkey", "l_linenumber")
    return x.select(F.col("o_custkey").alias("src"), F.lead("o_custkey").over(w).alias("dst")).where("dst is not null")


def social_graph(spark, d) -> Digraph:
    return as_digraph(social_arcs(spark, d), load(spark, d, "customer").select(F.col("c_custkey").alias("id")))


def web_arcs(spark, d):
    p = load(spark, d, "pages").select(F.concat(F.lit("p"), F.col("page_id").cast("string")).alias("page"), F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)).alias("links"))
    out = p.select(F.col("page").alias("src"), F.explode("links").alias("dst"))
    step = p.select(F.explode(F.arrays_zip(F.expr("slice(links, 1, greatest(size(links) - 1, 0))").alias("s"), F.expr("slice(links, 2, greatest(size(links) - 1, 0))").alias("t"))).alias("e")).select(F.col("e.s").alias("src"), F.col("e.t").alias("dst"))
    return out.unionByName(step.where("dst is not null")), p.select(F.col("page").alias("id"))


def named_graph(arcs: DataFrame, vertices: DataFrame | None = None, steps: bool = False) -> tuple[Digraph, DataFrame]:
    """String ids to their ranks 0..n-1 through a table of the distinct names, so no two names can meet in one id; and that table (id, rank).
    Pairs are merged under their names first, so only adjacent pairs are joined to it; steps: with less disk, see `dense_in_steps`."""
    ends = arcs.select(F.explode(F.array("src", "dst")).alias("id"))
    v = (ends if vertices is None else ends.unionByName(vertices)).distinct()
    g, names = (dense_in_steps if steps else dense)(as_digraph(arcs, v))
    return Digraph(g.dyads, names.agg(F.count("*").alias("n")), [], g.vertices, g.on_disk), names


def web_graph(spark, d) -> Digraph:
    arcs, pages = web_arcs(spark, d)
    return named_graph(arcs, pages)[0]


def word_graph(spark, d, longest: int | None = None) -> Digraph:
    """Word to next word, whole texts of all documents; with longest, only of documents up to so many characters."""
    docs = load(spark, d, "documents")
    t = (docs if longest is None else docs.where(F.length("text") <= longest)).select(F.split(F.lower("text"), r"[^\p{L}]+").alias("w"))
    e = t.select(F.explode(F.arrays_zip(F.expr("slice(w, 1, greatest(size(w) - 1, 0))").alias("s"), F.expr("slice(w, 2, greatest(size(w) - 1, 0))").alias("t"))).alias("e"))
    return named_graph(e.select(F.col("e.s").alias("src"), F.col("e.t").alias("dst")).where("src <> '' and dst <> ''"), steps=True)[0]


def project_arcs(df: DataFrame, src: Column | str, dst: Column | str, ts: Column | str | None = None, *more: str) -> DataFrame:
    """Arcs (src, dst[, ts], further columns) out of any table; rows that lack an end go."""
    col = lambda c, name: (F.expr(c) if isinstance(c, str) else c).alias(name)
    out = df.select(col(src, "src"), col(dst, "dst"), *([col(ts, "ts")] if ts is not None else []), *more)
    return out.where("src is not null and dst is not null")


def between_times(arcs: DataFrame, start, end, ts: str = "ts") -> DataFrame:
    """Arcs from start on and before end; a plain comparison, so files' statistics prune what lies outside."""
    kind = arcs.schema[ts].dataType
    return arcs.where((F.col(ts) >= F.lit(start).cast(kind)) & (F.col(ts) < F.lit(end).cast(kind)))


def by_event_type(arcs: DataFrame, types: list[str]) -> DataFrame:
    return arcs.where(F.col("event_type").isin(*types))


def traffic_arcs(spark, d):
    """(src, dst, ts, event_type): sender to the integer in its properties."""
    return project_arcs(load(spark, d, "events"), "user_id", F.get_json_object("props", "$.k").cast("long"), "ts", "event_type")


def traffic_vertices(spark, d):
    return traffic_arcs(spark, d).select(F.explode(F.array("src", "dst")).alias("id")).distinct()


def traffic_graph(spark, d, day: str | None = None) -> Digraph:
    a = traffic_arcs(spark, d)
    return as_digraph((a if day is None else a.where(F.to_date("ts") == F.lit(day))).select("src", "dst"), traffic_vertices(spark, d))


def trade_graph(spark, d) -> Digraph:
    o, l = load(spark, d, "orders"), load(spark, d, "lineitem")
    x = l.select("l_orderkey", "l_suppkey", "l_returnflag").join(o.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    c, s = 2 * F.col("o_custkey"), 2 * F.col("l_suppkey") + 1
    back = F.col("l_returnflag") == "R"
    arcs = x.select(F.when(back, s).otherwise(c).alias("src"), F.when(back, c).otherwise(s).alias("dst"))
    v = load(spark, d, "customer").select((2 * F.col("c_custkey")).alias("id")).unionByName(load(spark, d, "supplier").select((2 * F.col("s_suppkey") + 1).alias("id")))
    return as_digraph(arcs, v)


def nation_graph(spark, d) -> Digraph:
    o, l, c, s = (load(spark, d, x) for x in ("orders", "lineitem", "customer", "supplier"))
    f = (l.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
         .groupBy(F.col("s_nationkey").cast("long").alias("i"), F.col("c_nationkey").cast("long").alias("j")).agg(F.sum("l_quantity").cast("long").alias("q")))
    back = f.select(F.col("i").alias("j"), F.col("j").alias("i"), F.col("q").alias("r"))
    arcs = f.join(back, ["i", "j"], "left").where("i <> j and q > 0 and q >= coalesce(r, 0)").select(F.col("i").alias("src"), F.col("j").alias("dst"))
    return as_digraph(arcs, load(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("id")))


def region_graph(spark, d) -> Digraph:
    """The social graph restricted to the customers of each region, one graph a region."""
    home = load(spark, d, "customer").join(load(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("n_regionkey").cast("long").alias("region"), F.col("c_custkey").alias("id"))
    a = social_arcs(spark, d).join(home.toDF("region", "src"), "src").join(home.toDF("region", "dst"), ["region", "dst"])
    return as_digraph(a.select("region", "src", "dst"), home, ["region"])


def _nearest(k: int):
    """Best k of each left vector against one packed block of right vectors, all rows of a block at once."""
    import numpy as np
    import pyarrow as pa

    def side(batch, r, ids, vecs):
        i, v = batch[ids][r].values.to_numpy(zero_copy_only=False), batch[vecs][r].values
        m = v.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(i), -1)
        return i, m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)

    def run(batches):
        for batch in batches:
            for r in range(batch.num_rows):
                (ia, a), (ib, b) = side(batch, r, "ia", "va"), side(batch, r, "ib", "vb")
                cos = np.round(a @ b.T, 9)
                cos[ia[:, None] == ib[None, :]] = -2
                least = np.partition(cos, -k, axis=1)[:, [-k]] if len(ib) > k else -2  # all ties of the k-th stay for now
                row, col = np.nonzero((cos >= least) & (cos > -2))
                o = np.lexsort((ib[col], -cos[row, col], row))
                row, col = row[o], col[o]
                heads = np.searchsorted(row, row)
                best = np.arange(len(row)) - heads < k
                row, col = row[best], col[best]
                yield pa.RecordBatch.from_arrays([pa.array(ia[row]), pa.array(ib[col]), pa.array(cos[row, col])], names=["src", "dst", "cos"])

    return run


def knn_arcs(spark, d, k: int = 5, rows: int = 1024) -> DataFrame:
    """vector to its k most similar by cosine, exact: blocks of vectors meet blocks, each meeting keeps k a vector; ties by id."""
    v = load(spark, d, "embeddings").where("vec_id is not null and embedding is not null").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))
    b = v.groupBy(F.floor(F.col("id") / rows).alias("b")).agg(F.collect_list("id").alias("i"), F.collect_list("v").alias("v"))  # ids are dense
    x = b.select(F.col("i").alias("ia"), F.col("v").alias("va")).crossJoin(b.select(F.col("i").alias("ib"), F.col("v").alias("vb")))
    near = x.mapInArrow(_nearest(k), "src long, dst long, cos double")
    return near.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("cos"), "dst"))).where(F.col("r") <= k).select("src", "dst")


def knn_graph(spark, d) -> Digraph:
    return as_digraph(knn_arcs(spark, d), load(spark, d, "embeddings").select(F.col("vec_id").alias("id")))
