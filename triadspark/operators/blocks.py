"""Bounded-memory kernels: dense tiles of the class matrices, colour blocks of triangles, and the sampled census."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codes import CLOSED, FOLD, LABELS, fold_code
from .census import census_scalable, matrix_counts, triangles
from .graph import Digraph, both_ways, kept, relabel
from .keep import shuffles_removed


def _tile_products(block: int):
    def run(batches):
        names = "CRMZ"
        out = np.zeros((3, 3, 4), np.int64)

        def tile(cells):
            m = np.zeros(block * block, np.int8)
            if cells is not None:
                v = np.asarray(cells, np.int64)
                m[v >> 2] = v & 3
            return m.reshape(block, block)

        for batch in batches:
            for r in batch.to_pylist():
                left, right, ends = tile(r["xs"]), tile(r["ys"]), tile(r["ws"])
                off = ~np.eye(block, dtype=bool) if r["bi"] == r["bj"] else np.ones((block, block), bool)
                for x in range(3):
                    for y in range(3):
                        p = (left == x + 1).astype(np.float32) @ (right == y + 1).astype(np.float32)
                        for z in range(4):
                            out[x, y, z] += int(p[(ends == (z + 1) % 4) & off].sum(dtype=np.float64))
        keys = [names[x] + names[y] + names[z] for x in range(3) for y in range(3) for z in range(4)]
        yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(out.ravel())], names=["k", "p"])

    return run


def census_matrix_blocks(g: Digraph, block: int = 256) -> DataFrame:
    """The matrix census over tiles: only tiles with entries exist; tile (i, k) meets tile (k, j), each task holds three tiles at a time."""
    r = relabel(g.vertices)
    e = both_ways(g).join(r.toDF("id", "ri"), "id").join(r.toDF("nbr", "rj"), "nbr")
    cell = F.shiftleft((F.col("ri") % block) * block + F.col("rj") % block, 2).bitwiseOR(F.col("code").cast("long"))
    tiles = e.groupBy(F.floor(F.col("ri") / block).alias("bi"), F.floor(F.col("rj") / block).alias("bj")).agg(F.collect_list(cell).alias("cells"))
    x = tiles.select("bi", F.col("bj").alias("bk"), F.col("cells").alias("xs")).join(tiles.select(F.col("bi").alias("bk"), "bj", F.col("cells").alias("ys")), "bk")
    x = x.join(tiles.withColumnRenamed("cells", "ws"), ["bi", "bj"], "left").select("bi", "bj", "xs", "ys", "ws")
    return matrix_counts(g, x.mapInArrow(_tile_products(block), "k string, p long").groupBy("k").agg(F.sum("p").alias("p")))


def _block_triangles(pdf: pd.DataFrame) -> pd.DataFrame:
    """Triangles of one colour block by type, each counted in the block of exactly its colours."""
    ids, at = np.unique(np.concatenate([pdf.lo.to_numpy(), pdf.hi.to_numpy()]), return_inverse=True)
    n, p = len(ids), len(pdf)
    lo, hi, code = at[:p], at[p:], pdf.dir.to_numpy().astype(np.int64)
    colour = np.zeros(n, np.int64)
    colour[lo], colour[hi] = pdf.cl.to_numpy(), pdf.ch.to_numpy()
    key = lo * n + hi
    o = np.argsort(key)
    key, closing = key[o], code[o]
    deg = np.bincount(at, minlength=n)
    up = (deg[lo] < deg[hi]) | ((deg[lo] == deg[hi]) & (lo < hi))
    tail, head, c = np.where(up, lo, hi), np.where(up, hi, lo), np.where(up | (code == 3), code, 3 - code)
    o = np.lexsort((head, tail))
    tail, head, c = tail[o], head[o], c[o]
    run_end = np.searchsorted(tail, tail, "right")
    reach = run_end - np.arange(p) - 1  # later heads of the same tail
    count = np.zeros(17, np.int64)
    want = np.array([int(pdf.c1.iloc[0]), int(pdf.c2.iloc[0]), int(pdf.c3.iloc[0])])
    fold = np.array(FOLD)
    ends, s = np.cumsum(reach), 0
    while s < p:
        stop = max(s + 1, int(np.searchsorted(ends, (ends[s - 1] if s else 0) + 2_000_000, "right")))
        k = reach[s:stop]
        i = np.repeat(np.arange(s, stop), k)
        j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(k) - k, k)
        q = head[i] * n + head[j]
        f = np.minimum(np.searchsorted(key, q), p - 1)
        hit = key[f] == q
        i, j, f = i[hit], j[hit], f[hit]
        own = (np.sort(np.stack([colour[tail[i]], colour[head[i]], colour[head[j]]]), axis=0) == want[:, None]).all(axis=0)
        count += np.bincount(fold[c[i[own]] + 4 * c[j[own]] + 16 * closing[f[own]]], minlength=17)
        s = stop
    no = np.flatnonzero(count)
    return pd.DataFrame({"no": no.astype(np.int32), "c": count[no]})


def colours_for(pairs: int, block_pairs: int = 500_000) -> int:
    """Colours for which a block holds about `block_pairs` pairs."""
    return max(1, math.ceil(math.sqrt(3 * pairs / block_pairs)))


def enough_colours(g: Digraph, block_pairs: int = 500_000) -> int:
    return colours_for(g.dyads.count(), block_pairs)


def colour_counts(g: Digraph, colours: int | None = None) -> DataFrame:
    """(no, c) of closed types: vertices are hashed to colours, a pair goes to each of the blocks its colours belong to, wedges never
    leave their block.  A block holds about 3 p / colours^2 pairs; without a number, colours follow from the number of pairs.
    There are as many rounds as colours, a pair goes to one block in each, and a round's shuffle is deleted when it ends: p rows at once, not colours * p."""
    colours = colours or enough_colours(g)
    hue = lambda x: F.pmod(F.xxhash64(x), F.lit(colours)).cast("int")
    pairs = kept(g).dyads.select("lo", "hi", "dir", hue("lo").alias("cl"), hue("hi").alias("ch"))

    def counted(r: int) -> DataFrame:
        """The blocks whose colours add up to r, modulo their number."""
        d = pairs.withColumn("s", F.array_sort(F.array("cl", "ch", F.pmod(F.lit(r) - F.col("cl") - F.col("ch"), F.lit(colours)))))
        d = d.select("lo", "hi", "dir", "cl", "ch", *(F.col("s")[i].alias(f"c{i + 1}") for i in range(3)))
        return d.groupBy("c1", "c2", "c3").applyInPandas(_block_triangles, "no int, c long").groupBy("no").agg(F.sum("c").alias("c"))

    if colours == 1:
        return counted(0)
    spark = g.dyads.sparkSession
    with shuffles_removed(spark):
        rows = [(x.no, x.c) for r in range(colours) for x in counted(r).collect()]  # 7 a round at most
    return spark.createDataFrame(rows, "no int, c long").groupBy("no").agg(F.sum("c").alias("c"))


def census_colour_blocks(g: Digraph, colours: int | None = None) -> DataFrame:
    """The scalable census with triangles from colour blocks; for graphs whose wedges outgrow a shuffle."""
    g = kept(g)
    return census_scalable(g, closed=colour_counts(g, colours))


def sample_dyads(g: Digraph, rate: float, seed: int = 42) -> Digraph:
    """Keeps each adjacent pair with probability rate, by hash, so repeated runs keep the same pairs."""
    keep = F.pmod(F.xxhash64("lo", "hi", F.lit(seed)), F.lit(1 << 30)) < F.lit(int(rate * (1 << 30)))
    return Digraph(g.dyads.where(keep), g.sizes, g.keys, g.vertices)


def census_sampled(g: Digraph, rate: float, seed: int = 42) -> DataFrame:
    """Estimated census: triangles of sampled pairs over rate^3, everything else by exact degree sums.  Unbiased; wedges cost rate^2.

    std_error: of closed types from the number of triangles and of triangles of one type that share a pair, T (1 / q^3 - 1) + 2 K (1 / q - 1), both
    as estimated; of the others the sum of the closed types' errors with the weights they have in them, an upper bound."""
    tri = triangles(sample_dyads(g, rate, seed)).withColumn("no", fold_code(F.col("code"))).persist()
    seen = tri.groupBy("no").agg(F.count("*").alias("c"))
    side = lambda a, b: F.struct(F.least(a, b).alias("lo"), F.greatest(a, b).alias("hi"))
    per = tri.select("no", F.explode(F.array(side("t", "x"), side("t", "y"), side("x", "y"))).alias("p")).groupBy("no", "p").agg(F.count("*").alias("k"))
    shared = per.groupBy("no").agg(F.sum(F.col("k") * (F.col("k") - 1) / 2).alias("k"))
    var = F.col("c") / rate**3 * (1 / rate**3 - 1) + 2 * F.coalesce("k", F.lit(0.0)) / rate**5 * (1 / rate - 1)
    found = {r.no: (round(r.c / rate**3), math.sqrt(max(r.v, 0.0))) for r in seen.join(shared, "no", "left").select("no", "c", var.alias("v")).collect()}  # 7 rows at most
    tri.unpersist()
    error = {x: found.get(LABELS.index(x) + 1, (0, 0.0))[1] for x in CLOSED}
    weight = {"021D": {"030T": 1, "120D": 1}, "021U": {"030T": 1, "120U": 1}, "021C": {"030T": 1, "030C": 3, "120C": 1}, "111D": {"120D": 2, "120C": 1, "210": 1}, "111U": {"120U": 2, "120C": 1, "210": 1},
              "201": {"210": 1, "300": 3}, "012": {"030T": 3, "030C": 3, "120D": 2, "120U": 2, "120C": 2, "210": 1}, "102": {"120D": 1, "120U": 1, "120C": 1, "210": 2, "300": 3}, "003": dict.fromkeys(CLOSED, 1)}
    errors = [(x, round(error[x] if x in error else sum(w * error[y] for y, w in weight[x].items()), 6)) for x in LABELS]
    spark = g.dyads.sparkSession
    closed = spark.createDataFrame([(no, c) for no, (c, _) in found.items()], "no int, c long")
    return census_scalable(g, closed=closed).join(F.broadcast(spark.createDataFrame(errors, "triad_type string, std_error double")), "triad_type")


def small_graph_census(g: Digraph, most: int = 20_000) -> DataFrame:
    """The census of many small graphs, one a key: triangles of a key's pairs in one kernel call; keys with more than `most` pairs go the relational way."""
    size = g.dyads.groupBy(*g.keys).agg(F.count("*").alias("_p"))
    sized = g.dyads.join(size, g.keys)
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in g.dyads.schema if f.name in g.keys) + ", no int, c long"

    def count(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        out = _block_triangles(pdf.assign(cl=0, ch=0, c1=0, c2=0, c3=0))
        for i, k in enumerate(g_keys):
            out.insert(i, k, pd.Series([key[i]] * len(out), dtype=pdf[k].dtype))
        return out

    g_keys = list(g.keys)
    small = sized.where(F.col("_p") <= most).drop("_p").groupBy(*g.keys).applyInPandas(count, schema)
    large = triangles(Digraph(sized.where(F.col("_p") > most).drop("_p"), g.sizes, g.keys)).groupBy(*g.keys, fold_code(F.col("code")).alias("no")).agg(F.count("*").alias("c"))
    return census_scalable(g, closed=small.unionByName(large))
