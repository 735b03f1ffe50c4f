"""The triad census by every method: scalable (default), edge-driven in three forms, matrix, naive; 16 types or 64 states."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codes import CLOSED, LABELS, find_dir, flip_dir, fold_code, is_mutual, pack, triad_code, triad_total, type_label, unpack_id
from .graph import Digraph, both_ways, degrees, dense, kept, packable, packed_adjacency, relabel, settled
from .keep import keep, shuffles_removed
from .layout import weighted_units

BIG = "decimal(38,0)"


def _rows(wide: DataFrame, keys: list[str]) -> DataFrame:
    """One column per type to one row per type."""
    cells = F.explode(F.array(*(F.struct(F.lit(x).alias("triad_type"), F.lit(i + 1).alias("triad_no"), F.col(f"t{x}").cast(BIG).alias("n_triads")) for i, x in enumerate(LABELS))))
    return wide.select(*keys, cells.alias("c")).select(*keys, "c.*")


def oriented(g: Digraph, deg: DataFrame | None = None) -> DataFrame:
    """(keys, t, h, code): pairs from their end of smaller (degree, id); a hub's list shrinks to the root of the pairs."""
    d = (degrees(g) if deg is None else deg).select(*g.keys, "id", "d")
    x = g.dyads.join(d.withColumnsRenamed({"id": "lo", "d": "dl"}), [*g.keys, "lo"]).join(d.withColumnsRenamed({"id": "hi", "d": "dh"}), [*g.keys, "hi"])
    up = F.col("dl") <= F.col("dh")
    return x.select(*g.keys, F.when(up, F.col("lo")).otherwise(F.col("hi")).alias("t"), F.when(up, F.col("hi")).otherwise(F.col("lo")).alias("h"), F.when(up, F.col("dir")).otherwise(flip_dir(F.col("dir"))).alias("code"))


def triangles(g: Digraph, deg: DataFrame | None = None) -> DataFrame:
    """(keys, t, x, y, code): every closed triad once, code in the order (t, x, y) with x<y."""
    o = oriented(g, deg)
    w = o.select(*g.keys, "t", F.col("h").alias("x"), F.col("code").alias("cx")).join(o.select(*g.keys, "t", F.col("h").alias("y"), F.col("code").alias("cy")), [*g.keys, "t"]).where("x < y")
    return w.join(g.dyads.withColumnsRenamed({"lo": "x", "hi": "y"}), [*g.keys, "x", "y"]).select(*g.keys, "t", "x", "y", triad_code(F.col("cx"), F.col("cy"), F.col("dir")).alias("code"))


def ordered_triangles(g: Digraph, deg: DataFrame | None = None) -> DataFrame:
    """(u, v, w, code) with u<v<w and the state in that order."""
    t = triangles(g, deg)
    tx, ty, xy = (F.shiftright("code", k).bitwiseAND(F.lit(3)).cast("int") for k in (0, 2, 4))
    low, mid = F.col("t") < F.col("x"), F.col("t") < F.col("y")
    code = F.when(low, F.col("code")).when(mid, triad_code(flip_dir(tx), xy, ty)).otherwise(triad_code(xy, flip_dir(tx), flip_dir(ty)))
    return t.select(F.least("t", "x").alias("u"), F.when(low, F.col("x")).when(mid, F.col("t")).otherwise(F.col("y")).alias("v"), F.greatest("t", "y").alias("w"), code.cast("int").alias("code"))


def census_scalable(g: Digraph, closed: DataFrame | None = None) -> DataFrame:
    """Only triangles are enumerated; open, dyadic and null triads follow from degrees.  closed(keys, no, c): their counts from elsewhere."""
    k = g.keys
    g, deg = settled(g)
    if closed is None:
        closed = triangles(g, deg).groupBy(*k, fold_code(F.col("code")).alias("no")).agg(F.count("*").alias("c"))
    one = F.lit(1).cast("decimal(20,0)")
    a, b, m, d = (F.col(c).cast("decimal(18,0)") for c in "abmd")
    half = lambda x: F.sum((x * (x - one) / 2).cast(BIG))
    sums = deg.groupBy(*k).agg(half(a).alias("D"), half(b).alias("U"), F.sum(a * b).alias("C"), F.sum(m * b).alias("MI"), F.sum(m * a).alias("MO"), half(m).alias("MM"), F.sum(d * (a + b)).alias("DA"), F.sum(d * m).alias("DM"))
    pairs = g.dyads.groupBy(*k).agg(F.count_if(F.col("dir") < 3).alias("PA"), F.count_if(F.col("dir") == 3).alias("PM"))
    closed = closed.groupBy(*k).agg(*(F.sum(F.when(F.col("no") == LABELS.index(x) + 1, F.col("c"))).alias(f"T{x}") for x in CLOSED))
    if k:
        wide = g.sizes.join(sums, k, "left").join(pairs, k, "left").join(closed, k, "left")
    else:
        wide = g.sizes.crossJoin(F.broadcast(sums)).crossJoin(F.broadcast(pairs)).crossJoin(F.broadcast(closed))  # one row each
    z = lambda c: F.coalesce(F.col(c).cast(BIG), F.lit(0).cast(BIG))
    T = {x: z(f"T{x}") for x in CLOSED}
    n = F.col("n").cast("decimal(18,0)")
    out: dict[str, Column] = dict(T)
    out["021D"] = z("D") - T["030T"] - T["120D"]
    out["021U"] = z("U") - T["030T"] - T["120U"]
    out["021C"] = z("C") - T["030T"] - 3 * T["030C"] - T["120C"]
    out["111D"] = z("MI") - 2 * T["120D"] - T["120C"] - T["210"]
    out["111U"] = z("MO") - 2 * T["120U"] - T["120C"] - T["210"]
    out["201"] = z("MM") - T["210"] - 3 * T["300"]
    out["012"] = n * F.coalesce("PA", F.lit(0)).cast("decimal(18,0)") - z("DA") + 3 * (T["030T"] + T["030C"]) + 2 * (T["120D"] + T["120U"] + T["120C"]) + T["210"]
    out["102"] = n * F.coalesce("PM", F.lit(0)).cast("decimal(18,0)") - z("DM") + T["120D"] + T["120U"] + T["120C"] + 2 * T["210"] + 3 * T["300"]
    wide = wide.select(*k, "n", *(v.cast(BIG).alias(f"t{x}") for x, v in out.items()))
    rest = None
    for x in LABELS[1:]:
        rest = F.col(f"t{x}") if rest is None else rest + F.col(f"t{x}")
    return _rows(wide.withColumn("t003", (triad_total(F.col("n")) - rest).cast(BIG)), k)


# ---------------------------------------------------------------- edge-driven forms

def accumulate(rows: DataFrame, by: str = "triad_no", slots: int = 64, keep_slots: bool = False) -> DataFrame:
    """rows(u, v, by, c): private vectors per slot = hash of the pair, then their sum.  slots=1 is the single shared vector.  c may be negative; sums of 0 go."""
    part = rows.groupBy(F.pmod(F.xxhash64("u", "v"), F.lit(slots)).cast("int").alias("slot"), by).agg(F.sum("c").alias("c"))
    return (part if keep_slots else part.groupBy(by).agg(F.sum("c").alias("c"))).where("c <> 0")


def _finish(g: Digraph, counted: DataFrame) -> DataFrame:
    """Adds the null type by subtraction and absent types as 0."""
    wide = counted.groupBy().agg(*(F.coalesce(F.sum(F.when(F.col("triad_no") == i + 1, F.col("c").cast(BIG))), F.lit(0)).cast(BIG).alias(f"t{x}") for i, x in enumerate(LABELS) if i))
    rest = sum((F.col(f"t{x}") for x in LABELS[2:]), F.col(f"t{LABELS[1]}"))
    return _rows(g.sizes.crossJoin(F.broadcast(wide)).withColumn("t003", (triad_total(F.col("n")) - rest).cast(BIG)), [])


def connected_triads(g: Digraph) -> DataFrame:
    """(u, v, w, code) with u<v<w: every connected triad once, by 2-dyad paths and canonical choice; sum of d^2 rows."""
    s = both_ways(g)
    p = s.select(F.col("id").alias("k"), F.col("nbr").alias("i"), F.col("code").alias("ci")).join(s.select(F.col("id").alias("k"), F.col("nbr").alias("j"), F.col("code").alias("cj")), "k").where("i < j")
    x = p.join(g.dyads.select(F.col("lo").alias("i"), F.col("hi").alias("j"), F.col("dir").alias("cij")), ["i", "j"], "left").select("k", "i", "j", "ci", "cj", F.coalesce("cij", F.lit(0)).alias("cij"))
    x = x.where("cij = 0 or k < i")  # a closed triad at its smallest vertex only
    ki, kj, ij = F.col("ci"), F.col("cj"), F.col("cij")
    low, mid = F.col("k") < F.col("i"), F.col("k") < F.col("j")
    code = F.when(low, triad_code(ki, kj, ij)).when(mid, triad_code(flip_dir(ki), ij, kj)).otherwise(triad_code(ij, flip_dir(ki), flip_dir(kj)))
    return x.select(F.when(low, F.col("k")).otherwise(F.col("i")).alias("u"), F.when(low, F.col("i")).when(mid, F.col("k")).otherwise(F.col("j")).alias("v"), F.when(mid, F.col("j")).otherwise(F.col("k")).alias("w"), code.cast("int").alias("code"))


def connected_counts(g: Digraph) -> DataFrame:
    """(u, v, triad_no, c): `connected_triads` as counts whose sums are the same for every pair u<v and type.  Each 2-dyad path counts as an open triad, which
    needs no look-up of its third pair, and each triangle takes its three paths back, so no path is shuffled."""
    g, deg = settled(g)
    s = both_ways(g)
    p = s.select(F.col("id").alias("k"), F.col("nbr").alias("i"), F.col("code").alias("ci")).join(s.select(F.col("id").alias("k"), F.col("nbr").alias("j"), F.col("code").alias("cj")), "k").where("i < j")
    ki, kj, none = F.col("ci"), F.col("cj"), F.lit(0)
    low, mid = F.col("k") < F.col("i"), F.col("k") < F.col("j")
    code = F.when(low, triad_code(ki, kj, none)).when(mid, triad_code(flip_dir(ki), none, kj)).otherwise(triad_code(none, flip_dir(ki), flip_dir(kj)))
    paths = p.select(F.when(low, F.col("k")).otherwise(F.col("i")).alias("u"), F.when(low, F.col("i")).when(mid, F.col("k")).otherwise(F.col("j")).alias("v"), fold_code(code).alias("triad_no"), F.lit(1).cast("long").alias("c"))
    cut = lambda bits: F.col("code").bitwiseAND(F.lit(bits))
    cells = F.array(*(F.struct(fold_code(x).alias("triad_no"), F.lit(c).cast("long").alias("c")) for x, c in ((F.col("code"), 1), (cut(15), -1), (cut(51), -1), (cut(60), -1))))
    return paths.unionByName(ordered_triangles(g, deg).select("u", "v", F.explode(cells).alias("e")).select("u", "v", "e.*"))


def _with_runs(g: Digraph) -> DataFrame:
    adj = packed_adjacency(g)
    return g.dyads.join(adj.select(F.col("id").alias("lo"), F.col("packed").alias("pu"), F.col("deg").alias("du")), "lo").join(adj.select(F.col("id").alias("hi"), F.col("packed").alias("pv"), F.col("deg").alias("dv")), "hi")


def _stretches(g: Digraph) -> DataFrame:
    """(u, v, triad_no, c): every adjacent pair u<v as if its ends had no neighbour in common.  Third nodes of one end's run are alike where they have the same
    code, so their stretch beyond the other end is counted in the run once instead of being visited pair by pair; the dyadic type is n less both runs."""
    run = Window.partitionBy("id").orderBy(F.desc("nbr")).rowsBetween(Window.unboundedPreceding, -1)
    s = both_ways(g).withColumns({"d": F.count("*").over(Window.partitionBy("id")), **{f"f{q}": F.count_if(F.col("code") == q).over(run) for q in (1, 2, 3)}}).crossJoin(F.broadcast(g.sizes))
    low = F.col("id") < F.col("nbr")
    dir_ = F.when(low, F.col("code")).otherwise(flip_dir(F.col("code")))
    cell = lambda no, c: F.struct(no.alias("triad_no"), c.cast("long").alias("c"))
    cells = [cell(fold_code(dir_ + F.when(low, 4 * q).otherwise(16 * q)), F.col(f"f{q}")) for q in (1, 2, 3)] + [cell(F.when(is_mutual(dir_), 3).otherwise(2), F.when(low, F.col("n")).otherwise(0) - F.col("d"))]
    return s.select(F.least("id", "nbr").alias("u"), F.greatest("id", "nbr").alias("v"), F.explode(F.array(*cells)).alias("e")).select("u", "v", "e.*").where("c <> 0")


def _common(tri: DataFrame) -> DataFrame:
    """(u, v, triad_no, c): what common third nodes change in `_stretches`, from tri(u, v, w, code) with u<v<w.  The closed triad stands at its pair (u, v),
    canonical choice leaves it out at the others, and each of its pairs has one third node less in its union."""
    uv, uw, vw = (F.shiftright("code", k).bitwiseAND(F.lit(3)).cast("int") for k in (0, 2, 4))
    none = F.lit(0)
    cell = lambda a, b, no, c: F.struct(F.col(a).alias("u"), F.col(b).alias("v"), no.alias("triad_no"), F.lit(c).cast("long").alias("c"))
    pair = lambda d: F.when(is_mutual(d), 3).otherwise(2)
    cells = F.array(cell("u", "v", fold_code(F.col("code")), 1), cell("u", "v", fold_code(triad_code(uv, uw, none)), -1), cell("u", "v", fold_code(triad_code(uv, none, vw)), -1),
                    cell("u", "w", fold_code(triad_code(uw, none, flip_dir(vw))), -1), cell("u", "v", pair(uv), 1), cell("u", "w", pair(uw), 1), cell("v", "w", pair(vw), 1))
    return tri.select(F.explode(cells).alias("e")).select("e.*")


def _ordered(met: DataFrame) -> DataFrame:
    """(u, v, w, code) with u<v<w of met(lo, hi, w, code), lo<hi, whose w may stand anywhere."""
    d, lw, hw = (F.shiftright("code", k).bitwiseAND(F.lit(3)).cast("int") for k in (0, 2, 4))
    first, mid = F.col("w") < F.col("lo"), F.col("w") < F.col("hi")
    code = F.when(first, triad_code(flip_dir(lw), flip_dir(hw), d)).when(mid, triad_code(lw, d, flip_dir(hw))).otherwise(F.col("code"))
    return met.select(F.least("lo", "w").alias("u"), F.when(first, F.col("lo")).when(mid, F.col("w")).otherwise(F.col("hi")).alias("v"), F.greatest("hi", "w").alias("w"), code.cast("int").alias("code"))


def _out_runs(g: Digraph, deg: DataFrame) -> DataFrame:
    """(id, k, run): sorted neighbours of larger (degree, id) with direction bits; k is 0.  Such a run is no longer than the root of twice the pairs, and two ends
    have a third node in both runs once a triangle."""
    return oriented(g, deg).groupBy(F.col("t").alias("id"), F.lit(0).cast("long").alias("k")).agg(F.sort_array(F.collect_list(pack(F.col("h"), F.col("code")))).alias("run"))


def _run_pieces(g: Digraph, deg: DataFrame, most: int) -> DataFrame:
    """`_out_runs` cut by ranges k of third nodes, so that no row holds more than `most` of them."""
    each = oriented(g, deg).select(F.col("t").alias("id"), pack(F.col("h"), F.col("code")).alias("x")).withColumn("k", F.floor(unpack_id(F.col("x")) / most))
    return each.groupBy("id", "k").agg(F.sort_array(F.collect_list("x")).alias("run"))


def _both_runs(g: Digraph, runs: DataFrame) -> DataFrame:
    """(lo, hi, dir, pu, pv): the runs of both ends that may meet."""
    return g.dyads.join(runs.toDF("lo", "k", "pu"), "lo").join(runs.toDF("hi", "k", "pv"), ["hi", "k"]).select("lo", "hi", "dir", "pu", "pv")


def _meet_sets(x: DataFrame) -> DataFrame:
    """(lo, hi, w, code) by sets: the intersection of both runs as an array, then each third node is looked up in both."""
    ids = lambda c: F.transform(c, lambda x: unpack_id(x))
    y = x.withColumn("s", F.array_intersect(ids("pu"), ids("pv"))).where("size(s) > 0").select("lo", "hi", "dir", "pu", "pv", F.explode("s").alias("w"))
    return y.select("lo", "hi", "w", triad_code(F.col("dir"), find_dir(F.col("pu"), F.col("w")), find_dir(F.col("pv"), F.col("w"))).alias("code"))


def _merge_kernel(batches):
    """Two sorted runs a pair, merged for all pairs of a batch at once: third nodes in both."""
    for b in batches:
        n = b.num_rows
        lo, hi, dr = (b[c].to_numpy() for c in ("lo", "hi", "dir"))
        pair, key = [], []
        for c in ("pu", "pv"):
            arr = b[c]
            pair.append(np.repeat(np.arange(n), np.diff(arr.offsets.to_numpy())))
            key.append(arr.flatten().to_numpy())
        row, val = np.concatenate(pair), np.concatenate(key)
        side = np.repeat([0, 1], [len(key[0]), len(key[1])])
        o = np.lexsort((side, val >> 2, row))
        row, val = row[o], val[o]
        at = np.flatnonzero((row[1:] == row[:-1]) & (val[1:] >> 2 == val[:-1] >> 2))
        r, code = row[at], dr[row[at]] + 4 * (val[at] & 3) + 16 * (val[at + 1] & 3)
        yield pa.RecordBatch.from_arrays([pa.array(lo[r]), pa.array(hi[r]), pa.array(val[at] >> 2), pa.array(code.astype(np.int32))], names=["lo", "hi", "w", "code"])


def census_edge_driven(g: Digraph, union: str = "join", slots: int = 64, balance: str = "collapsed", parts: int | None = None, piece: int = 1 << 16) -> DataFrame:
    """union: how third nodes in both runs of a pair are found: set (arrays), merge (sorted runs in a kernel), join (relational); those in one run only are
    counted in stretches by every form.  balance: outer, collapsed or weighted task units.

    set and merge pack ids with their direction bits, so a graph whose ids leave no room for them goes through ranks first; merge cuts runs into
    ranges of `piece` third nodes where an id is far from the others or a run may be longer."""
    g, deg = settled(g if union == "join" else packable(g))
    if union == "join":
        tri = ordered_triangles(g, deg)
    elif union == "set":
        tri = _ordered(_meet_sets(_both_runs(g, _out_runs(g, deg))))
    else:
        n = parts or int(g.dyads.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        longest = deg.agg(F.max("d").alias("d")).first().d or 0  # one row
        if longest > piece:
            g, deg = settled(dense(g)[0])
        x = _both_runs(g, _run_pieces(g, deg, piece) if longest > piece else _out_runs(g, deg))
        if balance == "weighted":
            unit = weighted_units(x.groupBy("lo", "hi").agg(F.sum(F.size("pu") + F.size("pv")).alias("work")), n, ["lo"], "hi", F.col("work")).select("lo", "hi", "unit")
            x = x.join(unit, ["lo", "hi"]).repartitionById(n, "unit").drop("unit")
        else:
            x = x.repartition(n, "lo") if balance == "outer" else x.repartition(n, "lo", "hi")
        tri = _ordered(x.mapInArrow(_merge_kernel, "lo long, hi long, w long, code int"))
    return _finish(g, accumulate(_stretches(g).unionByName(_common(tri)), slots=slots))


def dyadic_counts(g: Digraph, ends: DataFrame, common: DataFrame) -> DataFrame:
    """(lo, hi, triad_no, c): per pair n - |S| - 2 with |S| = d_lo + d_hi - 2 - common."""
    x = g.dyads.join(ends.toDF("lo", "dl"), "lo").join(ends.toDF("hi", "dh"), "hi").join(common, ["lo", "hi"], "left").crossJoin(F.broadcast(g.sizes))
    return x.select("lo", "hi", F.when(F.col("dir") == 3, 3).otherwise(2).alias("triad_no"), (F.col("n") - (F.col("dl") + F.col("dh") - 2 - F.coalesce("common", F.lit(0))) - 2).alias("c"))


# ---------------------------------------------------------------- matrix and naive forms

def census_matrix(g: Digraph) -> DataFrame:
    """Products of class matrices, masked: an entry (i, j) of a product is only summed path by path where (i, j) is adjacent, which is to say on
    triangles; all other entries together are the product of the classes' counts at each centre, less those and less the diagonal."""
    C_, R_, M_ = "CRM"
    g, deg = settled(g)
    seen = triangles(g, deg).groupBy("code").agg(F.count("*").alias("c"))
    name = {1: C_, 2: R_, 3: M_}
    flip = {1: 2, 2: 1, 3: 3}
    paths = []
    for code in range(64):
        t, x, y = code & 3, (code >> 2) & 3, code >> 4  # pairs 01, 02, 12
        if t and x and y:
            d = {(0, 1): t, (0, 2): x, (1, 2): y}
            d |= {(b, a): flip[c] for (a, b), c in list(d.items())}
            paths += [(code, name[d[i, k]] + name[d[k, j]] + name[d[i, j]]) for i in range(3) for k in range(3) for j in range(3) if len({i, j, k}) == 3]
    table = g.dyads.sparkSession.createDataFrame(paths, "code int, k string")  # six paths for each of 27 states
    closed = seen.join(F.broadcast(table), "code").groupBy("k").agg(F.sum("c").cast(BIG).alias("p"))
    # from the centre: arrivals of class C are its in-only neighbours, departures of class C its out-only ones
    into, out = {C_: "b", R_: "a", M_: "m"}, {C_: "a", R_: "b", M_: "m"}
    back = {C_: R_, R_: C_, M_: M_}
    big = lambda c: F.col(c).cast("decimal(18,0)")
    sums = {p + q: F.sum((big(into[p]) * big(out[q]) - (big(into[p]) if back[p] == q else F.lit(0))).cast(BIG)) for p in "CRM" for q in "CRM"}
    every = deg.agg(*(v.alias(k) for k, v in sums.items())).select(F.explode(F.array(*(F.struct(F.lit(k).alias("pq"), F.col(k).alias("all")) for k in sums))).alias("r")).select("r.*")
    met = closed.groupBy(F.substring("k", 1, 2).alias("pq")).agg(F.sum("p").alias("p"))
    apart = every.join(F.broadcast(met), "pq", "left").select(F.concat("pq", F.lit("Z")).alias("k"), (F.coalesce("all", F.lit(0)) - F.coalesce("p", F.lit(0))).cast(BIG).alias("p"))
    return matrix_counts(g, closed.unionByName(apart))


def matrix_counts(g: Digraph, tot: DataFrame) -> DataFrame:
    """Census from tot(k, p): paths i-j-l summed by their two classes and the class of (i, l), Z where not adjacent."""
    wide = tot.groupBy().pivot("k", [x + y + z for x in "CRM" for y in "CRM" for z in "CRMZ"]).agg(F.sum("p"))
    q = lambda c: F.coalesce(F.col(c), F.lit(0)).cast(BIG)
    f = {"021D": q("RCZ") / 2, "021U": q("CRZ") / 2, "021C": q("CCZ"), "111D": q("MRZ"), "111U": q("MCZ"), "201": q("MMZ") / 2, "030T": q("CCC"), "030C": q("CCR") / 3,
         "120D": q("RCM") / 2, "120U": q("CRM") / 2, "120C": q("CCM"), "210": q("MMC"), "300": q("MMM") / 6}
    # common neighbours of asymmetric and of mutual pairs, summed
    f["012"] = sum((q(x + y + "C") for x in "CRM" for y in "CRM"), F.lit(0).cast(BIG))
    f["102"] = sum((q(x + y + "M") for x in "CRM" for y in "CRM"), F.lit(0).cast(BIG)) / 2
    rows = wide.select(F.explode(F.array(*(F.struct(F.lit(LABELS.index(x) + 1).alias("triad_no"), v.cast(BIG).alias("c")) for x, v in f.items()))).alias("r")).select("r.*")
    ends = degrees(g).select("id", "d")
    apart = g.dyads.join(ends.toDF("lo", "dl"), "lo").join(ends.toDF("hi", "dh"), "hi").crossJoin(F.broadcast(g.sizes))
    dy = apart.groupBy(F.when(F.col("dir") == 3, 3).otherwise(2).alias("triad_no")).agg(F.sum(F.col("n") - F.col("dl") - F.col("dh")).cast(BIG).alias("c"))
    return _finish(g, rows.unionByName(dy))


def naive_states(g: Digraph, max_n: int = 400) -> DataFrame:
    """(code, c) over all 3-subsets; refuses more than max_n vertices."""
    if g.vertices.limit(max_n + 1).count() > max_n:
        raise ValueError(f"the naive census is for at most {max_n} vertices")
    v = g.vertices.select("id")
    t = v.toDF("a").join(v.toDF("b"), F.col("a") < F.col("b")).join(v.toDF("c"), F.col("b") < F.col("c"))
    for x, y in ("ab", "ac", "bc"):
        t = t.join(g.dyads.toDF(x, y, x + y), [x, y], "left")
    z = lambda c: F.coalesce(F.col(c), F.lit(0))
    return t.groupBy(triad_code(z("ab"), z("ac"), z("bc")).alias("code")).agg(F.count("*").alias("c"))


def census_naive(g: Digraph, max_n: int = 400) -> DataFrame:
    return _finish(g, naive_states(g, max_n).select(fold_code(F.col("code")).alias("triad_no"), "c"))


def census64(g: Digraph) -> DataFrame:
    """(code, n_triads) for all 64 states under the vertex order; only triangles are enumerated.

    Two-pair states come from each centre's run in ascending order: products of its lower and higher neighbours by code, and running counts
    of codes before each neighbour on the same side.  One-pair states come from ranks and places in the runs of a pair's ends.  Both count
    every closed triad as if its other pairs were missing, which the triangles set right; null triads are what is left of the total."""
    g, deg = settled(g)
    f = lambda c: F.when(c == 3, 3).otherwise(3 - c)
    run = Window.partitionBy("id").orderBy("nbr")
    before, whole = run.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy("id")
    s = both_ways(g).withColumn("above", F.col("nbr") > F.col("id"))
    s = s.withColumns({"pos": F.row_number().over(run) - 1, "d": F.count("*").over(whole), "low": F.count_if(~F.col("above")).over(whole),
                       **{f"r{p}": F.count_if((F.col("code") == p)).over(before) for p in (1, 2, 3)}, **{f"l{p}": F.count_if((F.col("code") == p) & ~F.col("above")).over(whole) for p in (1, 2, 3)}})
    s = s.join(relabel(g.vertices), "id").crossJoin(F.broadcast(g.sizes))
    above, c, d, low, pos, r = (F.col(x) for x in ("above", "code", "d", "low", "pos", "rank"))
    cell = lambda code, n: F.struct(code.cast("int").alias("code"), n.cast("decimal(20,0)").alias("n"))
    two = []
    for p in (1, 2, 3):
        same = F.coalesce(F.col(f"r{p}"), F.lit(0)) - F.when(above, F.col(f"l{p}")).otherwise(0)
        q = 3 if p == 3 else 3 - p  # the same pair seen from the neighbour
        two.append(cell(F.when(above, p + 4 * c).otherwise(4 * q + 16 * f(c)), same))
        two.append(cell(F.when(above, q + 16 * c).otherwise(F.lit(0)), F.when(above, F.col(f"l{p}")).otherwise(0)))
    here = F.when(above, c).otherwise(f(c))  # the pair from its smaller end
    one = [cell(16 * here, F.when(above, r - low).otherwise(-pos)),
           cell(4 * here, F.when(above, -r - 1 - (pos - low)).otherwise(r - (low - pos - 1))),
           cell(here, F.when(above, -(d - pos - 1)).otherwise(F.col("n") - 1 - r - (d - low)))]
    open_ = s.select(F.explode(F.array(*two, *one)).alias("e")).groupBy("e.code").agg(F.sum("e.n").cast(BIG).alias("c"))
    tri = ordered_triangles(g, deg).groupBy("code").agg(F.count("*").cast(BIG).alias("c"))
    bits = lambda *keep: F.col("code").bitwiseAND(F.lit(sum(3 << (2 * k) for k in keep)))
    fix = [F.struct(F.col("code"), F.col("c"))] + [F.struct(bits(*k).alias("code"), (-F.col("c")).cast(BIG).alias("c")) for k in ((0, 1), (0, 2), (1, 2))] + [F.struct(bits(k).alias("code"), F.col("c")) for k in range(3)]
    some = open_.unionByName(tri.select(F.explode(F.array(*fix)).alias("e")).select("e.*")).where("code > 0").groupBy("code").agg(F.sum("c").cast(BIG).alias("c"))
    null = g.sizes.crossJoin(F.broadcast(some.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("s")))).select(F.lit(0).alias("code"), (triad_total(F.col("n")) - F.col("s")).cast(BIG).alias("c"))
    all_codes = g.dyads.sparkSession.range(64).select(F.col("id").cast("int").alias("code"))
    return all_codes.join(some.unionByName(null), "code", "left").select("code", F.coalesce("c", F.lit(0)).cast(BIG).alias("n_triads"))


def condense(c64: DataFrame) -> DataFrame:
    """64 states to 16 types."""
    return c64.groupBy(fold_code(F.col("code")).alias("triad_no")).agg(F.sum("n_triads").cast(BIG).alias("n_triads")).select(type_label(F.col("triad_no")).alias("triad_type"), "triad_no", "n_triads")


def cost_model(g: Digraph) -> DataFrame:
    """(n, pairs, d2, wedges, ordered_wedges): what each method would visit."""
    g, deg = settled(g)
    d = deg.agg(F.sum(F.col("d") * F.col("d")).cast("long").alias("d2"), F.sum((F.col("d") * (F.col("d") - 1) / 2).cast("long")).alias("wedges"))
    o = oriented(g, deg).groupBy("t").agg(F.count("*").alias("k")).agg(F.sum((F.col("k") * (F.col("k") - 1) / 2).cast("long")).alias("ordered_wedges"))
    return g.sizes.crossJoin(F.broadcast(g.dyads.agg(F.count("*").alias("pairs")))).crossJoin(F.broadcast(d)).crossJoin(F.broadcast(o))


def planned_method(g: Digraph, wedges_a_pair: int = 200, dense_share: float = 0.1, least_n: int = 2000) -> str:
    """The method whose cost is least by `cost_model`: tiles where a large share of all pairs is adjacent, colour blocks where wedges, which the scalable
    form shuffles, would be many times the pairs or many times the rows that colour blocks shuffle (a pair once a colour), else the scalable form."""
    from .blocks import colours_for

    c = cost_model(g).first()  # one row
    if c.n >= least_n and c.pairs >= dense_share * c.n * (c.n - 1) / 2:
        return "matrix_blocks"
    return "colour_blocks" if (c.ordered_wedges or 0) > min(wedges_a_pair, max(20, colours_for(c.pairs))) * max(c.pairs, 1) else "scalable"


def census(g: Digraph, method: str = "auto", **more) -> DataFrame:
    """The 16-type census, exact by every method; auto asks `planned_method`, but for many graphs at once, which are left to the scalable form."""
    from . import blocks

    forms = {"scalable": census_scalable, "edge_driven": census_edge_driven, "matrix": census_matrix, "naive": census_naive, "matrix_blocks": blocks.census_matrix_blocks, "colour_blocks": blocks.census_colour_blocks}
    if method == "auto" and not g.keys and not more:
        g = kept(g)  # the planner and the form it names read the sources once
        with shuffles_removed(g.dyads.sparkSession):
            method = planned_method(g)
    return forms["scalable" if method == "auto" else method](g, **more)


def census_vector(c: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """(keys, counts): the 16 counts as one array in the order of the types."""
    cells = F.sort_array(F.collect_list(F.struct("triad_no", F.col("n_triads").cast(BIG).alias("n"))))
    return c.groupBy(*(keys or [])).agg(cells.alias("v")).select(*(keys or []), F.transform("v", lambda x: x["n"]).alias("counts"))


def census_merge(vectors: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Adds census vectors place by place: (keys, counts)."""
    keys = keys or []
    each = vectors.select(*keys, F.posexplode("counts").alias("p", "n")).groupBy(*keys, "p").agg(F.sum("n").cast(BIG).alias("n"))
    return each.groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct("p", "n"))).alias("v")).select(*keys, F.transform("v", lambda x: x["n"]).alias("counts"))


def list_triads(g: Digraph, types: list[str], limit: int | None = None) -> DataFrame:
    """(u, v, w, triad_type) of the connected types asked for; closed types alone enumerate triangles only.  limit: the first ones by u, v, w."""
    t = ordered_triangles(g) if set(types) <= set(CLOSED) else connected_triads(g)
    t = t.select("u", "v", "w", type_label(fold_code(F.col("code"))).alias("triad_type")).where(F.col("triad_type").isin(*types))
    return t if limit is None else t.orderBy("u", "v", "w").limit(limit)
