"""How often each vertex stands in each connected triad type, and in which role."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.codes import flip_dir, fold_code, triad_code, type_label
from .census import triangles
from .graph import Digraph, both_ways, degrees


def _open(a, b):
    """Type of the open triad whose centre sees its ends with codes a and b."""
    return fold_code(triad_code(a, b, F.lit(0)))


def triad_participation(g: Digraph) -> DataFrame:
    """(id, triad_type, role, n): centre and end of open triads, corner of closed ones.

    Open roles come from class counts of centres, less what triangles close: only triangles are enumerated, the rest is linear in pairs."""
    d = degrees(g)
    a, b, m = (F.col(c) for c in "abm")
    kinds = {(1, 1): a * (a - 1) / 2, (2, 2): b * (b - 1) / 2, (1, 2): a * b, (3, 2): m * b, (3, 1): m * a, (3, 3): m * (m - 1) / 2}
    cells = [F.struct(_open(F.lit(x), F.lit(y)).alias("no"), F.lit("centre").alias("role"), n.cast("long").alias("n")) for (x, y), n in kinds.items()]
    centre = d.select("id", F.explode(F.array(*cells)).alias("e")).select("id", "e.*")
    # from the end's side: its neighbour j is the centre, seeing the end with the flipped code
    seen = both_ways(g).select("id", F.col("nbr").alias("j"), flip_dir(F.col("code")).alias("c")).join(d.withColumnRenamed("id", "j"), "j")
    other = [F.struct(_open(F.col("c"), F.lit(x)).alias("no"), F.lit("end").alias("role"), (n - (F.col("c") == x).cast("long")).alias("n")) for x, n in ((1, a), (2, b), (3, m))]
    end = seen.select("id", F.explode(F.array(*other)).alias("e")).select("id", "e.*")
    bits = lambda k: F.shiftright("code", k).bitwiseAND(F.lit(3)).cast("int")
    tx, ty, xy = bits(0), bits(2), bits(4)
    corners = (("t", "x", "y", tx, ty), ("x", "t", "y", flip_dir(tx), xy), ("y", "t", "x", flip_dir(ty), flip_dir(xy)))
    row = lambda v, no, role, n: F.struct(F.col(v).alias("id"), no.alias("no"), F.lit(role).alias("role"), F.lit(n).cast("long").alias("n"))
    closed = []
    for v, p, q, cp, cq in corners:
        shown = _open(cp, cq)
        closed += [row(v, fold_code(F.col("code")), "corner", 1), row(v, shown, "centre", -1), row(p, shown, "end", -1), row(q, shown, "end", -1)]
    tri = triangles(g).select(F.explode(F.array(*closed)).alias("e")).select("e.*")
    total = centre.unionByName(end).unionByName(tri).groupBy("id", "no", "role").agg(F.sum("n").alias("n")).where("n > 0")
    return total.select("id", type_label(F.col("no")).alias("triad_type"), "role", "n")


def top_participants(part: DataFrame, triad_type: str, k: int = 10) -> DataFrame:
    return part.where(F.col("triad_type") == triad_type).groupBy("id").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "id").limit(k)
