"""Direction codes, 6-bit triad states and the 16 types.

A dyad's code is 1 (first to second), 2 (second to first) or 3 (both).  A triad's state is dir(a,b) + 4 dir(a,c) + 16 dir(b,c).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: fixed values: slot, label, mutual, asymmetric, null pairs, transitive, intransitive, cyclic triples, states
TYPES = [
    (1, "003", 0, 0, 3, 0, 0, 0, [0]),
    (2, "012", 0, 1, 2, 0, 0, 0, [1, 2, 4, 8, 16, 32]),
    (3, "102", 1, 0, 2, 0, 0, 0, [3, 12, 48]),
    (4, "021D", 0, 2, 1, 0, 0, 0, [5, 18, 40]),
    (5, "021U", 0, 2, 1, 0, 0, 0, [10, 20, 33]),
    (6, "021C", 0, 2, 1, 0, 1, 0, [6, 9, 17, 24, 34, 36]),
    (7, "111D", 1, 1, 1, 0, 1, 0, [11, 14, 28, 35, 49, 52]),
    (8, "111U", 1, 1, 1, 0, 1, 0, [7, 13, 19, 44, 50, 56]),
    (9, "030T", 0, 3, 0, 1, 0, 0, [21, 22, 26, 37, 41, 42]),
    (10, "030C", 0, 3, 0, 0, 3, 1, [25, 38]),
    (11, "201", 2, 0, 1, 0, 2, 0, [15, 51, 60]),
    (12, "120D", 1, 2, 0, 2, 0, 0, [30, 43, 53]),
    (13, "120U", 1, 2, 0, 2, 0, 0, [23, 45, 58]),
    (14, "120C", 1, 2, 0, 1, 2, 1, [27, 29, 39, 46, 54, 57]),
    (15, "210", 2, 1, 0, 3, 1, 1, [31, 47, 55, 59, 61, 62]),
    (16, "300", 3, 0, 0, 6, 0, 2, [63]),
]
LABELS = [t[1] for t in TYPES]
CLOSED = ["030T", "030C", "120D", "120U", "120C", "210", "300"]
FOLD = [next(t[0] for t in TYPES if c in t[8]) for c in range(64)]


def type_table(spark: SparkSession) -> DataFrame:
    """(code, triad_no, triad_type, mutual, asym, nulls, trans, intrans, cyc), 64 rows."""
    rows = [(c, *t[:8]) for t in TYPES for c in t[8]]
    return spark.createDataFrame(rows, "code int, triad_no int, triad_type string, mutual int, asym int, nulls int, trans int, intrans int, cyc int")


def fold_code(code: Column) -> Column:
    """Type number of a state."""
    return F.element_at(F.array(*(F.lit(x) for x in FOLD)), code.cast("int") + 1)


def type_label(no: Column) -> Column:
    return F.element_at(F.array(*(F.lit(x) for x in LABELS)), no.cast("int"))


def family(label: Column) -> Column:
    """null, dyadic, open or closed."""
    return F.when(label == "003", "null").when(label.isin("012", "102"), "dyadic").when(label.isin(*CLOSED), "closed").otherwise("open")


def triad_code(ab: Column, ac: Column, bc: Column) -> Column:
    return (ab.bitwiseOR(F.shiftleft(ac, 2)).bitwiseOR(F.shiftleft(bc, 4))).cast("int")


def flip_dir(code: Column) -> Column:
    return F.when(code == 3, 3).otherwise(3 - code).cast("int")


#: ids from -MOST to MOST - 1 leave room for two direction bits
MOST = 1 << 61


def pack(nbr: Column, code: Column) -> Column:
    """neighbour * 4 + code; an error for ids that two bits cannot be added to."""
    id_ = nbr.cast("long")
    return F.when(id_.between(-MOST, MOST - 1), F.shiftleft(id_, 2).bitwiseOR(code.cast("long"))).otherwise(
        F.raise_error(F.concat(F.lit("id needs more than 62 bits, relabel the graph first: "), id_.cast("string"))).cast("long"))


def is_out(code: Column) -> Column:
    """The first vertex sends to the second."""
    return code.bitwiseAND(F.lit(1)) != 0


def is_in(code: Column) -> Column:
    return code.bitwiseAND(F.lit(2)) != 0


def is_mutual(code: Column) -> Column:
    return code == 3


def find_dir(packed: Column, nbr: Column) -> Column:
    """Direction code of nbr in a sorted packed run, 0 where it is no neighbour: binary search, so about log2 of the run's length reads."""
    want = F.shiftleft(nbr.cast("long"), 2)
    start = F.struct(F.lit(0).alias("lo"), F.size(packed).alias("hi"))  # the first element that is not below lies in lo..hi

    def halve(at: Column, _: Column) -> Column:
        mid = F.floor((at["lo"] + at["hi"]) / 2).cast("int")
        low = (at["lo"] < at["hi"]) & (F.get(packed, mid) < want)
        high = (at["lo"] < at["hi"]) & (F.get(packed, mid) >= want)
        return F.struct(F.when(low, mid + 1).otherwise(at["lo"]).alias("lo"), F.when(high, mid).otherwise(at["hi"]).alias("hi"))

    rounds = F.sequence(F.lit(0), F.ceil(F.log2(F.size(packed) + F.lit(1))).cast("int"))
    found = F.get(packed, F.aggregate(rounds, start, halve)["lo"])
    return F.when(F.shiftright(found, 2) == nbr.cast("long"), found.bitwiseAND(F.lit(3).cast("long")).cast("int")).otherwise(0)


def unpack_id(x: Column) -> Column:
    return F.shiftright(x, 2)


def unpack_dir(x: Column) -> Column:
    return x.bitwiseAND(F.lit(3).cast("long")).cast("int")


def canonical(u: Column, v: Column, w: Column, adj_uw: Column) -> Column:
    """Keeps each connected triad at one adjacent pair u<v: w beyond v, or between and not adjacent to u."""
    return (v < w) | ((u < w) & (w < v) & ~adj_uw)


def triad_total(n: Column) -> Column:
    """n(n-1)(n-2)/6 as DECIMAL(38,0); products are halved and cut by three first, so no intermediate overflows."""
    d = n.cast("decimal(19,0)")
    pairs = F.when(n % 2 == 0, (d / 2).cast("decimal(19,0)").cast("decimal(38,0)") * (d - 1).cast("decimal(19,0)")).otherwise(d.cast("decimal(38,0)") * ((d - 1) / 2).cast("decimal(19,0)")).cast("decimal(38,0)")
    return F.when(n < 3, F.lit(0).cast("decimal(38,0)")).otherwise((pairs * (d - 2).cast("decimal(19,0)") / 3).cast("decimal(38,0)"))
