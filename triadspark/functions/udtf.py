"""SQL surface: scalar functions over codes (expressions, no Python) and a table function that lists triads of one pair."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .codes import FOLD, LABELS


@udtf(returnType="w bigint, code int, triad_type string")
class TriadsOf:
    """triads_of(u, v, dir, packed_u, packed_v): every connected triad that is counted at the pair u < v, from two sorted packed runs."""

    def eval(self, u: int, v: int, direction: int, packed_u: list, packed_v: list):
        a, b = ({x >> 2: x & 3 for x in run or []} for run in (packed_u, packed_v))
        for w in sorted(a.keys() | b.keys()):
            if w not in (u, v) and (w > v or (u < w and w not in a)):
                code = direction + 4 * a.get(w, 0) + 16 * b.get(w, 0)
                yield w, code, LABELS[FOLD[code] - 1]


def register_functions(spark: SparkSession) -> None:
    """triad_code, fold_triad, pack_neighbour, neighbour_id, neighbour_dir as SQL expressions, and triads_of."""
    made = {
        "triad_code(ab int, ac int, bc int) returns int": "ab + 4 * ac + 16 * bc",
        "fold_triad(code int) returns int": f"element_at(array({', '.join(map(str, FOLD))}), code + 1)",
        "pack_neighbour(id bigint, dir int) returns bigint": "shiftleft(id, 2) | dir",
        "neighbour_id(x bigint) returns bigint": "shiftright(x, 2)",
        "neighbour_dir(x bigint) returns int": "cast(x & 3 as int)",
    }
    for head, body in made.items():
        spark.sql(f"create or replace temporary function {head} return {body}")
    spark.udtf.register("triads_of", TriadsOf)
