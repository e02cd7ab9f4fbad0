"""Two relations under two inequalities, summed by the rows of the left: no pairs are visited."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ranks import local_sums, prefix_sums  # noqa: F401
from .single_job import _pair

#: Rows of both sides that a slab or a bin holds about.
GROUP_ROWS = 100_000
NUMBERS = ("tinyint", "smallint", "int", "bigint", "float", "double")


def fits(left: DataFrame, right: DataFrame, conditions: list[tuple[str, str, str]]) -> bool:
    """Two conditions (left column, operator, right column), each < <= >= or > of numbers."""
    kind = dict(left.dtypes), dict(right.dtypes)
    return len(conditions) == 2 and all(op in ("<", "<=", ">=", ">") and kind[0][u] in NUMBERS and kind[1][v] in NUMBERS for u, op, v in conditions)


def dominance_sums(left: DataFrame, right: DataFrame, conditions: list[tuple[str, str, str]], weight: str, units: int = 8) -> DataFrame:
    """Columns of left, and s: the sum of weight over the rows of right that meet both conditions, where there are any.

    Right values of the first condition are cut into slabs, those of the second into bins. A left row takes from the
    bins that lie beyond its own in the slabs beyond its own by a table of sums; inside its slab, and inside its bin from the slabs
    beyond, by sorted ranks. So each row is sent twice, and the work is rows times their logarithm. A value that many rows have is not split.
    Columns are free of nulls; left may give a row several times, whose s add up to the whole.
    """
    parts = max(units, min(1024, -(-(left.count() + right.count()) // GROUP_ROWS)))
    (u0, op0, v0), (u1, op1, v1) = conditions
    cuts = [sorted(set(right.approxQuantile(v, [i / parts for i in range(1, parts)], 0.001))) if parts > 1 else [] for v in (v0, v1)]

    def placed(df: DataFrame, a: str, b: str) -> DataFrame:
        # the number of cuts below a value: of a < b, a's is not greater
        place = lambda c, of: F.size(F.filter(F.lit(of), lambda cut: F.col(c) > cut)) if of else F.lit(0)
        return df.withColumn("slab_", place(a, cuts[0])).withColumn("bin_", place(b, cuts[1]))

    lt, rt = placed(left, u0, u1), placed(right.select(v0, v1, weight), v0, v1)
    shape = len(cuts[0]) + 1, len(cuts[1]) + 1
    table = np.zeros(shape, np.int64)
    for r in rt.groupBy("slab_", "bin_").agg(F.sum(weight).alias("w")).collect():
        table[r["slab_"], r["bin_"]] = r["w"]
    for axis, op in ((0, op0), (1, op1)):
        table = np.flip(_before(np.flip(table, axis), axis), axis) if op in ("<", "<=") else _before(table, axis)
    beyond = "<" if op0 in ("<", "<=") else ">"
    names = left.columns
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in left.schema) + ", s bigint"

    def rows(lt: pa.Table, rt: pa.Table, first: tuple[str, str, str], whole: bool) -> pa.Table:
        l, r = (t.select(sorted({*c, "slab_", "bin_"})).to_pandas() for t, c in ((lt, {first[0], u1}), (rt, {first[2], v1, weight})))
        s = np.zeros(len(l), np.int64)
        if len(r) and len(l):
            s += local_sums([(*_pair(l[a], r[b]), op) for a, op, b in (first, (u1, op1, v1))], r[weight].to_numpy(np.int64))
        if whole:
            s += table[l["slab_"].to_numpy(), l["bin_"].to_numpy()]
        some = s > 0
        return lt.select(names).filter(pa.array(some)).append_column("s", pa.array(s[some]))

    def met(key: str, first: tuple[str, str, str], whole: bool) -> DataFrame:
        both = lt.repartition(parts, key).groupBy(key).cogroup(rt.repartition(parts, key).groupBy(key))
        return both.applyInArrow(lambda a, b: rows(a, b, first, whole), schema)

    return met("slab_", (u0, op0, v0), True).unionByName(met("bin_", ("slab_", beyond, "slab_"), False))


def _before(x: np.ndarray, axis: int) -> np.ndarray:
    """Sums of all earlier places along the axis, its own left out."""
    return np.cumsum(x, axis) - x
