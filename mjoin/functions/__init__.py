"""Scalar functions for regions: curve positions as SQL expressions and as an Arrow function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..partition.curves import hilbert_index


def zorder_expr(columns: list[Column], bits: int) -> Column:
    """Interleaved bits, most significant first, in whole-stage code."""
    out = F.lit(0).cast("long")
    for level in range(bits - 1, -1, -1):
        for c in columns:
            out = F.shiftleft(out, 1).bitwiseOR(F.shiftright(c.cast("long"), level).bitwiseAND(F.lit(1)))
    return out


def hilbert_expr(columns: list[Column], bits: int) -> Column:
    """Hilbert position by built-in functions: a fold over levels and dimensions, so the expression stays small."""
    m = len(columns)
    x = F.array(*[c.cast("long") for c in columns])
    if bits > 1:
        steps = [(1 << level) * m + d for level in range(bits - 1, 0, -1) for d in range(m)]

        def turn(acc: Column, s: Column) -> Column:
            level, d = F.floor(s / m).cast("long"), (s % m).cast("int")
            low, own = level - 1, acc[d]
            swap = acc[0].bitwiseXOR(own).bitwiseAND(low)
            set_ = own.bitwiseAND(level) > 0
            first = F.when(set_, acc[0].bitwiseXOR(low)).otherwise(acc[0].bitwiseXOR(swap))
            return F.transform(acc, lambda v, i: F.when(i == 0, first).when(i == d, F.when(set_, v).otherwise(v.bitwiseXOR(swap))).otherwise(v))

        x = F.aggregate(F.lit(steps).cast("array<long>"), x, turn)

    def interleaved(v: Column) -> Column:
        gray = [v[0]]
        for d in range(1, m):
            gray.append(gray[-1].bitwiseXOR(v[d]))
        flip = lambda acc, b: F.when(gray[-1].bitwiseAND(b) > 0, acc.bitwiseXOR(b - 1)).otherwise(acc)
        back = F.aggregate(F.lit([1 << k for k in range(bits - 1, 0, -1)] or [0]).cast("array<long>"), F.lit(0).cast("long"), flip) if bits > 1 else F.lit(0).cast("long")
        # bound once, so that the positions below do not repeat the fold
        bound = F.array(*gray, back)
        return F.transform(F.array(bound), lambda g: zorder_expr([g[d].bitwiseXOR(g[m]) for d in range(m)], bits))[0]

    return F.transform(F.array(x), interleaved)[0]


def hilbert_udf(bits: int):
    """The same for any size, in Arrow batches."""

    @F.pandas_udf("long")
    def index(coords):
        return pd.Series(hilbert_index(np.stack(coords.to_numpy()), bits) if len(coords) else [], dtype="int64")

    return index


def sign_keys(vector: Column, planes: list[list[float]], bands: int) -> Column:
    """Keys of a vector: bits of its sides of the planes, in bands; the band number is part of the key."""
    side = [F.aggregate(F.zip_with(vector, F.array(*map(F.lit, p)), lambda a, b: a.cast("double") * b), F.lit(0.0), lambda s, v: s + v) >= 0 for p in planes]
    rows = len(planes) // bands
    keys = []
    for b in range(bands):
        key = F.lit(b)
        for s in side[b * rows : (b + 1) * rows]:
            key = key * 2 + s.cast("int")
        keys.append(key)
    return F.array(*keys)


def register_regions_of(spark, assignment, aliases: list[str], name: str = "regions_of") -> None:
    """Makes the table function regions_of(alias, coord) -> (region) of an assignment known to SQL, for LATERAL joins."""
    from pyspark.sql.functions import udtf

    routes = dict(zip(aliases, assignment.routes, strict=True))

    @udtf(returnType="region: int")
    class RegionsOf:
        def eval(self, alias: str, coord: int):
            for r in routes[alias][coord]:
                yield (r,)

    spark.udtf.register(name, RegionsOf)


def selectivity_agg(op: str):
    """Aggregate of two columns: the share of rows whose pair of values meets the comparison; 0 for none. For sampled pairs."""
    compare = {"<": np.less, "<=": np.less_equal, "=": np.equal, ">=": np.greater_equal, ">": np.greater, "<>": np.not_equal}[op]

    def share(a: pd.Series, b: pd.Series) -> float:
        known = a.notna() & b.notna()
        return float(compare(a[known].to_numpy(), b[known].to_numpy()).mean()) if known.any() else 0.0

    return F.pandas_udf(share, "double")
