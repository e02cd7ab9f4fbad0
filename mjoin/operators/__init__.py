"""Relational operators around the engine, as DataFrame compositions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def join_asof(left: DataFrame, right: DataFrame, by: str, at: str, columns: list[str], inclusive: bool = False) -> DataFrame:
    """Each left row with columns of the latest right row of the same key before it (inclusive: or at the same time).

    One union and one window over the key: no pairs are made. Left rows without an earlier right row get nulls.
    """
    seen = F.struct(*[F.col(c).alias(c) for c in columns])
    kind = right.select(seen.alias("s")).schema["s"].dataType
    base = left.select(*left.columns, F.lit(None).cast(kind).alias("seen_"), F.lit(True).alias("left_"))
    other = right.select(*[F.col(c) if c in (by, at) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], seen.alias("seen_"), F.lit(False).alias("left_"))
    # at equal times left rows stand before right ones unless the bound is inclusive
    order = Window.partitionBy(by).orderBy(F.col(at), F.col("left_").asc() if inclusive else F.col("left_").desc())
    last = F.last("seen_", ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    both = base.unionByName(other).withColumn("last_", last).where("left_")
    return both.select(*left.columns, *[F.col(f"last_.{c}").alias(f"asof_{c}") for c in columns])


def band_join(left: DataFrame, right: DataFrame, x: str, y: str, low: float, high: float, width: float | None = None) -> DataFrame:
    """Pairs with x + low <= y <= x + high: buckets of one width as an equi key, left rows copied to the buckets they reach."""
    width = width or max(high - low, 1e-9)
    reach = F.sequence(F.floor((F.col(x) + low) / width), F.floor((F.col(x) + high) / width))
    a = left.withColumn("bucket_", F.explode(reach))
    b = right.withColumn("bucket_", F.floor(F.col(y) / width))
    return a.join(b, "bucket_").where((F.col(y) >= F.col(x) + low) & (F.col(y) <= F.col(x) + high)).drop("bucket_")


def semi_join(left: DataFrame, right: DataFrame, condition: Column) -> DataFrame:
    return left.join(right, condition, "left_semi")


def anti_join(left: DataFrame, right: DataFrame, condition: Column) -> DataFrame:
    return left.join(right, condition, "left_anti")


def salted_join(left: DataFrame, right: DataFrame, on: str, salts: int) -> DataFrame:
    """Equi join of a skewed left side: its keys are dealt to salts parts, the right rows copied to all of them."""
    a = left.withColumn("salt_", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    b = right.withColumn("salt_", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [on, "salt_"]).drop("salt_")


def top_k_by(df: DataFrame, by: str, order: list[Column], k: int) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy(by).orderBy(*order))
    return df.withColumn("rank_", rank).where(F.col("rank_") <= k).drop("rank_")


def same_bag(a: DataFrame, b: DataFrame) -> bool:
    """Whether two frames hold the same rows equally often."""
    return not a.exceptAll(b).limit(1).count() and not b.exceptAll(a).limit(1).count()
