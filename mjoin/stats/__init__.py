"""Counts, samples, quantiles and selectivities."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query import MultiJoinQuery, Predicate, RelOp

_NUMPY = {RelOp.LT: np.less, RelOp.LE: np.less_equal, RelOp.EQ: np.equal, RelOp.GE: np.greater_equal, RelOp.GT: np.greater, RelOp.NE: np.not_equal}
#: Rows of a relation that selectivities are estimated from.
SAMPLE_ROWS = 500


@dataclass(frozen=True)
class Statistics:
    rows: dict[str, int]
    row_bytes: dict[str, float]
    selectivity: dict[int, float]
    samples: dict[str, pd.DataFrame] = field(default_factory=dict, repr=False)


def hash_sample(df: DataFrame, rid: str, most: int = SAMPLE_ROWS, seed: int = 0) -> DataFrame:
    """The most rows of least hash of their id: the same ones each time, whatever the partitions."""
    return df.orderBy(F.xxhash64(F.lit(seed), rid), rid).limit(most)


def selectivity_of(p: Predicate, left: pd.Series, right: pd.Series) -> float:
    """Share of pairs of sampled values that meet the condition; at least one in twice as many pairs."""
    a, b = left.dropna().to_numpy(), right.dropna().to_numpy()
    if not len(a) or not len(b):
        return 0.0
    hit = _NUMPY[p.op].outer(a, b)
    return max(float(hit.mean()), 0.5 / hit.size)


def collect_statistics(q: MultiJoinQuery, most: int = SAMPLE_ROWS, seed: int = 0, stored: dict[str, str] | None = None) -> Statistics:
    """Rows after local filters, bytes of a compared row, and the selectivity of each condition, from samples.

    stored: by alias the folder that ingest wrote; its sample then stands for a scan of the relation.
    """
    rows, width, selectivity, samples, counted, drawn = {}, {}, {}, {}, {}, {}
    key_of = lambda a: (id(q.relations[a]), q.filters.get(a))
    sides = {a: {s.expr for p in q.predicates for s in (p.left, p.right) if s.alias == a} for a in q.relations}
    for alias in q.relations:
        df, key = q.filtered(alias), key_of(alias)
        if key not in counted:
            # one count and one ordered scan for each distinct relation; its aliases get parts of one sample
            counted[key] = df.count()
            alike = [a for a in q.relations if key_of(a) == key]
            if alias in (stored or {}):
                df = df.sparkSession.read.parquet(f"{stored[alias]}/sample").where(q.filters.get(alias, "true"))
            named = df.select(F.col(q.rid_of(alias)).alias("rid_"), *(F.expr(e).alias(e) for e in sorted(set().union(*(sides[a] for a in alike)))))
            drawn[key] = hash_sample(named, "rid_", most * len(alike), seed).toPandas(), alike
        rows[alias] = counted[key]
        width[alias] = 8.0 * (1 + len(sides[alias]))
        sample, alike = drawn[key]
        part = sample.iloc[alike.index(alias) :: len(alike)] if len(sample) >= 2 * len(alike) else sample
        samples[alias] = part[["rid_", *sorted(sides[alias])]].reset_index(drop=True)
    for p in q.predicates:
        selectivity[p.label] = selectivity_of(p, samples[p.left.alias][p.left.expr], samples[p.right.alias][p.right.expr])
    return Statistics(rows, width, selectivity, samples)


def estimate_rows(q: MultiJoinQuery, stats: Statistics, labels: frozenset[int]) -> float:
    """Rows of the combinations under labels, conditions taken as independent."""
    out = 1.0
    for a in {a for p in q.predicates if p.label in labels for a in p.aliases}:
        out *= stats.rows[a]
    for k in labels:
        out *= stats.selectivity[k]
    return out


#: Rows of a sample that must share a key before it counts as hot.
HOT_ROWS = 5


def hot_share(q: MultiJoinQuery, stats: Statistics, labels: frozenset[int]) -> float:
    """Share of an equality join's pairs that its most frequent key holds, from the samples: the largest over the pairs of relations joined.

    Several equalities between two relations count as independent. Keys that no sample shows HOT_ROWS times share evenly.
    """
    share: dict[frozenset, float] = {}
    for p in q.predicates:
        if p.label in labels and p.op is RelOp.EQ:
            a, b = (stats.samples[s.alias][s.expr].value_counts() for s in (p.left, p.right))
            pairs = (a * b).dropna()  # by key
            hot = float(pairs.max() / pairs.sum()) if len(pairs) and max(a.max(), b.max()) >= HOT_ROWS else 0.0
            share[p.aliases] = share.get(p.aliases, 1.0) * hot
    return max(share.values(), default=0.0)


def quantiles(df: DataFrame, column: str, n: int) -> list:
    return df.agg(F.percentile_approx(column, [k / n for k in range(1, n)], 10_000).alias("q")).first()["q"] or []


def selectivity_from_quantiles(a: list, b: list, op: RelOp) -> float:
    """P(x op y) for two columns given by equi-depth quantiles; half a bucket where two coincide."""
    if op in (RelOp.EQ, RelOp.NE):
        equal = sum(x == y for x in a for y in b) / max(1, len(a) * len(b))
        return equal if op is RelOp.EQ else 1 - equal
    if not a or not b:
        return 0.5
    less = sum((x < y) + 0.5 * (x == y) for x in a for y in b) / (len(a) * len(b))
    return less if op in (RelOp.LT, RelOp.LE) else 1 - less


@dataclass(frozen=True)
class TableStats:
    rows: int
    columns: dict[str, dict]


def ingest(df: DataFrame, path: str, sort: list[str], buckets: int, rid: str = "rid", sample_rows: int = SAMPLE_ROWS) -> TableStats:
    """Write df in ranges of sort columns, sorted within files (so that min/max prune), with statistics and a sample beside it."""
    df.repartitionByRange(buckets, *sort).sortWithinPartitions(*sort).write.mode("overwrite").parquet(f"{path}/data")
    stored = df.sparkSession.read.parquet(f"{path}/data")
    plain = [f.name for f in stored.schema if f.dataType.simpleString() in ("int", "bigint", "double", "float", "timestamp", "date", "string")]
    row = stored.agg(F.count("*").alias("rows"), *(x for c in plain for x in (F.min(c).cast("string").alias(f"{c}.min"), F.max(c).cast("string").alias(f"{c}.max"), F.approx_count_distinct(c).alias(f"{c}.ndv"), F.count(c).alias(f"{c}.n")))).first()
    stats = [(c, row[f"{c}.n"], row[f"{c}.ndv"], row[f"{c}.min"], row[f"{c}.max"]) for c in plain]
    df.sparkSession.createDataFrame(stats, "column string, n bigint, ndv bigint, least string, greatest string").coalesce(1).write.mode("overwrite").parquet(f"{path}/stats")
    hash_sample(stored, rid if rid in stored.columns else stored.columns[0], sample_rows).coalesce(1).write.mode("overwrite").parquet(f"{path}/sample")
    return TableStats(row["rows"], {c: {"n": n, "ndv": v, "min": lo, "max": hi} for c, n, v, lo, hi in stats})
