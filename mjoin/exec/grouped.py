"""Numbers of combinations by a column without giving the combinations out: equal rows are counted first, leaves are folded in."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query import MultiJoinQuery, Predicate, Side
from ..sources import materialise
from .dominance import dominance_sums, fits
from .single_job import co_partitioned, run_trail


def _collapsed(q: MultiJoinQuery, alias: str, exprs: list[str], more: list[str]) -> DataFrame:
    """Distinct values of the compared expressions (v0, v1, ...) and further columns of a relation, with their number of rows."""
    df = q.filtered(alias).select(*(F.expr(e).alias(f"v{n}") for n, e in enumerate(exprs)), *(F.col(c).alias(f"out_{c}") for c in more))
    for n in range(len(exprs)):
        df = df.where(F.col(f"v{n}").isNotNull())
    return _numbered(df.groupBy(*df.columns).agg(F.count("*").alias("w")))


def _numbered(df: DataFrame) -> DataFrame:
    """A row id from the values: it only draws coordinates, and equal rows are one row here."""
    keys = [c for c in df.columns if c not in ("w", "rid")]
    return df.withColumn("rid", F.xxhash64(*keys) if keys else F.lit(0).cast("bigint"))


def grouped_counts(q: MultiJoinQuery, alias: str, column: str, name: str = "id", k: int = 8) -> DataFrame:
    """(name, n): combinations of q by a column of alias; n is exact however many there are.

    Every relation becomes its distinct compared values with a weight. A relation that meets only one other is a
    leaf: one job joins the two, sums the products of weights by the other's values, and the leaf is gone. What
    remains around alias is one job. Jobs are cubes, or hash joins where equalities connect them; sums are
    partial in the regions, so the shuffles carry values and not combinations. Two relations under one or two
    inequalities of numbers are summed by sorted ranks and visit no pairs.
    """
    spark = q.relations[alias].sparkSession
    exprs = {a: sorted({s.expr for p in q.predicates for s in (p.left, p.right) if s.alias == a}) for a in q.relations}
    place = {a: {e: f"v{n}" for n, e in enumerate(x)} for a, x in exprs.items()}
    frames = {a: _collapsed(q, a, exprs[a], [column] if a == alias else []) for a in q.relations}
    left = [Predicate(p.label, Side(p.left.alias, place[p.left.alias][p.left.expr]), p.op, Side(p.right.alias, place[p.right.alias][p.right.expr])) for p in q.predicates]

    def joined(aliases: set[str], conditions: list[Predicate]) -> DataFrame:
        part = MultiJoinQuery({a: frames[a] for a in aliases}, tuple(conditions))
        return run_trail(part, None, k, {a: [c for c in frames[a].columns if c != "rid"] for a in aliases})

    def summed(a: str, other: str, conditions: list[Predicate], keys: dict[str, str]) -> DataFrame:
        """The sums of products of weights of two relations by columns of a (name: new name)."""
        met = [(p if p.left.alias == a else p.flip()) for p in conditions]
        met = [(p.left.expr, p.op.value, p.right.expr) for p in met]
        x, y = frames[a], frames[other]
        if len(met) == 1:
            # a second condition that always holds
            x, y, met = x.withColumn("same_", F.lit(0)), y.withColumn("same_", F.lit(0)), [*met, ("same_", "<=", "same_")]
        if fits(x, y, met):
            # both are read several times
            x, y = materialise(x, "weighted"), materialise(y, "weighted")
            part = dominance_sums(x, y, met, "w", k)
            return part.groupBy(*(F.col(c).alias(n) for c, n in keys.items())).agg(F.sum(F.col("w") * F.col("s")).alias("w"))
        return joined({a, other}, conditions).groupBy(*(F.col(f"{a}__{c}").alias(n) for c, n in keys.items())).agg(weight((other, a)))

    weight = lambda aliases: F.sum(_product([F.col(f"{a}__w") for a in aliases])).alias("w")
    with co_partitioned(spark):
        while True:
            near = {a: {b for p in left if a in p.aliases for b in p.aliases - {a}} for a in frames}
            leaf = next((a for a in frames if a != alias and len(near[a]) == 1), None)
            if leaf is None:
                break
            parent = near[leaf].pop()
            # values of the parent that only the leaf asked for end with it
            own = [p for p in left if leaf in p.aliases]
            left = [p for p in left if leaf not in p.aliases]
            needed = {s.expr for p in left for s in (p.left, p.right) if s.alias == parent}
            keys = [c for c in frames[parent].columns if c.startswith("out_") or c in needed]
            frames[parent] = materialise(_numbered(summed(parent, leaf, own, {c: c for c in keys})), "folded")
            del frames[leaf]
        if len(frames) == 2:
            other = next(a for a in frames if a != alias)
            out = summed(alias, other, left, {f"out_{column}": name}).withColumnRenamed("w", "n")
            return materialise(out.withColumn("n", F.col("n").cast("bigint")), "counted")
        rest = joined(set(frames), left) if len(frames) > 1 else frames[alias].select(*(F.col(c).alias(f"{alias}__{c}") for c in frames[alias].columns))
        out = rest.groupBy(F.col(f"{alias}__out_{column}").alias(name)).agg(weight(frames).alias("n"))
        return materialise(out.withColumn("n", F.col("n").cast("bigint")), "counted")


def _product(columns: list):
    out = columns[0]
    for c in columns[1:]:
        out = out * c
    return out


def weighted(q: MultiJoinQuery, alias: str, column: str, parts: int = 8) -> MultiJoinQuery:
    """The same query over the distinct compared values of each relation, written once; a row id is a struct of number (n), weight (w) and,
    for alias, the column (out). A combination stands for as many as the product of its weights (weigh)."""
    exprs = {a: sorted({s.expr for p in q.predicates for s in (p.left, p.right) if s.alias == a}) for a in q.relations}
    place = {a: {e: f"v{n}" for n, e in enumerate(x)} for a, x in exprs.items()}
    frames = {}
    for a in q.relations:
        df = _collapsed(q, a, exprs[a], [column] if a == alias else [])
        kept = [F.col(f"out_{column}").alias("out")] if a == alias else []
        own = df.select(*place[a].values(), F.struct(F.monotonically_increasing_id().alias("n"), "w", *kept).alias("rid"))
        frames[a] = materialise(own.repartition(parts), "values")
    left = tuple(Predicate(p.label, Side(p.left.alias, place[p.left.alias][p.left.expr]), p.op, Side(p.right.alias, place[p.right.alias][p.right.expr])) for p in q.predicates)
    return MultiJoinQuery(frames, left)


def weigh(ids: DataFrame, alias: str, name: str = "id") -> DataFrame:
    """(name, n) of combinations of weighted rows, by alias's column."""
    n = _product([F.col(f"{c}.w") for c in ids.columns])
    return ids.groupBy(F.col(f"{alias}__rid.out").alias(name)).agg(F.sum(n).cast("bigint").alias("n"))
