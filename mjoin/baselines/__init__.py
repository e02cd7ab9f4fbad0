"""Other ways to evaluate a multi-join query, to compare with."""

from __future__ import annotations

import itertools
import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..exec.dominance import dominance_sums, fits
from ..exec.ranks import met_sums
from ..exec.single_job import _pair, chain_join, condition, hash_join, prepare, region_names, relations_of, side_names
from ..exec.single_job import from_far_end as _from_far_end
from ..exec.single_job import pairs_of as _pairs
from ..query import MultiJoinQuery, RelOp
from ..sources import materialise


def _labels(q: MultiJoinQuery) -> frozenset[int]:
    return frozenset(p.label for p in q.predicates)


def _steps(q: MultiJoinQuery):
    """Relations in order, each with the conditions that link it to earlier ones."""
    order, names = relations_of(q, _labels(q)), side_names(q, _labels(q))
    for i, a in enumerate(order):
        yield a, prepare(q, a, names), [condition(q, p.label, names) for p in q.predicates if a in p.aliases and (p.aliases - {a}) <= set(order[:i])], names


def _both(conditions):
    out = F.lit(True)
    for c in conditions:
        out &= c
    return out


def _ids(q: MultiJoinQuery, df: DataFrame) -> DataFrame:
    return df.select(*[f"{a}__rid" for a in relations_of(q, _labels(q))])


def native(q: MultiJoinQuery, sums: str | None = None) -> DataFrame:
    """Whatever Catalyst does with the plain joins.

    sums: as in op_by_op; a chain of pairs is joined from its far end, with joins, sums and windows of Catalyst and nothing written between.
    """
    order = sums and _from_far_end(q, sums)
    if not order:
        return hash_join(q)
    names = side_names(q, _labels(q))
    out = _weights_of(q, order[0], names, sums).withColumnRenamed(f"w_{order[0]}", "w_")
    for n, a in enumerate(order[1:], 1):
        out = _next_sums(q, out, a, _weights_of(q, a, names, sums), set(order[:n]), names, 8, window_sums)
    return _as_weighted(out, sums)


def window_sums(left: DataFrame, right: DataFrame, conditions: list[tuple[str, str, str]], weight: str, units: int = 8, bin_rows: int = 1000) -> DataFrame:
    """As dominance_sums, by joins and windows alone.

    The first condition's values are cut into 2^levels bins of about bin_rows rows. Rows of one bin are joined; the bins beyond a left row's
    are at most one node a level of the binary tree over them, in which a running sum along the second condition has its number.
    """
    (u0, op0, v0), (u1, op1, v1) = conditions
    levels = max(1, (max(left.count(), right.count()) // bin_rows).bit_length())
    bins = 1 << levels
    cuts = sorted(set(right.approxQuantile(v0, [i / bins for i in range(1, bins)], 0.25 / bins)))
    # the number of cuts below a value, by bisection: of a < b, a's is not greater, and bins differ only where the values do
    step = lambda c: lambda at, s: F.when(F.get(F.lit(cuts), at + s - 1) < c, at + s).otherwise(at)
    place = lambda c: F.aggregate(F.lit([1 << j for j in reversed(range(levels))]), F.lit(0), step(F.col(c))) if cuts else F.lit(0)
    l, r = left.withColumn("bin_", place(u0)), right.select(v0, v1, weight).withColumn("other_bin_", place(v0))
    compare = lambda u, op, v: RelOp(op).to_column(F.col(u), F.col(v))
    same = l.join(r, (F.col("bin_") == F.col("other_bin_")) & compare(u0, op0, v0) & compare(u1, op1, v1))
    same = same.select(*left.columns, F.col(weight).cast("bigint").alias("s"))
    above = op0 in ("<", "<=")
    row = F.struct(*left.columns)

    def nodes(df: DataFrame, at: str, mine: bool, x: str, w, kept) -> DataFrame:
        # a left row asks for its node's sibling on the side beyond, a right row is in the nodes that are such siblings
        odd = (not mine) == above
        at_level = lambda j: F.shiftright(F.col(at), j)
        asked = [F.when(at_level(j) % 2 == int(odd), F.struct(F.lit(j).alias("level"), (at_level(j).bitwiseXOR(F.lit(1)) if mine else at_level(j)).alias("node"))) for j in range(levels)]
        known = df.withColumn("node_", F.explode(F.filter(F.array(*asked), lambda n: n.isNotNull())))
        return known.select("node_.level", "node_.node", F.col(x).alias("x_"), F.lit(int(mine)).alias("left_"), w.cast("bigint").alias("add_"), kept.cast(left.select(row.alias("r")).schema[0].dataType).alias("row_"))

    both = nodes(l, "bin_", True, u1, F.lit(0), row).unionByName(nodes(r, "other_bin_", False, v1, F.col(weight), F.lit(None)))
    first_come = F.col("left_") if op1 in ("<=", ">=") else -F.col("left_")
    along = Window.partitionBy("level", "node").orderBy(F.col("x_").desc() if op1 in ("<", "<=") else F.col("x_"), first_come).rowsBetween(Window.unboundedPreceding, 0)
    far = both.withColumn("s", F.sum("add_").over(along)).where("left_ = 1 AND s > 0")
    return same.unionByName(far.select("row_.*", "s"))


def _summed(q: MultiJoinQuery, df: DataFrame, seen: set[str], names: dict, alias: str) -> DataFrame:
    """Weighted combinations of the relations seen, summed by the columns that later conditions compare and by alias's column.

    Row ids are those of exec.grouped.weighted; alias's carries the sums on, the others end here.
    """
    later = [p for p in q.predicates if not p.aliases <= seen]
    kept = sorted({names[s.alias, s.expr] for p in later for s in (p.left, p.right) if s.alias in seen})
    w = F.lit(1).cast("bigint")
    for c in df.columns:
        if c.endswith("__rid"):
            w = w * F.col(f"{c}.w")
    sums = df.groupBy(*kept, F.col(f"{alias}__rid.out").alias("out_")).agg(F.sum(w).alias("w_"))
    return sums.select(*kept, F.struct(F.lit(0).cast("bigint").alias("n"), F.col("w_").alias("w"), F.col("out_").alias("out")).alias(f"{alias}__rid"))


def _weights_of(q: MultiJoinQuery, a: str, names: dict, alias: str) -> DataFrame:
    """Compared values of a relation of exec.grouped.weighted with their weight w_a, and for alias its column out_."""
    df = prepare(q, a, names)
    kept = [F.col(f"{a}__rid.out").alias("out_")] if a == alias else []
    return df.select(*(c for c in df.columns if c != f"{a}__rid"), F.col(f"{a}__rid.w").alias(f"w_{a}"), *kept)


def _next_sums(q: MultiJoinQuery, out: DataFrame, a: str, df: DataFrame, seen: set[str], names: dict, k: int, ranked=None) -> DataFrame:
    """Sums w_ of the products of weights of out (w_) and relation a by a's columns that are still needed; out_ comes with the last.

    Two inequalities of numbers are summed by sorted ranks (ranked), other conditions by the join.
    """
    later = [p for p in q.predicates if a in p.aliases and not p.aliases <= seen | {a}]
    keys = sorted({names[s.alias, s.expr] for p in later for s in (p.left, p.right) if s.alias == a}) + [c for c in df.columns if c == "out_"]
    near = [p if p.left.alias == a else p.flip() for p in q.predicates if a in p.aliases and p.aliases - {a} <= seen]
    met = [(names[a, p.left.expr], p.op.value, names[p.right.alias, p.right.expr]) for p in near]
    if fits(df, out, met):
        both = (ranked or dominance_sums)(df, out, met, "w_", k).withColumnRenamed("s", "w_")
    else:
        both = out.join(df, _both([condition(q, p.label, names) for p in near]))
    return both.groupBy(*keys).agg(F.sum(F.col("w_") * F.col(f"w_{a}")).alias("w_"))


def _as_weighted(out: DataFrame, alias: str) -> DataFrame:
    """(out_, w_) as weighted row ids of alias."""
    return out.select(F.struct(F.lit(0).cast("bigint").alias("n"), F.col("w_").alias("w"), F.col("out_").alias("out")).alias(f"{alias}__rid"))


def op_by_op(q: MultiJoinQuery, k: int = 8, sums: str | None = None) -> DataFrame:
    """One job for each join, left-deep in the given order, every result written and read again, as many reducers as there are.

    sums: the relation by whose column weighted combinations are counted; then every result is summed by what is still needed of it,
    and a chain of pairs is joined from its far end.
    """
    order = sums and _from_far_end(q, sums)
    if order:
        names = side_names(q, _labels(q))
        out = _weights_of(q, order[0], names, sums).withColumnRenamed(f"w_{order[0]}", "w_")
        for n, a in enumerate(order[1:], 1):
            out = materialise(_next_sums(q, out.repartition(k), a, _weights_of(q, a, names, sums), set(order[:n]), names, k), "op-by-op")
        return _as_weighted(out, sums)
    out, seen = None, set()
    for a, df, conditions, names in _steps(q):
        seen.add(a)
        if out is None:
            out = df
            continue
        # rows of one value in one task, so that its sums are whole there
        near = out.repartition(k, F.col(f"{sums}__rid.out")) if sums else out.repartition(k)
        both = near.join(df, _both(conditions))
        out = materialise(_summed(q, both, seen, names, sums) if sums else both, "op-by-op")
    return out if sums else _ids(q, out)


def dataflow(q: MultiJoinQuery) -> DataFrame:
    """Joins in program order: by the equalities where there are any, else a product; everything else as filters behind."""
    labels, out, seen = _labels(q), None, []
    order, names = relations_of(q, labels), side_names(q, labels)
    for a in order:
        df = prepare(q, a, names)
        if out is None:
            out = df
        else:
            near = [p for p in q.predicates if a in p.aliases and (p.aliases - {a}) <= set(seen)]
            equal = [condition(q, p.label, names) for p in near if p.op is RelOp.EQ]
            out = out.join(df, _both(equal)) if equal else out.crossJoin(df)
            out = out.where(_both([condition(q, p.label, names) for p in near if p.op is not RelOp.EQ]))
        seen.append(a)
    return _ids(q, out)


def correlation_merge(q: MultiJoinQuery, share: tuple[str, ...] = ("input", "transit", "flow"), sums: str | None = None, k: int = 8) -> DataFrame:
    """Jobs fused by what they share, without regard to units.

    input: relations of one table are read and cached once; transit: consecutive joins on one key keep its partitioning;
    flow: a join whose input is the former's output runs in its job, without writing between them.
    sums: as in op_by_op; results are summed before they are written or moved, a chain of pairs is joined from its far end.
    """
    cached: dict[int, DataFrame] = {}
    if "input" in share:
        cached = {id(df): df.persist() for df in {id(d): d for d in q.relations.values()}.values()}
        q = MultiJoinQuery({a: cached[id(d)] for a, d in q.relations.items()}, q.predicates, q.select, q.filters, q.rid)
    order = sums and _from_far_end(q, sums)
    if order:
        done = _correlated_sums(q, share, sums, k, order)
        for df in cached.values():
            df.unpersist()
        return done
    out, keyed, seen, whole = None, None, set(), True
    for a, df, conditions, names in _steps(q):
        if out is None:
            out, seen = df, {a}
            if sums:
                out = out.repartition(k, F.col(f"{sums}__rid.out"))
            continue
        if "transit" in share:
            equal = [p for p in q.predicates if p.op is RelOp.EQ and a in p.aliases and p.aliases - {a} <= seen]
            if equal:
                own, other = (equal[0].left, equal[0].right) if equal[0].left.alias == a else (equal[0].right, equal[0].left)
                key = names[other.alias, other.expr]
                if keyed != key:
                    out = (_summed(q, out, seen, names, sums) if sums and not whole else out).repartition(key)
                keyed = key
                df = df.repartition(names[own.alias, own.expr])
        out, whole = out.join(df, _both(conditions)), False
        seen.add(a)
        if "flow" not in share:
            out, whole = materialise(_summed(q, out, seen, names, sums) if sums else out, "correlated"), True
    done = out if sums and whole else materialise(_summed(q, out, seen, names, sums) if sums else _ids(q, out), "correlation")
    for df in cached.values():
        df.unpersist()
    return done


def _correlated_sums(q: MultiJoinQuery, share: tuple[str, ...], alias: str, k: int, order: list[str]) -> DataFrame:
    """correlation_merge of a chain of pairs by sums, in the order given."""
    names, keyed = side_names(q, _labels(q)), None
    out = _weights_of(q, order[0], names, alias).withColumnRenamed(f"w_{order[0]}", "w_")
    for n, a in enumerate(order[1:], 1):
        df = _weights_of(q, a, names, alias)
        equal = [p if p.left.alias == a else p.flip() for p in q.predicates if p.op is RelOp.EQ and a in p.aliases and p.aliases - {a} <= set(order[:n])]
        if "transit" in share and equal:
            own, key = names[a, equal[0].left.expr], names[equal[0].right.alias, equal[0].right.expr]
            out, df = out if keyed == key else out.repartition(key), df.repartition(own)
            keyed = own
        out = _next_sums(q, out, a, df, set(order[:n]), names, k)
        if "flow" not in share or a == order[-1]:
            out = materialise(out, "correlated")
    return _as_weighted(out, alias)


def pairwise_rect(q: MultiJoinQuery, k: int = 8, sums: str | None = None) -> DataFrame:
    """A job for each pair of relations over rectangles of their product; results written, then met on shared ids.

    sums: as in op_by_op (see pairs_summed); for conditions that make a tree of the relations.
    """
    from ..exec.merge import merge_outputs

    if sums:
        return pairs_summed(q, sums, dict.fromkeys(_pairs(q), k))
    return _ids(q, merge_outputs([materialise(chain_join(q, labels, k, curve="grid"), "rect") for labels in _pairs(q).values()]))


def pairs_summed(q: MultiJoinQuery, alias: str, units: dict[frozenset, int]) -> DataFrame:
    """Jobs of pairs over weighted values, from alias outwards; each is summed by the values at which it meets the next ones.

    The nearer relation of a pair is alias itself, or the distinct values of it that the pair compares, each once: its weights are in
    the pair before. Results are written and met on those values. A chain of pairs goes from its far end instead.
    """
    groups, done, out = _pairs(q), {alias}, None
    if order := _from_far_end(q, alias):
        return _pairs_from_far_end(q, alias, units, order)
    if sum(alias in pair for pair in groups) != 1 or len(groups) != len(q.relations) - 1:
        raise ValueError("a tree of pairs is needed, with one pair at the counted relation")
    columns = lambda a, labels: sorted({s.expr for p in q.predicates if p.label in labels for s in (p.left, p.right) if s.alias == a})
    while groups:
        pair = next((g for g in groups if len(g & done) == 1), None)
        if pair is None:
            raise ValueError("the conditions must connect all relations")
        labels, (near,), (far,) = groups.pop(pair), pair & done, pair - done
        done.add(far)
        own, on = columns(near, labels), columns(far, set().union(*(x for g, x in groups.items() if far in g)))
        frame = q.relations[near]
        if near != alias:
            frame = frame.select(*own).distinct().withColumn("rid", F.struct(F.xxhash64(*own).alias("n"), F.lit(1).cast("bigint").alias("w")))
        part = MultiJoinQuery({near: frame, far: q.relations[far]}, tuple(p for p in q.predicates if p.label in labels))
        both = chain_join(part, None, units[pair], curve="grid", hint="shuffle_hash", payload={near: own, far: on})
        keys = [F.col(f"{alias}__rid.out").alias("out_")] if near == alias else [F.col(f"{near}__{c}") for c in own]
        met = materialise(both.groupBy(*keys, *(f"{far}__{c}" for c in on)).agg(F.sum(F.col(f"{near}__rid.w") * F.col(f"{far}__rid.w")).alias("w_" if out is None else f"w_{far}")), "pair")
        # a value of a further relation is in own once it is met
        out = met if out is None else out.join(met, [f"{near}__{c}" for c in own]).withColumn("w_", F.col("w_") * F.col(f"w_{far}")).drop(f"w_{far}")
    sums = out.groupBy("out_").agg(F.sum("w_").alias("w_"))
    return sums.select(F.struct(F.lit(0).cast("bigint").alias("n"), F.col("w_").alias("w"), F.col("out_").alias("out")).alias(f"{alias}__rid"))


def _pairs_from_far_end(q: MultiJoinQuery, alias: str, units: dict[frozenset, int], order: list[str]) -> DataFrame:
    """pairs_summed of a chain in the order given: a pair's result is a sum for each distinct value of its nearer relation, written and met on it.

    Two inequalities of numbers are summed by sorted ranks, other pairs over rectangles.
    """
    groups, names = _pairs(q), side_names(q, _labels(q))
    out = _weights_of(q, order[0], names, alias).withColumnRenamed(f"w_{order[0]}", "w_")
    for far, near in itertools.pairwise(order):
        labels, k = groups[frozenset({far, near})], units[frozenset({far, near})]
        conditions = tuple(p if p.left.alias == near else p.flip() for p in q.predicates if p.label in labels)
        met = [(names[near, p.left.expr], p.op.value, names[far, p.right.expr]) for p in conditions]
        df, own = _weights_of(q, near, names, alias), sorted({p.left.expr for p in conditions})
        on = [names[near, x] for x in own]
        values = df.select(*on).distinct()
        if fits(values, out, met):
            both = dominance_sums(values, out, met, "w_", k).withColumnRenamed("s", "w_")
        else:
            frames = {}
            for a, frame, exprs, w in ((near, values, own, F.lit(1)), (far, out, sorted({p.right.expr for p in conditions}), F.col("w_"))):
                kept = [F.col(names[a, x]).alias(x) for x in exprs]
                frames[a] = frame.select(*kept, F.struct(F.xxhash64(*(names[a, x] for x in exprs)).alias("n"), w.cast("bigint").alias("w")).alias("rid"))
            both = chain_join(MultiJoinQuery(frames, conditions), None, k, curve="grid", hint="shuffle_hash", payload={near: own})
            both = both.select(*(F.col(f"{near}__{x}").alias(names[near, x]) for x in own), F.col(f"{far}__rid.w").alias("w_"))
        written = materialise(both.groupBy(*on).agg(F.sum("w_").alias("w_")), "pair")
        later = [p for p in q.predicates if near in p.aliases and p.label not in labels]
        keys = sorted({names[s.alias, s.expr] for p in later for s in (p.left, p.right) if s.alias == near}) + [c for c in df.columns if c == "out_"]
        out = df.join(written, on).groupBy(*keys).agg(F.sum(F.col("w_") * F.col(f"w_{near}")).alias("w_"))
    return _as_weighted(out, alias)


def pairwise_scheduled(q: MultiJoinQuery, units: int = 8, sums: str | None = None) -> DataFrame:
    """Pairs as jobs, scheduled by cost. sums: as in op_by_op, with the units that the schedule gives to each pair."""
    from ..api import MultiJoinEngine
    from ..plan.planner import name_of

    spark = next(iter(q.relations.values())).sparkSession
    if sums:
        plan = MultiJoinEngine(spark, units).plan(q, "pairwise", infer=False)
        share = {p.name: p.units for p in plan.schedule.placed}
        given = {pair: share.get(name_of(frozenset(labels)), units) for pair, labels in _pairs(q).items()}
        return pairs_summed(q, sums, given)
    return _ids(q, MultiJoinEngine(spark, units).ids(q, strategy="pairwise", infer=False))


def best_shares(sizes: dict[str, tuple[float, list[str]]], attributes: list[str], k: int) -> dict[str, int]:
    """Split k among attributes, shares multiplying to at most k, with the fewest copies: a relation is copied along the attributes it lacks."""
    best, cost = {a: 1 for a in attributes}, float("inf")
    for shares in itertools.product(range(1, k + 1), repeat=len(attributes)):
        n = 1
        for s in shares:
            n *= s
        if n > k or n * 2 <= k:
            continue
        of = dict(zip(attributes, shares, strict=True))
        total = sum(rows * n / max(1, _product(of[a] for a in own)) for rows, own in sizes.values())
        if total < cost:
            best, cost = of, total
    return best


def _product(xs) -> int:
    out = 1
    for x in xs:
        out *= x
    return out


def shares_equi(q: MultiJoinQuery, k: int = 8) -> DataFrame:
    """All equalities in one job: every join attribute has a share of the reducers, rows hash on those they have and are copied along the others."""
    labels = _labels(q)
    if any(p.op is not RelOp.EQ for p in q.predicates):
        raise ValueError("only equalities")
    # attributes: classes of equal expressions
    group: dict[tuple[str, str], int] = {}
    for p in q.predicates:
        ends = [(p.left.alias, p.left.expr), (p.right.alias, p.right.expr)]
        have = sorted({group[e] for e in ends if e in group})
        to = have[0] if have else len(group)
        for e in list(group):
            if group[e] in have:
                group[e] = to
        for e in ends:
            group[e] = to
    attributes = [str(g) for g in sorted(set(group.values()))]
    order, names = relations_of(q, labels), side_names(q, labels)
    frames = {a: prepare(q, a, names) for a in order}
    own = {a: {str(group[e]): names[e] for e in group if e[0] == a} for a in order}
    shares = best_shares({a: (frames[a].count(), list(own[a])) for a in order}, attributes, k)
    total = _product(shares.values())
    regions = region_names(total, int(frames[order[0]].sparkSession.conf.get("spark.sql.shuffle.partitions")))
    out = None
    for i, a in enumerate(order):
        cell = F.array(F.lit(0))
        for g in attributes:
            step = F.array(F.pmod(F.xxhash64(own[a][g]), F.lit(shares[g])).cast("int")) if g in own[a] else F.sequence(F.lit(0), F.lit(shares[g] - 1))
            cell = _spread(cell, step, shares[g])
        named = F.transform(cell, lambda c: F.element_at(F.lit(regions), c + 1))
        df = frames[a].withColumn(f"{a}__region", F.explode(named)).repartition(total, f"{a}__region")
        if out is None:
            out = df
        else:
            on = F.col(f"{order[0]}__region") == F.col(f"{a}__region")
            for p in q.predicates:
                if a in p.aliases and (p.aliases - {a}) <= set(order[:i]):
                    on &= condition(q, p.label, names)
            out = out.join(df, on)
    return _ids(q, out)


def _spread(cell, step, n: int):
    """All numbers c * n + x of c in cell and x in step."""
    return F.flatten(F.transform(cell, lambda c: F.transform(step, lambda x: c * n + x)))


def hash_equi(left: DataFrame, right: DataFrame, on: str | list[str]) -> DataFrame:
    """The join attribute as the key."""
    return left.join(right, on)


def replicate_all(q: MultiJoinQuery, most_bytes: int = 64 << 20, sums: str | None = None) -> DataFrame:
    """The first relation stays, every other goes to all tasks; beyond most_bytes (rows counted, by the width of their columns) it is shuffled by Catalyst's own choice.

    sums: as in op_by_op; a chain of pairs is joined from its far end, and what goes to all tasks is summed by what is still needed of it.
    """
    order = sums and _from_far_end(q, sums)
    if order:
        return _replicated_sums(q, sums, most_bytes, order)
    out = None
    for a, df, conditions, _ in _steps(q):
        if out is None:
            out = df
        else:
            out = out.join(F.broadcast(df) if _bytes(df) <= most_bytes else df, _both(conditions))
    return _ids(q, out)


def _bytes(df: DataFrame) -> int:
    return df.count() * sum(f.dataType.typeName() in ("string", "binary") and 64 or 8 for f in df.schema)


def _replicated_sums(q: MultiJoinQuery, alias: str, most_bytes: int, order: list[str]) -> DataFrame:
    """replicate_all of a chain of pairs by sums, in the order given: what is joined so far goes to all tasks of the next relation.

    Two inequalities of numbers are summed by sorted ranks in each task.
    """
    names = side_names(q, _labels(q))
    out = _weights_of(q, order[0], names, alias).withColumnRenamed(f"w_{order[0]}", "w_")
    for n, a in enumerate(order[1:], 1):
        df, seen = _weights_of(q, a, names, alias), set(order[:n])
        out = materialise(out, "replicated") if n > 1 else out
        if _bytes(out) <= most_bytes:
            out = _next_sums(q, F.broadcast(out), a, df, seen, names, 8, _sums_beside)
        else:
            out = _next_sums(q, out, a, df, seen, names, 8)
    return _as_weighted(out, alias)


def _sums_beside(left: DataFrame, right: DataFrame, conditions: list[tuple[str, str, str]], weight: str, units: int = 8) -> DataFrame:
    """As dominance_sums, with all of right in every task: left stays where it is, nothing is shuffled."""
    rows = right.select(*dict.fromkeys([v for _, _, v in conditions]), weight).toArrow().to_pandas()
    shared = left.sparkSession.sparkContext.broadcast(rows)
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in left.schema) + ", s bigint"

    def run(batches):
        rt, held = shared.value, []

        def met():
            lt = pa.Table.from_batches(held)
            own = lt.select(list(dict.fromkeys(u for u, _, _ in conditions))).to_pandas()
            s = met_sums([(*_pair(own[u], rt[v]), op) for u, op, v in conditions], rt[weight].to_numpy(np.int64))
            held.clear()
            return lt.append_column("s", pa.array(s)).filter(pa.array(s > 0)).to_batches()

        for batch in batches:
            held.append(batch)
            # ranks of right are worth as many rows of left
            if sum(b.num_rows for b in held) >= max(100_000, len(rt)):
                yield from met()
        if held:
            yield from met()

    return left.mapInArrow(run, schema)


def brute_force(q: MultiJoinQuery) -> DataFrame:
    """The whole product and a filter: an oracle for small inputs."""
    labels = _labels(q)
    order, names = relations_of(q, labels), side_names(q, labels)
    out = None
    for a in order:
        df = prepare(q, a, names)
        out = df if out is None else out.crossJoin(df)
    return _ids(q, out.where(_both([condition(q, k, names) for k in sorted(labels)])))


def key_set_join(df: DataFrame, rid: str, keys: F.Column, verify, payload: str) -> DataFrame:
    """Similarity join: rows with a key in common are candidates once, in the least key they share; verify decides.

    keys: an array of ints for each row. verify(left, right) is a condition over the payload columns.
    """
    base = df.select(F.col(rid).alias("rid"), F.array_distinct(keys).alias("keys"), F.col(payload).alias("v"))
    a = base.select(F.col("rid").alias("left_rid"), F.col("keys").alias("left_keys"), F.col("v").alias("left_v"), F.explode("keys").alias("key"))
    b = base.select(F.col("rid").alias("right_rid"), F.col("keys").alias("right_keys"), F.col("v").alias("right_v"), F.explode("keys").alias("key"))
    both = a.join(b, "key").where(F.col("left_rid") < F.col("right_rid"))
    first = F.array_min(F.array_intersect("left_keys", "right_keys")) == F.col("key")
    return both.where(first & verify(F.col("left_v"), F.col("right_v"))).select("left_rid", "right_rid")


def key_set_pairs(df: DataFrame, rid: str, keys: F.Column, vector: str, threshold: float, block: int = 1000) -> DataFrame:
    """key_set_join of vectors by their cosine: the rows of a key are compared as matrices, in blocks any two of which are one task.

    keys: an array with one key for each band, of which no two bands share any. A pair is given out at the least key that it shares.
    """
    base = materialise(df.select(F.col(rid).alias("rid"), F.col(vector).alias("v"), keys.alias("keys")).where(F.col("rid").isNotNull() & F.col("v").isNotNull()), "keys")
    each = base.withColumn("key", F.explode("keys"))
    most = each.groupBy("key").count().agg(F.max("count")).first()[0] or 1
    blocks = -(-most // block)
    own = F.pmod(F.xxhash64(F.lit("block"), "rid"), F.lit(blocks)).cast("int")
    part = lambda o: F.struct((F.least(o, F.col("own")) * blocks + F.greatest(o, F.col("own"))).alias("part"), (o < F.col("own")).cast("int").alias("side"))
    dealt = each.withColumn("own", own).withColumn("x", F.explode(F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), part))).select("key", "rid", "v", "keys", "x.part", "x.side")
    kind = next(f.dataType for f in base.schema if f.name == "rid").simpleString()

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        left, right = (rows[rows["side"] == s] for s in (0, 1))
        # part of two blocks or of one with itself
        alone = key[1] // blocks == key[1] % blocks
        right = left if alone else right
        if not len(left) or not len(right):
            return pd.DataFrame({"left_rid": [], "right_rid": []})
        a, b = (np.stack(x["v"].to_numpy()).astype(np.float64) for x in (left, right))
        i, j = np.nonzero(a @ b.T >= threshold * np.sqrt(np.outer((a * a).sum(1), (b * b).sum(1))))
        x, y = left["rid"].to_numpy()[i], right["rid"].to_numpy()[j]
        keep = x < y if alone else x != y
        i, j, x, y = i[keep], j[keep], x[keep], y[keep]
        k, m = (np.stack(t["keys"].to_numpy()) for t in (left, right))
        first = np.where(k[i] == m[j], k[i], np.iinfo(np.int32).max).min(1) == key[0]
        return pd.DataFrame({"left_rid": np.minimum(x, y)[first], "right_rid": np.maximum(x, y)[first]})

    return dealt.groupBy("key", "part").applyInPandas(run, f"left_rid {kind}, right_rid {kind}")


def bands_for(threshold: float, rows: int, recall: float) -> int:
    """Bands of so many planes each at which two vectors of the threshold's cosine share a key with the recall."""
    same = 1 - math.acos(threshold) / math.pi
    return math.ceil(math.log(1 - recall) / math.log(1 - same**rows))


def block_pairs(df: DataFrame, rid: str, vector: str, threshold: float, block: int = 1000) -> DataFrame:
    """All pairs (left_rid < right_rid) of vectors of at least the threshold's cosine: the exact way for key_set_join.

    Rows are dealt into blocks, any two of which are one task: each row is copied as often as there are blocks, no task
    holds more than two, and no keys are needed. The work is that of all pairs.
    """
    rows = df.select(F.col(rid).alias("rid"), F.col(vector).alias("v")).where(F.col(rid).isNotNull() & F.col(vector).isNotNull())
    blocks = max(1, -(-rows.count() // block))
    own = F.pmod(F.xxhash64(F.lit("block"), "rid"), F.lit(blocks)).cast("int")
    part = lambda o: F.struct((F.least(o, F.col("own")) * blocks + F.greatest(o, F.col("own"))).alias("part"), (o < F.col("own")).cast("int").alias("side"))
    dealt = rows.withColumn("own", own).select("rid", "v", F.explode(F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), part)).alias("x")).select("rid", "v", "x.part", "x.side")
    kind = next(f.dataType for f in rows.schema if f.name == "rid").simpleString()

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        left, right = (rows[rows["side"] == s] for s in (0, 1))
        alone = not len(right)
        right = left if alone else right
        a, b = (np.stack(x["v"].to_numpy()).astype(np.float64) if len(x) else np.empty((0, 0)) for x in (left, right))
        if not len(a) or not len(b):
            return pd.DataFrame({"left_rid": [], "right_rid": []})
        norm = np.sqrt(np.outer((a * a).sum(1), (b * b).sum(1)))
        i, j = np.nonzero(a @ b.T >= threshold * norm)
        x, y = left["rid"].to_numpy()[i], right["rid"].to_numpy()[j]
        keep = x < y if alone else x != y
        return pd.DataFrame({"left_rid": np.minimum(x, y)[keep], "right_rid": np.maximum(x, y)[keep]})

    return dealt.groupBy("part").applyInPandas(run, f"left_rid {kind}, right_rid {kind}")
