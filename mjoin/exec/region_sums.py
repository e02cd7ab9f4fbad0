"""A chain of pairs over a cube, summed inside its regions: no combinations are visited."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..partition.assign import RegionAssignment
from ..query import MultiJoinQuery
from .dominance import fits
from .ranks import met_sums
from .single_job import _pair, condition, owned


def region_sums(q: MultiJoinQuery, routed: dict[str, DataFrame], chain: list[str], order: list[str], names: dict, a: RegionAssignment, regions: list[int], hint: str) -> DataFrame:
    """Row ids of the chain's last relation with sums of products of weights, of the combinations whose cell each region owns.

    routed: relations of exec.grouped.weighted dealt to their regions. Every result is summed by region, the coordinates so far (their
    cell decides at the end) and the values that are still compared. At the last pair two inequalities of numbers go by sorted ranks.
    """
    first, seen, last = chain[0], {chain[0]}, chain[-1]
    out = routed[first].withColumn("w_", F.col(f"{first}__rid.w")).drop(f"{first}__rid")
    for before, alias in zip(chain, chain[1:], strict=False):
        near = [p if p.left.alias == alias else p.flip() for p in q.predicates if alias in p.aliases and p.aliases - {alias} <= seen]
        seen.add(alias)
        df, cells = routed[alias], [f"{x}__c" for x in chain if x in seen]
        met = [(names[alias, p.left.expr], p.op.value, names[p.right.alias, p.right.expr]) for p in near]
        if alias == last:
            df = df.select("*", F.col(f"{alias}__rid.w").alias(f"w_{alias}"), F.col(f"{alias}__rid.out").alias("out_")).drop(f"{alias}__rid")
            if fits(df, out, met):
                both = _ranked(df, out, met, alias, before, order, a, regions)
            else:
                both = owned(_met(q, out, df, before, alias, near, names, hint), order, a, regions)
            sums = both.groupBy("out_").agg(F.sum(F.col("w_") * F.col(f"w_{alias}")).alias("w_"))
            return sums.select(F.struct(F.lit(0).cast("bigint").alias("n"), F.col("w_").alias("w"), F.col("out_").alias("out")).alias(f"{alias}__rid"))
        keys = sorted({names[s.alias, s.expr] for p in q.predicates if not p.aliases <= seen for s in (p.left, p.right) if s.alias == alias})
        both = _met(q, out, df, before, alias, near, names, hint)
        out = both.groupBy(f"{alias}__region", *cells, *keys).agg(F.sum(F.col("w_") * F.col(f"{alias}__rid.w")).alias("w_"))
    raise ValueError("a chain has two relations or more")


def _met(q: MultiJoinQuery, out: DataFrame, df: DataFrame, before: str, alias: str, near: list, names: dict, hint: str) -> DataFrame:
    on = F.col(f"{before}__region") == F.col(f"{alias}__region")
    for p in near:
        on &= condition(q, p.label, names)
    return out.join(df.hint(hint), on)


def _ranked(left: DataFrame, right: DataFrame, conditions: list[tuple[str, str, str]], alias: str, before: str, order: list[str], a: RegionAssignment, regions: list[int]) -> DataFrame:
    """Weight and out_ of the left rows of a region, and w_: the sum over the right rows that meet the conditions in a cell of the region."""
    own, others = f"{alias}__c", [f"{x}__c" for x in order if x != alias]
    shape, number, owner = [1 << b for b in a.bits], {v: r for r, v in enumerate(regions)}, a.owner
    lefts, rights = list(dict.fromkeys(u for u, _, _ in conditions)), list(dict.fromkeys(v for _, _, v in conditions))
    kept = [f"w_{alias}", "out_"]
    kinds = {f.name: f.dataType.simpleString() for f in left.schema}

    def run(key: tuple, lt: pa.Table, rt: pa.Table) -> pa.Table:
        l, r = lt.select([own, *lefts]).to_pandas(), rt.select([*others, *rights, "w_"]).to_pandas()
        mine, s = l[own].to_numpy(), np.zeros(len(l), np.int64)
        sides = [(*_pair(l[u], r[v]), op) for u, op, v in conditions]
        w = r["w_"].to_numpy(np.int64)
        for c in np.unique(mine) if len(r) else ():
            at = np.ravel_multi_index([np.full(len(r), c) if f"{x}__c" == own else r[f"{x}__c"].to_numpy() for x in order], shape)
            rows, theirs = np.flatnonzero(mine == c), np.flatnonzero(owner[at] == number[key[0].as_py()])
            s[rows] = met_sums([(x[rows], v[theirs], op) for x, v, op in sides], w[theirs])
        some = s > 0
        return lt.select(kept).filter(pa.array(some)).append_column("w_", pa.array(s[some]))

    both = left.groupBy(f"{alias}__region").cogroup(right.groupBy(f"{before}__region"))
    return both.applyInArrow(run, ", ".join(f"`{c}` {kinds[c]}" for c in kept) + ", w_ bigint")
