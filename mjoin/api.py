"""The engine: plan, explain and run a multi-join query."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .exec.grouped import grouped_counts
from .exec.merge import count_by, hydrate, per_id
from .exec.runner import Run, run_plan
from .exec.single_job import answer, co_partitioned, relations_of
from .plan.infer import tightened, with_implied
from .plan.planner import Plan, Planner, explain
from .query import MultiJoinQuery, multi_join
from .sources import materialise
from .sqlfront import parse_sql

__all__ = ["MultiJoinEngine", "multi_join"]


class MultiJoinEngine:
    def __init__(self, spark: SparkSession, units: int | None = None, planner: Planner | None = None):
        self.spark, self.units, self.planner = spark, units or spark.sparkContext.defaultParallelism, planner or Planner()
        self.last: tuple[Plan, Run] | None = None

    def plan(self, q: MultiJoinQuery, strategy: str = "planned", jobs: list | None = None, infer: bool = True) -> Plan:
        return self.planner.plan(self._inferred(q, strategy) if infer else q, self.units, None, strategy, jobs)

    def _inferred(self, q: MultiJoinQuery, strategy: str) -> MultiJoinQuery:
        """With what follows from the conditions; a job for each pair gets all that holds of its pair."""
        return with_implied(tightened(q)) if strategy == "pairwise" else tightened(q)

    def explain(self, q: MultiJoinQuery, **options) -> DataFrame:
        return explain(self.spark, self.plan(q, **options))

    def ids(self, q: MultiJoinQuery, strategy: str = "planned", jobs: list | None = None, infer: bool = True, curve: str = "auto", finish=None) -> DataFrame:
        """Row ids alias__rid of all combinations, or what finish makes of them before the last of them are written."""
        q = self._inferred(q, strategy) if infer and jobs is None else q
        plan = self.planner.plan(q, self.units, None, strategy, jobs)
        run = run_plan(q, plan, self.units, curve=curve, finish=finish)
        self.last = plan, run
        return run.ids

    def run(self, q: MultiJoinQuery, **options) -> DataFrame:
        """The answer's columns."""
        return hydrate(q, self.ids(q, **options))

    def sql(self, text: str, tables: dict[str, DataFrame] | None = None, rid: dict[str, str] | None = None, **options) -> DataFrame:
        """A plain join query in SQL text, planned and run."""
        return self.run(parse_sql(self.spark, text, tables, rid), **options)

    def counts(self, q: MultiJoinQuery, alias: str, column: str, name: str = "id", **options) -> DataFrame:
        """Combinations by a column of one relation: (name, n), by giving all of them out to the counting."""
        return count_by(q, self.ids(q, finish=per_id(alias), **options), alias, column, name)

    def grouped_counts(self, q: MultiJoinQuery, alias: str, column: str, name: str = "id", infer: bool = True) -> DataFrame:
        """The same numbers without visiting each combination: equal rows count once, leaves of the join graph are folded in."""
        return grouped_counts(tightened(q) if infer else q, alias, column, name, self.units)

    def single(self, q: MultiJoinQuery, k: int | None = None, **options) -> DataFrame:
        """The answer by one job that carries its columns, written once; a cube's shape follows the sizes of its relations."""
        if options.get("method") == "cube" and "cards" not in options:
            order = relations_of(q, frozenset(p.label for p in q.predicates))
            sizes = {(id(q.relations[a]), q.filters.get(a)): a for a in order}
            counted = {key: max(1, q.filtered(a).count()) for key, a in sizes.items()}
            options |= {"cards": [counted[id(q.relations[a]), q.filters.get(a)] for a in order], "curve": options.get("curve", "auto")}
        with co_partitioned(self.spark):
            return materialise(answer(q, k or self.units, **options), "single")
