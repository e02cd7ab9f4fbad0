"""Merging outputs of jobs on the ids of the relations that they share, and fetching columns at the end."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query import MultiJoinQuery
from .single_job import payload_of, project


def shared_ids(a: DataFrame, b: DataFrame) -> list[str]:
    return [c for c in a.columns if c in b.columns and c.endswith("__rid")]


def merge_outputs(outputs: list[DataFrame]) -> DataFrame:
    """Equi joins on shared ids, each time with an output that shares most; ids are unique within a relation."""
    out, rest = outputs[0], list(outputs[1:])
    while rest:
        best = max(rest, key=lambda o: len(shared_ids(out, o)))
        if not (on := shared_ids(out, best)):
            raise ValueError("outputs share no relation")
        out = out.join(best, on)
        rest.remove(best)
    return out


def hydrate(q: MultiJoinQuery, ids: DataFrame) -> DataFrame:
    """The answer's columns for combinations of ids: every relation is visited once more, by its id."""
    for alias, columns in payload_of(q).items():
        more = [c for c in columns if c not in ("rid", q.rid_of(alias))]
        own = [F.col(q.rid_of(alias)).alias(f"{alias}__rid"), *(F.col(c).alias(f"{alias}__{c}") for c in columns if c != "rid")]
        if more or (columns and "rid" not in columns):
            ids = ids.join(q.relations[alias].select(*own), f"{alias}__rid")
    return project(q, ids)


def per_id(alias: str):
    """Combinations by the id of one relation."""
    return lambda ids: ids.groupBy(f"{alias}__rid").agg(F.count("*").alias("n_"))


def count_by(q: MultiJoinQuery, ids: DataFrame, alias: str, column: str, name: str) -> DataFrame:
    """Combinations by a column of one relation: counted by id first (unless ids are counts already), so that only one row for each id is joined."""
    per = ids if "n_" in ids.columns else per_id(alias)(ids)
    rows = q.relations[alias].select(F.col(q.rid_of(alias)).alias(f"{alias}__rid"), F.col(column).alias(name))
    return per.join(rows, f"{alias}__rid").groupBy(name).agg(F.sum("n_").cast("bigint").alias("n"))
