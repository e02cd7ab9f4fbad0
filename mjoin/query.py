"""Multi-join queries: relations, comparisons between two of them, row ids and the columns of the answer."""

from __future__ import annotations

import enum
import re
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class RelOp(enum.Enum):
    LT = "<"
    LE = "<="
    EQ = "="
    GE = ">="
    GT = ">"
    NE = "<>"

    def to_column(self, left: Column, right: Column) -> Column:
        return {"<": left < right, "<=": left <= right, "=": left == right, ">=": left >= right, ">": left > right, "<>": left != right}[self.value]

    def flip(self) -> RelOp:
        """The operator with its sides exchanged."""
        return {RelOp.LT: RelOp.GT, RelOp.LE: RelOp.GE, RelOp.GE: RelOp.LE, RelOp.GT: RelOp.LT}.get(self, self)

    def negate(self) -> RelOp:
        """True where this is false, for values that aren't null."""
        return {RelOp.LT: RelOp.GE, RelOp.LE: RelOp.GT, RelOp.GE: RelOp.LT, RelOp.GT: RelOp.LE, RelOp.EQ: RelOp.NE, RelOp.NE: RelOp.EQ}[self]


_OPERATORS = re.compile(r"<=|>=|<>|!=|==|=|<|>")
_ALIAS = re.compile(r"\b([A-Za-z_]\w*)\.(?=[A-Za-z_])")


@dataclass(frozen=True)
class Side:
    """An expression over the columns of one relation."""

    alias: str
    expr: str

    @classmethod
    def parse(cls, text: str) -> Side:
        names = set(_ALIAS.findall(text))
        if len(names) != 1:
            raise ValueError(f"one relation is needed on each side of a comparison: {text!r}")
        return cls(names.pop(), _ALIAS.sub("", text).strip())


@dataclass(frozen=True)
class Predicate:
    """label: left op right, between two relations; constant shifts are part of the expressions."""

    label: int
    left: Side
    op: RelOp
    right: Side

    def __post_init__(self):
        if self.left.alias == self.right.alias:
            raise ValueError(f"condition {self.label} compares {self.left.alias} with itself; use a local filter")

    @classmethod
    def parse(cls, label: int, text: str) -> Predicate:
        m = _OPERATORS.search(text)
        if not m:
            raise ValueError(f"no comparison in {text!r}")
        op = {"!=": "<>", "==": "="}.get(m.group(), m.group())
        return cls(label, Side.parse(text[: m.start()]), RelOp(op), Side.parse(text[m.end() :]))

    @property
    def aliases(self) -> frozenset[str]:
        return frozenset((self.left.alias, self.right.alias))

    def flip(self) -> Predicate:
        return Predicate(self.label, self.right, self.op.flip(), self.left)

    def sql(self) -> str:
        at = lambda s: re.sub(r"\b([A-Za-z_]\w*)\b(?!\s*\()", lambda m: m.group() if m.group().lower() in _WORDS else f"{s.alias}.{m.group()}", s.expr)
        return f"{at(self.left)} {self.op.value} {at(self.right)}"


#: Words of expressions that aren't columns (fixed values).
_WORDS = frozenset("interval day days hour hours minute minutes second seconds and or not null cast as date double int bigint".split())


def band(first_label: int, left: str, right: str, low: str, high: str, closed: bool = False) -> list[str]:
    """Two conditions for left + low < right < left + high (closed: with equality)."""
    op = "<=" if closed else "<"
    return [f"{left} + {low} {op} {right}", f"{right} {op} {left} + {high}"]


@dataclass(frozen=True)
class MultiJoinQuery:
    """relations by alias, conditions with unique labels, local filters (SQL) and the answer's columns (name, 'alias.expression')."""

    relations: dict[str, DataFrame]
    predicates: tuple[Predicate, ...]
    select: tuple[tuple[str, str], ...] = ()
    filters: dict[str, str] = field(default_factory=dict)
    rid: dict[str, str] = field(default_factory=dict)

    def rid_of(self, alias: str) -> str:
        return self.rid.get(alias, "rid")

    def validate(self) -> MultiJoinQuery:
        labels = [p.label for p in self.predicates]
        if len(set(labels)) != len(labels):
            raise ValueError("labels of conditions must be unique")
        for p in self.predicates:
            for s in (p.left, p.right):
                if s.alias not in self.relations:
                    raise ValueError(f"unknown relation {s.alias} in condition {p.label}")
            kinds = [self.relations[s.alias].select(F.expr(s.expr)).dtypes[0][1] for s in (p.left, p.right)]
            if not _comparable(*kinds):
                raise ValueError(f"condition {p.label} compares {kinds[0]} with {kinds[1]}; cast one side")
        for a, df in self.relations.items():
            if self.rid_of(a) not in df.columns:
                raise ValueError(f"relation {a} has no row id {self.rid_of(a)}")
        from .plan.graph import JoinGraph

        if not JoinGraph.from_query(self).is_connected():
            raise ValueError("the join graph is not connected")
        return self

    def predicate(self, label: int) -> Predicate:
        return next(p for p in self.predicates if p.label == label)

    def filtered(self, alias: str) -> DataFrame:
        df = self.relations[alias]
        return df.where(self.filters[alias]) if alias in self.filters else df


def _comparable(a: str, b: str) -> bool:
    group = lambda k: "number" if k.startswith(("tinyint", "smallint", "int", "bigint", "float", "double", "decimal")) and not k.startswith("interval") else "time" if k.startswith(("date", "timestamp")) else k
    return group(a) == group(b)


class QueryBuilder:
    """multi_join(lead=calls, mid=calls).where("lead", "d < 2").on("lead.bt <= mid.bt").select(id="lead.id").build()"""

    def __init__(self, **relations: DataFrame):
        self.relations, self.conditions, self.filters, self.out, self.rids = relations, [], {}, [], {}

    def on(self, *conditions: str) -> QueryBuilder:
        self.conditions += conditions
        return self

    def where(self, alias: str, condition: str) -> QueryBuilder:
        self.filters[alias] = f"({self.filters[alias]}) AND ({condition})" if alias in self.filters else condition
        return self

    def rid(self, **names: str) -> QueryBuilder:
        self.rids |= names
        return self

    def select(self, **columns: str) -> QueryBuilder:
        self.out += columns.items()
        return self

    def build(self) -> MultiJoinQuery:
        predicates = tuple(Predicate.parse(k, c) for k, c in enumerate(self.conditions, 1))
        return MultiJoinQuery(self.relations, predicates, tuple(self.out), self.filters, self.rids).validate()


def multi_join(**relations: DataFrame) -> QueryBuilder:
    return QueryBuilder(**relations)
