"""One trail as one job: every relation is shuffled once to the regions that need it, and joined there."""

from __future__ import annotations

import contextlib
import json
import re

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..partition.assign import RegionAssignment, assign_regions, live_cells
from ..query import MultiJoinQuery, RelOp
from ..sources import dense_ids
from .ranks import met_sums, ranked

_QUALIFIED = re.compile(r"\b([A-Za-z_]\w*)\.([A-Za-z_]\w*)")
#: Cells up to which tables are literals of the plan; beyond, broadcast tables of one row a cell (at most 2^20).
LITERAL_CELLS = 1 << 13


def spark_hash_int(value: int, seed: int = 42) -> int:
    """Spark's hash of one int column (32-bit Murmur3), signed."""
    mask = 0xFFFFFFFF
    turn = lambda x, r: ((x << r) | (x >> (32 - r))) & mask
    k = turn((value & mask) * 0xCC9E2D51 & mask, 15) * 0x1B873593 & mask
    h = (turn(seed ^ k, 13) * 5 + 0xE6546B64) & mask
    h ^= 4
    h = (h ^ (h >> 16)) * 0x85EBCA6B & mask
    h = (h ^ (h >> 13)) * 0xC2B2AE35 & mask
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


#: Lets joins on region and further keys stay in the regions' partitions.
_CO_PARTITION = "spark.sql.requireAllClusterKeysForCoPartition"


@contextlib.contextmanager
def co_partitioned(spark: SparkSession):
    """Plans made inside keep one exchange for each relation even where equalities join the region as keys.

    A runtime setting of SQL, put back afterwards; plan and run inside (chain_join alone is lazy).
    """
    before = spark.conf.get(_CO_PARTITION)
    spark.conf.set(_CO_PARTITION, "false")
    try:
        yield
    finally:
        spark.conf.set(_CO_PARTITION, before)


def region_names(k: int, partitions: int | None = None) -> list[int]:
    """A name for each of k regions whose hash sends it to the partition of the same number out of partitions.

    Thus a plain hash repartition by the name deals every region to a partition of its own, and Catalyst knows the
    partitioning for all joins that follow. Spark joins in spark.sql.shuffle.partitions partitions at least.
    """
    n = max(k, partitions or k)
    names: list[int | None] = [None] * k
    value, missing = 0, k
    while missing:
        at = spark_hash_int(value) % n
        if at < k and names[at] is None:
            names[at] = value
            missing -= 1
        value += 1
    return names


def side_names(q: MultiJoinQuery, labels: frozenset[int]) -> dict[tuple[str, str], str]:
    """A column name for each distinct expression that the conditions compare."""
    sides = sorted({(s.alias, s.expr) for p in q.predicates if p.label in labels for s in (p.left, p.right)})
    return {s: f"{s[0]}__e{n}" for n, s in enumerate(sides)}


def condition(q: MultiJoinQuery, label: int, names: dict) -> Column:
    p = q.predicate(label)
    return p.op.to_column(F.col(names[p.left.alias, p.left.expr]), F.col(names[p.right.alias, p.right.expr]))


def payload_of(q: MultiJoinQuery) -> dict[str, list[str]]:
    """Columns of each relation that the answer needs."""
    out: dict[str, list[str]] = {a: [] for a in q.relations}
    for _, expr in q.select:
        for alias, column in _QUALIFIED.findall(expr):
            if alias in out and column not in out[alias]:
                out[alias].append(column)
    return out


def project(q: MultiJoinQuery, df: DataFrame) -> DataFrame:
    """The answer's columns over columns alias__name."""
    return df.select(*[F.expr(_QUALIFIED.sub(lambda m: f"{m[1]}__{m[2]}" if m[1] in q.relations else m[0], expr)).alias(name) for name, expr in q.select])


def prepare(q: MultiJoinQuery, alias: str, names: dict, payload: dict | None = None) -> DataFrame:
    """Row id and compared expressions of a relation, local filters applied, rows with a null in them left out.

    A condition over null is not true, so such a row is in no combination. payload names columns to carry along.
    """
    own = {n: F.expr(expr) for (a, expr), n in names.items() if a == alias}
    more = [F.col(c).alias(f"{alias}__{c}") for c in (payload or {}).get(alias, []) if c != "rid"]
    df = q.filtered(alias).select(F.col(q.rid_of(alias)).alias(f"{alias}__rid"), *(c.alias(n) for n, c in own.items()), *more)
    for n in own:
        df = df.where(F.col(n).isNotNull())
    return df


def draw_coord(alias: str, bits: int, seed: int) -> Column:
    """A coordinate from a hash of the row id: any rerun of a task draws the same one."""
    return F.pmod(F.xxhash64(F.lit(seed), F.lit(alias), F.col(f"{alias}__rid")), F.lit(1 << bits)).cast("int")


def dense_coord(df: DataFrame, alias: str, bits: int) -> DataFrame:
    """Coordinates by the exact rank of the row id: a sort by ranges and offsets of the partitions, no task holds all rows."""
    ranked = dense_ids(df, "rank_", f"{alias}__rid")
    n = max(1, ranked.count())
    return ranked.withColumn(f"{alias}__c", F.floor(F.col("rank_") * (1 << bits) / n).cast("int")).drop("rank_")


def range_coord(df: DataFrame, alias: str, column: str, bounds: list) -> DataFrame:
    """Coordinates by ranges of a compared expression; equal values share one, so skew shows."""
    at = sum((F.when(F.col(column) > F.lit(b), 1).otherwise(0) for b in bounds), F.lit(0))
    return df.withColumn(f"{alias}__c", at.cast("int"))


def route(df: DataFrame, alias: str, routes: list[list[int]], names: list[int], k: int) -> DataFrame:
    """A copy of each row for every region that its coordinate meets, dealt to the regions' partitions."""
    table = [[names[r] for r in rs] for rs in routes]
    if sum(map(len, table)) <= 4 * LITERAL_CELLS:
        regions = F.from_json(F.lit(json.dumps(table)), "array<array<int>>")[F.col(f"{alias}__c")]
        out = df.withColumn(f"{alias}__region", F.explode(regions))
    else:
        rows = df.sparkSession.createDataFrame(list(enumerate(table)), "c int, regions array<int>")
        out = df.join(F.broadcast(rows), F.col(f"{alias}__c") == F.col("c")).withColumn(f"{alias}__region", F.explode("regions")).drop("c", "regions")
    return out.repartition(k, f"{alias}__region")


def owned(df: DataFrame, dims: list[str], a: RegionAssignment, names: list[int]) -> DataFrame:
    """Only the combinations whose cell belongs to the region that found them: each is given out once."""
    index = F.lit(0)
    for alias, b in zip(dims, a.bits, strict=True):
        index = F.shiftleft(index, b) + F.col(f"{alias}__c")
    region = F.col(f"{dims[0]}__region")
    if len(a.owner) <= LITERAL_CELLS:
        table = F.from_json(F.lit(json.dumps([names[r] if r >= 0 else None for r in a.owner.tolist()])), "array<int>")
        return df.where(table[index] == region)
    rows = df.sparkSession.createDataFrame([(i, names[r]) for i, r in enumerate(a.owner.tolist()) if r >= 0], "cell_ int, owner_ int")
    return df.withColumn("cell_at_", index).join(F.broadcast(rows), (F.col("cell_at_") == F.col("cell_")) & (region == F.col("owner_"))).drop("cell_", "owner_", "cell_at_")


def relations_of(q: MultiJoinQuery, labels: frozenset[int]) -> list[str]:
    """Relations of the conditions, each joined to an earlier one, equality joins first."""
    left = {p.label: p for p in q.predicates if p.label in labels}
    first = min((a for p in left.values() for a in p.aliases), key=list(q.relations).index)
    order = [first]
    while True:
        near = [(p.op is not RelOp.EQ, list(q.relations).index(b), b) for p in left.values() for a, b in (sorted(p.aliases), sorted(p.aliases)[::-1]) if a in order and b not in order]
        if not near:
            break
        order.append(min(near)[2])
    if set(order) != {a for p in left.values() for a in p.aliases}:
        raise ValueError("the conditions of one job must be connected")
    return order


def equality_spans(q: MultiJoinQuery, labels: frozenset[int]) -> bool:
    """Whether equalities alone connect all relations of the conditions: then hashing by keys needs no copies."""
    root = {a: a for a in relations_of(q, labels)}

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for p in q.predicates:
        if p.label in labels and p.op is RelOp.EQ:
            a, b = p.aliases
            root[find(a)] = find(b)
    return len({find(a) for a in root}) == 1


def pairs_of(q: MultiJoinQuery) -> dict[frozenset, set[int]]:
    groups: dict[frozenset, set[int]] = {}
    for p in q.predicates:
        groups.setdefault(p.aliases, set()).add(p.label)
    return groups


def from_far_end(q: MultiJoinQuery, alias: str) -> list[str] | None:
    """Relations from the far end of a chain of pairs to alias, if the conditions make one; so little is still needed of every result."""
    near, order = {a: set().union(*(g - {a} for g in pairs_of(q) if a in g)) for a in q.relations}, [alias]
    while len(after := near[order[-1]] - set(order)) == 1:
        order.append(after.pop())
    chain = len(order) == len(near) and sum(map(len, near.values())) == 2 * len(order) - 2
    return order[::-1] if chain and all(len(p.aliases) == 2 for p in q.predicates) else None


def chain_join(q: MultiJoinQuery, labels=None, k: int = 8, curve: str = "hilbert", bits=None, seed: int = 0, coord: str = "hash", cards: list[float] | None = None, keep_owned: bool = True, hint: str = "merge", bounds: dict | None = None, payload: dict | None = None, prune: bool = False, sums: str | None = None) -> DataFrame:
    """Row ids of all combinations of the conditions' relations that meet them, as columns alias__rid.

    One exchange for each relation and no other: regions are partitions of their own, joins use region and
    equalities as keys and the other conditions as filters inside a region. coord: "hash" of the id; "dense" rank of it;
    "range" of the column in bounds (alias: (expression, sorted cuts)) where there is one, and then prune leaves out
    cells in which no pair of values can meet a condition: rows of only such cells are not sent at all.
    sums: the first relation, by whose column combinations of exec.grouped.weighted are counted; in a region a chain of pairs is then
    summed from its far end by cells and what is still needed, its row ids carry the sums, and no combinations are visited.
    """
    labels = frozenset(labels or (p.label for p in q.predicates))
    order = relations_of(q, labels)
    names = side_names(q, labels)
    a = assign_regions(len(order), k, curve, bits, cards)
    spark = q.relations[order[0]].sparkSession
    if coord == "range" and prune:
        a = a.restricted(_live(q, labels, order, a, bounds or {}))
        k = a.k
    regions = region_names(k, int(spark.conf.get("spark.sql.shuffle.partitions")))
    out, seen, routed = None, [], {}
    chain = from_far_end(q, sums) if sums else None
    if sums and (chain is None or order[0] != sums or set(chain) != set(order)):
        raise ValueError("a chain of pairs from the counted first relation is needed")
    for i, alias in enumerate(order):
        df = prepare(q, alias, names, payload)
        if coord == "dense":
            df = dense_coord(df, alias, a.bits[i])
        elif coord == "range" and (bounds or {}).get(alias):
            column, cuts = bounds[alias]
            df = range_coord(df, alias, names[alias, column], cuts[: (1 << a.bits[i]) - 1])
        else:
            df = df.withColumn(f"{alias}__c", draw_coord(alias, a.bits[i], seed))
        df = route(df, alias, a.routes[i], regions, k)
        if sums:
            routed[alias] = df
        elif out is None:
            out = df
        else:
            on = F.col(f"{order[0]}__region") == F.col(f"{alias}__region")
            for p in q.predicates:
                if p.label in labels and alias in p.aliases and (p.aliases - {alias}) <= set(seen):
                    on &= condition(q, p.label, names)
            out = out.join(df.hint(hint), on)
        seen.append(alias)
    if sums:
        from .region_sums import region_sums

        return region_sums(q, routed, chain, order, names, a, regions, hint)
    if keep_owned and len(order) > 1:
        out = owned(out, order, a, regions)
    return out.select(*_kept(order, payload))


def _live(q: MultiJoinQuery, labels: frozenset[int], order: list[str], a: RegionAssignment, bounds: dict):
    spans = []
    for alias, b in zip(order, a.bits, strict=True):
        cuts = bounds[alias][1][: (1 << b) - 1] if bounds.get(alias) else None
        # coordinate c holds values above cut c - 1 up to cut c; those beyond the last cut share the last one
        spans.append(None if cuts is None else [(cuts[c - 1] if 0 < c <= len(cuts) else None if c == 0 else cuts[-1], cuts[c] if c < len(cuts) else None) for c in range(1 << b)])
    place = {alias: i for i, alias in enumerate(order)}
    known = lambda s: bounds.get(s.alias) and bounds[s.alias][0] == s.expr
    compared = [(place[p.left.alias], p.op.value, place[p.right.alias]) for p in q.predicates if p.label in labels and known(p.left) and known(p.right)]
    return live_cells(a.bits, spans, compared)


def sorted_pairs(q: MultiJoinQuery, labels=None, k: int = 8, curve: str = "hilbert", bits=None, seed: int = 0, counted: bool = False) -> DataFrame:
    """Two relations in one job, met inside a region by sorting: one inequality gives each left row a range of the sorted right rows.

    The rest of the conditions filters what the ranges hold. For regions with many more pairs tested than found.
    counted: the numbers of pairs (n_) of each left row and region instead of pairs, so that a task holds its rows only; two
    inequalities and any = and <> are counted by ranks and visit no pairs.
    """
    labels = frozenset(labels or (p.label for p in q.predicates))
    order, names = relations_of(q, labels), side_names(q, labels)
    if len(order) != 2:
        raise ValueError("two relations are needed")
    a = assign_regions(2, k, curve, bits)
    spark = q.relations[order[0]].sparkSession
    regions = region_names(k, int(spark.conf.get("spark.sql.shuffle.partitions")))
    parts = [route(prepare(q, x, names).withColumn(f"{x}__c", draw_coord(x, a.bits[i], seed)), x, a.routes[i], regions, k) for i, x in enumerate(order)]
    number = {v: r for r, v in enumerate(regions)}
    conditions = [(names[p.left.alias, p.left.expr], p.op.value, names[p.right.alias, p.right.expr]) for p in (p if p.left.alias == order[0] else p.flip() for p in (q.predicate(x) for x in sorted(labels)))]
    owner, width, (left, right) = a.owner, a.bits[1], order
    kinds = [next(f.dataType.simpleString() for f in d.schema if f.name == f"{x}__rid") for d, x in zip(parts, order, strict=True)]
    second = "n_" if counted else f"{right}__rid"

    def run(key, lt: pd.DataFrame, rt: pd.DataFrame) -> pd.DataFrame:
        out = {f"{left}__rid": [], second: []}
        lead = next((n for n, c in enumerate(conditions) if c[1] != "<>"), 0)
        rt = rt.iloc[np.argsort(_pair(lt[conditions[lead][0]], rt[conditions[lead][2]])[1], kind="stable")]
        sides = [(*_pair(lt[u], rt[v]), op) for u, op, v in conditions]
        op, region = sides[lead][2], number[int(key[0])]
        more = [n for n in range(len(sides)) if n != lead or op == "<>"]
        ids, other, cells = rt[f"{right}__rid"].to_numpy(), rt[f"{right}__c"].to_numpy(), lt[f"{left}__c"].to_numpy().astype(np.int64)
        for cell in np.unique(cells):
            mine, theirs = np.flatnonzero(cells == cell), np.flatnonzero(owner[(cell << width) + other] == region)
            if not len(theirs):
                continue
            if counted and ranked([c[1] for c in conditions]):
                found = met_sums([(u[mine], v[theirs], c) for u, v, c in sides])
                some = np.flatnonzero(found)
                out[f"{left}__rid"].append(lt[f"{left}__rid"].to_numpy()[mine[some]])
                out[second].append(found[some])
                continue
            x, values = sides[lead][0][mine], sides[lead][1][theirs]
            below, upto, n = np.searchsorted(values, x, "left"), np.searchsorted(values, x, "right"), len(theirs)
            lo = {"<": upto, "<=": below, "=": below}.get(op, np.zeros(len(mine), int)).tolist()
            hi = {">": below, ">=": upto, "=": upto}.get(op, np.full(len(mine), n)).tolist()
            # the right sides in one piece each: a range of them is compared with one left value at a time
            rest = [(sides[m][0][mine], sides[m][1][theirs], _COMPARE[sides[m][2]]) for m in more]
            own, found = ids[theirs], np.zeros(len(mine), np.int64)
            for i, (b, e) in enumerate(zip(lo, hi, strict=True)):
                if b >= e:
                    continue
                good = None
                for u, v, holds in rest:
                    part = holds(u[i], v[b:e]).astype(bool, copy=False)
                    good = part if good is None else good & part
                found[i] = e - b if good is None else np.count_nonzero(good)
                if not counted and found[i]:
                    out[second].append(own[b:e] if good is None else own[b:e][good])
            some = np.flatnonzero(found)
            lead_ids = lt[f"{left}__rid"].to_numpy()[mine[some]]
            out[f"{left}__rid"].append(lead_ids if counted else np.repeat(lead_ids, found[some]))
            if counted:
                out[second].append(found[some])
        return pd.DataFrame({c: np.concatenate(v) if v else [] for c, v in out.items()})

    schema = f"{left}__rid {kinds[0]}, {second} {'bigint' if counted else kinds[1]}"
    return parts[0].groupBy(f"{left}__region").cogroup(parts[1].groupBy(f"{right}__region")).applyInPandas(run, schema)


def _pair(left: pd.Series, right: pd.Series) -> tuple[np.ndarray, np.ndarray]:
    """Values of both sides of a condition in one order; floats as integers with NaN equal to itself and above all others, as Spark has it."""
    if left.dtype.kind != "f" and right.dtype.kind != "f":
        return left.to_numpy(), right.to_numpy()
    return _ordered(left.to_numpy(np.float64)), _ordered(right.to_numpy(np.float64))


def _ordered(x: np.ndarray) -> np.ndarray:
    bits = (x + 0.0).view(np.int64)  # no negative zero
    return np.where(np.isnan(x), np.iinfo(np.int64).max, np.where(bits < 0, bits ^ np.iinfo(np.int64).max, bits))


_COMPARE = {"<": np.less, "<=": np.less_equal, "=": np.equal, ">=": np.greater_equal, ">": np.greater, "<>": np.not_equal}


def _kept(order: list[str], payload: dict | None) -> list[str]:
    return [c for a in order for c in (f"{a}__rid", *(f"{a}__{c}" for c in (payload or {}).get(a, []) if c != "rid"))]


def hash_join(q: MultiJoinQuery, labels=None, payload: dict | None = None) -> DataFrame:
    """The same combinations by plain joins on the equalities, other conditions as filters: Catalyst's own plan."""
    labels = frozenset(labels or (p.label for p in q.predicates))
    order, names = relations_of(q, labels), side_names(q, labels)
    out, seen = None, []
    for alias in order:
        df = prepare(q, alias, names, payload)
        if out is None:
            out = df
        else:
            on = F.lit(True)
            for p in q.predicates:
                if p.label in labels and alias in p.aliases and (p.aliases - {alias}) <= set(seen):
                    on &= condition(q, p.label, names)
            out = out.join(df, on)
        seen.append(alias)
    return out.select(*_kept(order, payload))


def run_trail(q: MultiJoinQuery, labels=None, k: int = 8, payload: dict | None = None, method: str = "auto", **options) -> DataFrame:
    """hash_join or chain_join ("hash", "cube"); auto: hash_join where equalities connect the relations, chain_join otherwise.

    A planner that knows the keys decides itself: few or hot keys leave units idle under hashing, a cube doesn't.
    """
    labels = frozenset(labels or (p.label for p in q.predicates))
    if method == "auto":
        method = "hash" if equality_spans(q, labels) else "cube"
    return hash_join(q, labels, payload) if method == "hash" else chain_join(q, labels, k, payload=payload, **options)


def answer(q: MultiJoinQuery, k: int = 8, **options) -> DataFrame:
    """The query as one job that carries the answer's columns along: no merging, no second visit of a relation."""
    return project(q, run_trail(q, None, k, payload_of(q), **options))
