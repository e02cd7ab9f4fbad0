"""What a reviewer found wrong, unfinished or without a table; each test failed before."""

import datetime as dt
import itertools
import random

import __spark_entry__ as E
import numpy as np
import pytest
from mjoin.exec.dominance import dominance_sums, prefix_sums
from mjoin import baselines as B
from mjoin import queries as Q
from mjoin.api import MultiJoinEngine
from mjoin.exec import grouped as G
from mjoin.exec import region_sums as R
from mjoin.exec.ranks import met_sums, ranked
from mjoin.exec.single_job import chain_join, sorted_pairs
from mjoin.functions import sign_keys
from mjoin.plan.infer import tightened, with_implied
from mjoin.query import multi_join
from mjoin.sources import calls, load
from mjoin.workloads import calls as C
from mjoin.workloads import synthetic as Y
from mjoin.workloads.synthetic import calibrate, controlled_self_join
from pyspark.sql import functions as F


def test_revenues_round_in_any_order_of_lines(spark, tmp_path):
    """Four prices of 10.5 together in every order: adding them as doubles falls below the half in some."""
    day = dt.datetime(1998, 3, 10)
    spark.createDataFrame([(1, "BUILDING")], "c_custkey bigint, c_mktsegment string").write.parquet(f"{tmp_path}/customer.parquet")
    orders = list(enumerate(itertools.permutations((1.1, 2.2, 3.3, 3.9))))
    spark.createDataFrame([(k, 1, day) for k, _ in orders], "o_orderkey bigint, o_custkey bigint, o_orderdate timestamp").write.parquet(f"{tmp_path}/orders.parquet")
    lines = [(k, p, 0.0, day + dt.timedelta(days=9)) for k, prices in orders for p in prices]
    spark.createDataFrame(lines, "l_orderkey bigint, l_extendedprice double, l_discount double, l_shipdate timestamp").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    assert {(r["okey"], r["revenue"]) for r in E.queries()["tpch_q3"](spark, str(tmp_path)).collect()} == {(k, 11) for k, _ in orders}


def test_calibrated_costs_are_plain_numbers(spark, sf):
    """Rows of numpy numbers are no rows of doubles."""
    params, _ = calibrate(spark, sf, [50], [1])
    assert type(params.c1) is float and type(params.c2) is float
    rows = {r["curve"]: r["seconds"] for r in E.queries()["calibration_curves"](spark, sf).collect()}
    assert set(rows) == {"spill", "connect", "planned"}


def test_sorted_pairs_are_counted_in_their_regions(spark, sf):
    """Numbers by left row and region, and not pairs, leave a task."""
    q = multi_join(a=calls(spark, sf), b=calls(spark, sf)).on("a.bt <= b.bt", "a.l >= b.l", "a.bsc <> b.bsc").build()
    counts = sorted_pairs(q, None, 7, counted=True)
    assert counts.columns == ["a__rid", "n_"]
    got = {r["a__rid"]: r["n"] for r in counts.groupBy("a__rid").agg(F.sum("n_").alias("n")).collect()}
    want = {r["a__rid"]: r["n"] for r in sorted_pairs(q, None, 7).groupBy("a__rid").agg(F.count("*").alias("n")).collect()}
    assert got == want and sum(got.values()) == 252563


def test_dominance_sums_visit_no_pairs(spark):
    """All operators, ties, NaN and repeated values against the joined pairs, over many slabs and bins."""
    rng = random.Random(5)
    pick = lambda: rng.choice((float("nan"), -0.0, 0.0, 0.5, 1.5, 7.25, -2.0))
    left, right = (spark.createDataFrame([(k, rng.randrange(12), pick()) for k in range(n)], "k bigint, x bigint, y double") for n in (60, 90))
    right = right.select(F.col("x").alias("rx"), F.col("y").alias("ry"), (F.col("k") % 4 + 1).alias("w"))
    for first, second in (("<=", ">="), ("<", ">"), (">", "<"), (">=", "<=")):
        got = dominance_sums(left, right, [("x", first, "rx"), ("y", second, "ry")], "w", 5).groupBy("k").agg(F.sum("s").alias("n"))
        want = left.join(right, F.expr(f"x {first} rx AND y {second} ry")).groupBy("k").agg(F.sum("w").alias("n"))
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) != []
    ranks, weights = np.array([3, 0, 2, 1]), np.array([1, 10, 100, 1000])
    assert prefix_sums(ranks, weights, np.array([4, 3, 0, 4]), np.array([4, 2, 4, 3])).tolist() == [1111, 10, 0, 1110]


def _no_pairs(spark, sf, q, monkeypatch):
    """Grouped numbers of q, and the pairs of relations that were joined on the way."""
    met, run = [], G.run_trail
    monkeypatch.setattr(G, "run_trail", lambda q, *a, **k: met.append(set(q.relations)) or run(q, *a, **k))
    return MultiJoinEngine(spark).grouped_counts(q, "lead", "id"), met


def test_w2_folds_stations_and_joins_no_leads(spark, sf, monkeypatch):
    got, met = _no_pairs(spark, sf, C.w2(calls(spark, sf)), monkeypatch)
    assert met == [{"mid", "tail"}] and got.agg(F.sum("n")).first()[0] == 8558225


def test_exact_selectivity_joins_no_leads(spark, sf, monkeypatch):
    met, run = [], G.run_trail
    monkeypatch.setattr(G, "run_trail", lambda q, *a, **k: met.append(set(q.relations)) or run(q, *a, **k))
    assert E.queries()["selectivity_exact"](spark, sf).first()["n_rows"] == 340840 and met == [{"mid", "tail"}]


#: Methods over distinct values with weights.
WEIGHED = """
native
correlation_flow_only
op_by_op
correlation_merge
correlation_input_only
correlation_transit_only
pairwise_rect
pairwise_scheduled
replicate_all
""".split()


@pytest.mark.parametrize("name", WEIGHED)
def test_methods_visit_values_and_not_rows(spark, sf, monkeypatch, name):
    """The lead's and mid's calls keep their values; tail's 1,000 rows come as one for each station and day."""
    seen, make = [], Q.weighted
    monkeypatch.setattr(Q, "weighted", lambda *a, **k: seen.append(make(*a, **k)) or seen[-1])
    assert E.queries()[name](spark, sf).agg(F.sum("n")).first()[0] == 340840
    assert seen[0].relations["tail"].count() == calls(spark, sf).select("bsc", "d").distinct().count() < 1000


#: Queries whose data come from a table.
TABLED = """
cost_model_grid
cover_example
delta_scan
hilbert_positions
pruned_trails_example
query_features
regions_by_table_function
schedule_example
score_powers
score_table
trail_graph_example
""".split()


@pytest.mark.parametrize("name", TABLED)
def test_examples_come_from_a_table(spark, sf, name):
    """Of tables ten times as large they tell something else."""
    small, large = (sorted(map(str, E.queries()[name](spark, d).collect())) for d in (sf, sf.replace("0.001", "0.01")))
    assert small and large and small != large


def test_controlled_output_has_the_pairs_of_the_probe_join(spark, sf):
    """The numbers are those of the joined pairs, but no pairs are made: weights of 50 keys meet."""
    got = E.queries()["controlled_output"](spark, sf)
    assert "Generate" not in (plan := got._jdf.queryExecution().optimizedPlan().toString()) and plan.count("Aggregate") == 2 and plan.index("Join") < plan.index("Aggregate")
    want = controlled_self_join(spark, sf, 50).groupBy("key").agg(F.count("*").alias("n"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_stars_of_one_inequality_give_no_rows_out(spark, sf, monkeypatch):
    met, run = [], G.run_trail
    monkeypatch.setattr(G, "run_trail", lambda q, *a, **k: met.append(set(q.relations)) or run(q, *a, **k))
    got = {r["nation"]: r["n"] for r in E.queries()["unequal_star"](spark, sf).collect()}
    s, li = load(spark, sf, "supplier"), load(spark, sf, "lineitem")
    want = s.join(li, s.s_acctbal >= li.l_extendedprice * 0.1).groupBy("s_nationkey").count()
    assert got == {r["s_nationkey"]: r["count"] for r in want.collect()} != {} and {"s", "l"} not in met


def test_keys_meet_in_blocks_of_matrices(spark, sf):
    """The pairs of the plain join by keys, each once, in keys of one and of many blocks."""
    e = load(spark, sf, "embeddings").where("vec_id < 120").select("vec_id", "embedding")
    keys = sign_keys(F.col("embedding"), Q.planes(20, 64), 5)
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)
    want = sorted(map(tuple, B.key_set_join(e, "vec_id", keys, lambda a, b: dot(a, b) >= 0.2 * F.sqrt(dot(a, a) * dot(b, b)), "embedding").collect()))
    for block in (7, 1000):
        assert sorted(map(tuple, B.key_set_pairs(e, "vec_id", keys, "embedding", 0.2, block).collect())) == want != []


def test_recall_compares_matrices(spark, sf, monkeypatch):
    used, make = [], B.key_set_pairs
    monkeypatch.setattr(B, "key_set_pairs", lambda *a, **k: used.append(a) or make(*a, **k))
    assert E.queries()["key_set_recall"](spark, sf).first()["recall"] >= 0.9 and used


def test_calibration_sorts_no_pairs(spark, sf, monkeypatch):
    """Pairs are dealt to their reducers by a hash, not in turn."""
    dealt, make = [], Y.controlled_self_join

    class Watched:
        def __init__(self, df):
            self.df = df

        def repartition(self, *how):
            dealt.append(how)
            return self.df.repartition(*how)

    monkeypatch.setattr(Y, "controlled_self_join", lambda *a: Watched(make(*a)))
    assert len(calibrate(spark, sf, [50], [1, 2])[1]) == 2 and all(len(how) > 1 for how in dealt)


def test_balanced_cube_visits_values_and_not_rows(spark, sf, monkeypatch):
    """As the baselines over w1: tail's rows come as one for each station and day, and the cube keeps its balanced bits."""
    seen, made, make, chain = [], [], Q.weighted, Q.chain_join
    monkeypatch.setattr(Q, "weighted", lambda *a, **k: seen.append(make(*a, **k)) or seen[-1])
    monkeypatch.setattr(Q, "chain_join", lambda *a, **k: made.append(k["bits"]) or chain(*a, **k))
    assert E.queries()["w1_balanced_bits"](spark, sf).agg(F.sum("n")).first()[0] == 340840
    assert made == ["balanced"] and seen[0].relations["tail"].count() == calls(spark, sf).select("bsc", "d").distinct().count() < 1000


@pytest.mark.parametrize("name", ["op_by_op", "correlation_merge", "correlation_input_only", "correlation_transit_only", "correlation_flow_only"])
def test_chains_are_joined_from_the_far_end_and_visit_no_leads(spark, sf, monkeypatch, name):
    met, make = [], B.dominance_sums
    monkeypatch.setattr(B, "dominance_sums", lambda left, right, *a, **k: met.append((left.columns, right.columns)) or make(left, right, *a, **k))
    assert E.queries()[name](spark, sf).agg(F.sum("n")).first()[0] == 340840
    assert [("out_" in left, "out_" in right, len(right)) for left, right in met] == [(True, False, 3)]


@pytest.mark.parametrize("name", ["pairwise_rect", "pairwise_scheduled"])
def test_pairs_write_a_sum_for_each_value_of_the_nearer_relation(spark, sf, monkeypatch, name):
    """A pair's result has no more rows than its nearer relation has values; subscribers and stations never stand in one result."""
    written, make = [], B.materialise
    monkeypatch.setattr(B, "materialise", lambda *a: written.append(make(*a)) or written[-1])
    assert E.queries()[name](spark, sf).agg(F.sum("n")).first()[0] == 340840
    assert [len(w.columns) for w in written] == [3, 3] and all(w.count() <= calls(spark, sf).count() for w in written)


@pytest.mark.parametrize("ops", ["<", "<>", "=", "<= >=", "< > <>", "> <> <>", "= <= <", "= = <> >=", "<> ="])
def test_ranks_count_what_pairs_meet(ops):
    """Ties, one value only in one side, one row or none, with weights and without."""
    rng, ops = np.random.default_rng(3), ops.split()
    holds = {"<": np.less, "<=": np.less_equal, ">": np.greater, ">=": np.greater_equal, "=": np.equal, "<>": np.not_equal}
    assert ranked(ops) and not ranked(["<", "<=", ">"])
    for m, n in ((40, 70), (1, 5), (3, 0), (0, 4)):
        pairs = [(rng.integers(0, 7, m), rng.integers(-1, 6, n), op) for op in ops]
        met = np.logical_and.reduce([holds[op].outer(x, v) for x, v, op in pairs])
        w = rng.integers(1, 9, n)
        assert met_sums(pairs).tolist() == met.sum(1).tolist() and met_sums(pairs, w).tolist() == (met * w).sum(1).tolist()


def test_counted_pairs_are_ranked_and_not_visited(spark, sf):
    """2.5e11 pairs of two inequalities and another value, against their number by each value; visiting them takes minutes."""
    df = spark.range(500_000).selectExpr("id AS rid", "id % 5 AS a", "id % 7 AS b", "id % 11 AS c")
    q = multi_join(l=df, r=df).on("l.a <= r.a", "l.b >= r.b", "l.c <> r.c").build()
    got = sorted_pairs(q, None, 7, counted=True).groupBy("l__rid").agg(F.sum("n_").alias("n")).agg(F.sum("n")).first()[0]
    rows = [tuple(r) for r in df.groupBy("a", "b", "c").count().collect()]
    assert got == sum(x[3] * y[3] for x in rows for y in rows if x[0] <= y[0] and x[1] >= y[1] and x[2] != y[2])


def test_replicated_sums_visit_no_leads(spark, sf, monkeypatch):
    """What goes to all tasks is summed by ranks beside the leads that stay; beyond the bytes it is shuffled."""
    met, make = [], B._sums_beside
    monkeypatch.setattr(B, "_sums_beside", lambda left, right, *a, **k: met.append((left.columns, right.columns)) or make(left, right, *a, **k))
    want = {r["id"]: r["n"] for r in MultiJoinEngine(spark).grouped_counts(C.w1(calls(spark, sf)), "lead", "id").collect()}
    assert {r["id"]: r["n"] for r in E.queries()["replicate_all"](spark, sf).collect()} == want
    assert [("out_" in left, len(right)) for left, right in met] == [(True, 3)]
    shuffled = B.replicate_all(G.weighted(C.w1(calls(spark, sf)), "lead", "id"), 0, "lead")
    assert {r["id"]: r["n"] for r in G.weigh(shuffled, "lead").collect()} == want and len(met) == 1


@pytest.mark.parametrize("on", [["lead.bt <= mid.bt", "lead.l >= mid.l", "mid.bsc = tail.bsc", "mid.d = tail.d"], ["lead.d < mid.d", "mid.bsc = tail.bsc"], ["lead.bsc > mid.bsc", "lead.d < mid.d", "mid.d <> tail.d", "mid.bsc <= tail.bsc"]])
@pytest.mark.parametrize("bits", ["balanced", (1, 3, 2)])
def test_regions_sum_the_cells_that_they_own(spark, sf, on, bits):
    """Every cell counts once, whichever regions its values meet in."""
    c = calls(spark, sf).where("d < 12")
    q = multi_join(lead=c, mid=c, tail=c).on(*on).build()
    got = G.weigh(chain_join(G.weighted(q, "lead", "id"), None, 6, bits=bits, sums="lead"), "lead")
    want = MultiJoinEngine(spark).grouped_counts(q, "lead", "id")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) != []


def test_balanced_cube_visits_no_leads(spark, sf, monkeypatch):
    met, make = [], R._ranked
    monkeypatch.setattr(R, "_ranked", lambda left, *a: met.append(left.columns) or make(left, *a))
    assert E.queries()["w1_balanced_bits"](spark, sf).agg(F.sum("n")).first()[0] == 340840 and len(met) == 1
    with pytest.raises(ValueError):
        chain_join(C.three_days(calls(spark, sf), "=", False), None, 6, sums="lead")


def test_jobs_of_pairs_know_what_follows_for_their_pair(spark, sf):
    """lead and tail are compared by day only, but have one subscriber; the answer stays."""
    q = C.three_days(calls(spark, sf), "=", True)
    more = with_implied(tightened(q))
    equal = {frozenset(((p.left.alias, p.left.expr), (p.right.alias, p.right.expr))) for p in more.predicates if p.op.value == "="}
    assert {frozenset((("lead", "id"), ("tail", "id"))), frozenset((("mid", "d + 1"), ("tail", "d")))} <= equal
    assert {p.aliases for p in more.predicates} == {p.aliases for p in q.predicates} and with_implied(more) == more
    engine = MultiJoinEngine(spark)
    got, want = (engine.counts(q, "lead", "id", strategy=s) for s in ("pairwise", "single"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) != []
    low = C.three_days(calls(spark, sf), "<>", False)
    assert with_implied(tightened(low)).predicates[: len(low.predicates)] == low.predicates


@pytest.mark.parametrize("first, second", [("<=", ">="), ("<", ">"), (">", "<"), (">=", "<="), ("<", "<=")])
def test_windows_sum_what_pairs_meet(spark, first, second):
    """Ties in both conditions, NaN, and bins of one row, of some and of all."""
    rng = random.Random(7)
    pick = lambda: rng.choice((float("nan"), -0.0, 0.0, 0.5, 1.5, 7.25, -2.0))
    left, right = (spark.createDataFrame([(k, rng.randrange(12), pick()) for k in range(n)], "k bigint, x bigint, y double") for n in (60, 90))
    right = right.select(F.col("x").alias("rx"), F.col("y").alias("ry"), (F.col("k") % 4 + 1).alias("w"))
    want = sorted(map(tuple, left.join(right, F.expr(f"x {first} rx AND y {second} ry")).groupBy("k").agg(F.sum("w").alias("n")).collect()))
    for size in (1, 20, 1000):
        got = B.window_sums(left, right, [("x", first, "rx"), ("y", second, "ry")], "w", 8, size).groupBy("k").agg(F.sum("s").alias("n"))
        assert sorted(map(tuple, got.collect())) == want != []


def test_native_joins_no_leads_with_all_others(spark, sf):
    """Catalyst's plan of the inequalities has no nested loops: bins are joined, the rest comes from windows."""
    ids = B.native(G.weighted(C.w1(calls(spark, sf)), "lead", "id"), "lead")
    plan = ids._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan and "Window" in plan and "Arrow" not in plan
    assert G.weigh(ids, "lead").agg(F.sum("n")).first()[0] == 340840


def test_calibration_moves_all_pairs_in_blocks(spark, sf):
    """Each pair once, in the reducer of its other id, and far fewer rows than pairs; reducers have partitions of their own."""
    blocks, pairs = controlled_self_join(spark, sf, 20, 4), controlled_self_join(spark, sf, 20)
    got = blocks.select("event_id", F.explode("others").alias("other_id"))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, pairs.select("event_id", "other_id").collect()))
    assert blocks.count() <= 4 * load(spark, sf, "events").count() < pairs.count()
    moved = blocks.repartition(4, "region").withColumn("part", F.spark_partition_id())
    assert moved.select("region", "part").distinct().count() == 4 == moved.select("part").distinct().count()
    assert [r[2] for r in calibrate(spark, sf, [20, 50], [1, 4])[1]] == [50_000, 50_000, 20_000, 20_000]
