"""Registered queries take every row of their tables: brute force over a few calls of late days and high subscribers."""

import datetime
import itertools
from collections import Counter

import __spark_entry__ as E
import pytest
from mjoin import baselines as B
from mjoin import streaming as S
from mjoin.api import MultiJoinEngine
from mjoin.plan.planner import Planner
from mjoin.query import multi_join
from mjoin.sources import load, scale_calls
from mjoin.workloads import calls as C
from pyspark.sql import functions as F

W1 = lambda a, b, c: a.bt <= b.bt and a.l >= b.l and b.bsc == c.bsc and b.d == c.d
W2 = lambda a, b, c: a.bt <= b.bt and a.l >= b.l and b.bsc != c.bsc and b.d == c.d
DAYS = lambda a, b, c: a.d < b.d < c.d < a.d + 3
W3 = lambda a, b, c, e: DAYS(a, b, c) and a.bsc == e.bsc
W4 = lambda a, b, c, e: DAYS(a, b, c) and a.bsc != e.bsc
SAME = lambda a, *others: all(a.id == x.id for x in others)

W1_QUERIES = (
    "calls_w1 w1_single_hilbert w1_single_zorder w1_single_grid w1_single_rowmajor w1_single_random w1_single_auto w1_k1 w1_k5 w1_k9 w1_dense_coord w1_balanced_bits "
    "w1_pairwise w1_planned w1_range_coord w1_range_pruned native op_by_op correlation_merge correlation_input_only correlation_transit_only correlation_flow_only "
    "pairwise_rect pairwise_scheduled replicate_all"
).split()
COUNTED = {
    **dict.fromkeys(W1_QUERIES, (3, W1)),
    "calls_w2": (3, W2),
    "calls_w3": (4, W3),
    **dict.fromkeys("calls_w3_same_id calls_w3_same_id_cube calls_w3_same_id_planned w3_single w3_planned w3_jobs_forced".split(), (4, lambda *x: W3(*x) and SAME(*x))),
    "calls_w4": (4, W4),
    **dict.fromkeys(("calls_w4_same_id", "calls_w4_same_id_cube", "calls_w4_same_id_planned"), (4, lambda *x: W4(*x) and SAME(*x))),
    "w1_sorted_pairs": (2, lambda a, b: a.bt <= b.bt and a.l >= b.l and a.bsc != b.bsc),
}


@pytest.fixture(scope="module")
def few(spark, tmp_path_factory):
    """A folder with 20 calls of days 8 to 27 by subscribers 40 to 42, suppliers and customers of high keys; and the calls."""
    path = str(tmp_path_factory.mktemp("few"))
    rows = [(k, 40 + k % 3, 8 + k % 4 if k < 14 else 20 + k % 8, 300 * (k * 7 % 20) + k, 10.0 * (k * 5 % 13), k // 2 % 3) for k in range(20)]
    events = [(rid, datetime.datetime(2024, 1, 1) + datetime.timedelta(days=d, seconds=bt), id, "view", l, f'{{"k": {bsc}}}') for rid, id, d, bt, l, bsc in rows]
    spark.createDataFrame(events, "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string").write.parquet(f"{path}/events.parquet")
    spark.createDataFrame([(k, 1.0 * (k % 2)) for k in (1, 50, 51, 52)], "s_suppkey bigint, s_acctbal double").write.parquet(f"{path}/supplier.parquet")
    spark.createDataFrame([(k, 0.5) for k in (1, 50, 51, 70)], "c_custkey bigint, c_acctbal double").write.parquet(f"{path}/customer.parquet")

    class Call:
        def __init__(self, *values):
            self.rid, self.id, self.d, self.bt, self.l, self.bsc = values

    return path, [Call(*r) for r in rows]


@pytest.mark.parametrize("name", COUNTED)
def test_counts_over_all_calls(spark, few, name):
    path, calls = few
    width, holds = COUNTED[name]
    want = Counter(x[0].id for x in itertools.product(calls, repeat=width) if holds(*x))
    assert want and {r["id"]: r["n"] for r in E.queries()[name](spark, path).collect()} == want


def test_other_queries_over_all_rows(spark, few):
    path, calls = few
    q = E.queries()
    pairs = {(a.rid, b.rid) for a, b in itertools.product(calls, repeat=2) if a.d == b.d and a.bsc != b.bsc and a.bt <= b.bt <= a.bt + 60 * a.l}
    for name in ("calls_w2_concurrent", "calls_w2_concurrent_cube", "calls_w2_concurrent_planned"):
        assert pairs and sorted(tuple(r) for r in q[name](spark, path).collect()) == sorted(pairs)
    alike = {(a.rid, b.rid) for a, b in itertools.product(calls, repeat=2) if a is not b and a.d == b.d and a.bsc == b.bsc and a.bt <= b.bt <= a.bt + 60 * a.l}
    assert sorted(tuple(r) for r in q["stream_deltas"](spark, path).collect()) == sorted(alike)
    n = sum(W1(*x) for x in itertools.product(calls, repeat=3))
    assert q["selectivity_exact"](spark, path).first()["n_rows"] == n > 0
    assert {r["rows"] for r in q["copies_by_relation"](spark, path).collect()} == {len(calls)}
    assert q["region_skew"](spark, path).count() > 0 and q["plan_explain"](spark, path).count() > 0
    joined = {(1, 1), (51, -1), (-1, 51), (50, 50), (52, -1), (-1, 70)}
    # balances: suppliers 1 and 51 have 1.0, 50 and 52 have 0.0, customers 0.5
    joined = joined - {(1, 1)} | {(1, -1), (-1, 1)}
    assert {tuple(r) for r in q["op_outer_full"](spark, path).collect()} == joined


def test_streams_keep_nulls_and_replays_count_once(spark, few, tmp_path):
    path, calls = few
    c = C.relation(spark, path)
    odd = c.unionByName(c.limit(3).withColumn("bt", F.lit(None).cast("bigint")).withColumn("rid", F.col("rid") + 100))
    assert S.finish(S.file_stream(spark, odd, 4, None, "bt")).count() == odd.count() == len(calls) + 3
    q = C.concurrent(c, "=")
    want = sorted(tuple(r) for r in E.queries()["stream_deltas"](spark, path).collect())
    seen, out = f"{tmp_path}/seen", f"{tmp_path}/out"
    parts = [c.where(F.col("rid") % 3 == k) for k in range(3)]
    for number, part in ((0, parts[0]), (1, parts[1]), (0, parts[0]), (1, parts[1]), (2, parts[2]), (2, parts[2])):
        S.delta_step(q, "lead", part, number, seen, out, 4)
    assert sorted(tuple(r) for r in spark.read.parquet(out).drop("batch").collect()) == want
    assert scale_calls(c, 0, [1]).count() == 0


def test_keys_find_nearly_all_and_blocks_all_alike_vectors(spark, sf):
    r = E.queries()["key_set_recall"](spark, sf).first()
    assert r["alike"] > 0 and r["recall"] >= 0.9
    e = load(spark, sf, "embeddings").select("vec_id", "embedding")
    want = sorted(tuple(r) for r in E.queries()["alike_pairs"](spark, sf).collect())
    assert sorted(tuple(r) for r in B.block_pairs(e, "vec_id", "embedding", 0.3, block=17).collect()) == want


def test_hot_keys_choose_the_cube(spark):
    """Hashing for many keys, the cube where one key holds most pairs."""
    many = spark.range(200_000).selectExpr("id AS rid", "id AS k", "id % 97 AS v")
    hot = spark.range(200_000).selectExpr("id AS rid", "CASE WHEN id % 3 > 0 THEN 0 ELSE id END AS k", "id % 97 AS v")
    planner = Planner()
    for df, method in ((many, "hash"), (hot, "cube")):
        q = multi_join(a=df, b=df).on("a.k = b.k", "a.v < b.v").build()
        plan = planner.plan(q, 64, None, "single")
        assert set(plan.methods.values()) == {method}


def test_grouped_counts_need_no_combinations(spark):
    """A chain of five with 1e20 combinations."""
    df = spark.range(10_000).selectExpr("id AS rid", "id % 5 AS x", "id % 3 AS y")
    q = multi_join(a=df, b=df, c=df, d=df, e=df).on("a.x <= b.x", "b.y <> c.y", "c.x = d.x", "d.y >= e.y").build()
    got = {r["id"]: r["n"] for r in MultiJoinEngine(spark).grouped_counts(q, "a", "x").collect()}
    rows = Counter((i % 5, i % 3) for i in range(10_000))
    e = {y: sum(w for (_, v), w in rows.items() if y >= v) for y in range(3)}
    d = {x: sum(w * e[y] for (v, y), w in rows.items() if v == x) for x in range(5)}
    c = {y: sum(w * d[x] for (x, v), w in rows.items() if v != y) for y in range(3)}
    b = {x: sum(w * c[y] for (v, y), w in rows.items() if x <= v) for x in range(5)}
    assert got == {x: b[x] * 2000 for x in range(5)}
