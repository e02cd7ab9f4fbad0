"""Single jobs, merging, the planner and baselines against brute force in Spark."""

import datetime as dt
import random

import pytest
from mjoin import baselines as B
from mjoin import metrics as M
from mjoin.api import MultiJoinEngine
from mjoin.exec.merge import hydrate, merge_outputs
from mjoin.exec.runner import run_plan
from mjoin import queries as Q
from mjoin.exec.single_job import answer, chain_join, co_partitioned, hash_join, region_names, sorted_pairs, spark_hash_int
from mjoin.partition.assign import assign_regions, live_cells
from mjoin.operators import band_join, join_asof, same_bag
from mjoin.query import RelOp, multi_join
from mjoin.sources import calls, dense_ids, load, materialise, scale_calls
from mjoin.stats import collect_statistics, ingest, selectivity_from_quantiles
from mjoin.workloads import calls as C
from pyspark.sql import functions as F

SCHEMA = "rid bigint, a bigint, x double, s string, t timestamp"


def rows(seed, n=20):
    rng = random.Random(seed)
    pick = lambda *xs: rng.choice(xs)
    return [(k, pick(None, 1, 2, 3, 4), pick(None, float("nan"), 0.5, 1.5, -2.0), pick(None, "", "b", "bb"), pick(None, *(dt.datetime(2024, 1, d) for d in (1, 2, 3)))) for k in range(n)]


@pytest.mark.parametrize("op", [o.value for o in RelOp])
@pytest.mark.parametrize("k", [1, 7])
def test_two_relations_all_operators_and_types(spark, op, k):
    left, right = spark.createDataFrame(rows(1), SCHEMA), spark.createDataFrame(rows(2), SCHEMA)
    for column in "as" if k == 1 else "axst":
        q = multi_join(l=left, r=right).on(f"l.{column} {op} r.{column}").build()
        assert same_bag(chain_join(q, k=k), B.brute_force(q))


@pytest.mark.parametrize(("k", "curve", "coord", "seed"), [(5, "hilbert", "hash", 0), (9, "zorder", "hash", 3), (6, "grid", "hash", 1), (7, "random", "dense", 0), (3, "rowmajor", "hash", 2), (6, "auto", "hash", 0)])
def test_three_relations(spark, k, curve, coord, seed):
    a, b, c = (spark.createDataFrame(rows(s), SCHEMA) for s in (3, 4, 5))
    q = multi_join(a=a, b=b, c=c).on("a.a <= b.a", "b.x <> c.x", "a.s = c.s").build()
    with co_partitioned(spark):
        assert same_bag(materialise(chain_join(q, None, k, curve, coord=coord, seed=seed)), B.brute_force(q))


def test_without_owners_combinations_repeat(spark):
    c = calls(spark, "/root/testdata/sf0.001").where("d < 3")
    q = C.w1(c)
    true = hash_join(q).count()
    assert chain_join(q, k=7).count() == true < chain_join(q, k=7, keep_owned=False).count()


def test_one_exchange_for_each_relation(spark, sf):
    q = C.w1(calls(spark, sf))
    with co_partitioned(spark):
        plan = chain_join(q, k=9)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 3 and "CartesianProduct" not in plan and "NestedLoop" not in plan and "Python" not in plan
    assert spark.conf.get("spark.sql.requireAllClusterKeysForCoPartition") == "true"


def test_region_names_fill_partitions(spark):
    for k, n in ((1, 1), (7, 7), (5, 8)):
        names = region_names(k, n)
        df = spark.createDataFrame([(r, v) for r, v in enumerate(names)], "r int, v int").repartition(max(k, n), "v")
        assert all(r["r"] == r["p"] for r in df.withColumn("p", F.spark_partition_id()).collect())
    got = spark.range(100).select(F.hash(F.col("id").cast("int")).alias("h")).collect()
    assert [r["h"] for r in got] == [spark_hash_int(i) for i in range(100)]


def test_routing_is_the_same_on_rerun(spark, sf):
    q = C.w1(calls(spark, sf))
    assert same_bag(M.routed(q, 7), M.routed(q, 7))
    counts = {r["alias"]: r for r in M.copies(M.routed(q, 7)).collect()}
    assert len(counts) == 3 and all(r["copies"] >= r["rows"] for r in counts.values())
    skew = M.region_skew(M.routed(q, 7)).first()
    assert skew["regions"] == 7 and skew["most"] < 1.5 * skew["mean"]


@pytest.mark.parametrize("size", [(0, 5), (1, 1), (1, 30)])
def test_tiny_relations(spark, size):
    a, b = (spark.createDataFrame(rows(9, n), SCHEMA) for n in size)
    q = multi_join(a=a, b=b).on("a.a < b.a").build()
    assert same_bag(chain_join(q, k=16), B.brute_force(q))


def test_skewed_keys_are_spread(spark):
    many = spark.range(1000).select(F.col("id").alias("rid"), F.when(F.col("id") % 10 == 0, F.col("id")).otherwise(0).alias("k"))
    q = multi_join(a=many, b=many).on("a.k <= b.k").build()
    skew = M.region_skew(M.routed(q, 8)).first()
    assert skew["most"] < 1.3 * skew["mean"]
    assert same_bag(chain_join(q, k=8), hash_join(q))


@pytest.mark.parametrize("strategy", ["planned", "single", "pairwise"])
def test_plans_give_the_same_rows(spark, strategy):
    a, b, c, d = (spark.createDataFrame(rows(s, 12), SCHEMA) for s in (3, 4, 5, 6))
    q = multi_join(a=a, b=b, c=c, d=d).on("a.a <= b.a", "b.x <> c.x", "c.t < d.t", "a.s = d.s").select(v="a.a + d.a", s="b.s").build()
    engine = MultiJoinEngine(spark, 4)
    order = [f"{x}__rid" for x in "abcd"]
    assert same_bag(engine.ids(q, strategy=strategy, infer=False).select(*order), B.brute_force(q).select(*order))
    assert same_bag(engine.run(q, strategy=strategy, infer=False), answer(q))
    plan, run = engine.last
    assert {x for j in plan.jobs for x in j.labels} == {1, 2, 3, 4} and len(run.history) >= len(plan.jobs)
    assert engine.explain(q, strategy=strategy).count() == len(plan.jobs)


def test_given_jobs_may_overlap(spark):
    a, b, c = (spark.createDataFrame(rows(s, 12), SCHEMA) for s in (3, 4, 5))
    q = multi_join(a=a, b=b, c=c).on("a.a <= b.a", "b.x <> c.x", "a.s = c.s").select(r="a.rid").build()
    engine = MultiJoinEngine(spark, 4)
    order = [f"{x}__rid" for x in "abc"]
    assert same_bag(engine.ids(q, jobs=[[1, 2], [2, 3]]).select(*order), B.brute_force(q).select(*order))
    outputs = [chain_join(q, {1}, 3), chain_join(q, {2}, 2), chain_join(q, {3}, 2)]
    assert same_bag(merge_outputs(outputs).select(*order), B.brute_force(q).select(*order))
    assert same_bag(hydrate(q, merge_outputs(outputs)), answer(q))
    stats = collect_statistics(q)
    plan = engine.planner.plan(q, 4, stats)
    assert run_plan(q, plan, 4).ids.count() == B.brute_force(q).count() and plan.considered


def test_inference_keeps_the_answer(spark, sf):
    c = calls(spark, sf).where("id < 8 AND d < 5")
    q = C.three_days(c, "<>", False)
    engine = MultiJoinEngine(spark, 4)
    order = [f"{a}__rid" for a in q.relations]
    assert same_bag(engine.ids(q).select(*order), engine.ids(q, infer=False, strategy="single").select(*order))


@pytest.mark.parametrize("name", ["native", "op_by_op", "dataflow", "correlation_merge", "pairwise_rect", "pairwise_scheduled", "replicate_all"])
def test_baselines(spark, name):
    a, b, c = (spark.createDataFrame(rows(s, 15), SCHEMA) for s in (3, 4, 5))
    q = multi_join(a=a, b=b, c=c).on("a.a = b.a", "b.x <> c.x", "a.t <= c.t").build()
    order = [f"{x}__rid" for x in "abc"]
    assert same_bag(getattr(B, name)(q).select(*order), B.brute_force(q).select(*order))


def test_shares(spark):
    a, b, c = (spark.createDataFrame(rows(s, 25), SCHEMA) for s in (3, 4, 5))
    q = multi_join(a=a, b=b, c=c).on("a.a = b.a", "b.s = c.s", "a.t = c.t").build()
    order = [f"{x}__rid" for x in "abc"]
    assert same_bag(B.shares_equi(q, 8).select(*order), B.brute_force(q).select(*order))
    assert B.best_shares({"r": (10, ["a"]), "s": (10_000, ["a", "b"]), "t": (10, ["b"])}, ["a", "b"], 16)
    with pytest.raises(ValueError):
        B.shares_equi(multi_join(a=a, b=b).on("a.a < b.a").build())


def test_dense_ids_and_scaling(spark, sf):
    li = dense_ids(load(spark, sf, "lineitem"), "rid", "l_orderkey", "l_linenumber")
    r = li.agg(F.count("*").alias("n"), F.countDistinct("rid").alias("d"), F.min("rid").alias("lo"), F.max("rid").alias("hi")).first()
    assert r["n"] == r["d"] == r["hi"] + 1 and r["lo"] == 0
    base = calls(spark, sf)
    more = scale_calls(base, 4, [1] * 12 + [3] * 12)
    assert more.count() == 4 * base.count() == more.select("rid").distinct().count()
    late = more.where("bt >= 43200").count() / more.count()
    assert abs(late - 0.75) < 0.03


def test_statistics_and_ingest(spark, sf, tmp_path):
    c = calls(spark, sf)
    q = C.w1(c)
    s = collect_statistics(q, most=300)
    true = c.alias("a").crossJoin(c.alias("b")).where("a.bt <= b.bt").count() / c.count() ** 2
    assert abs(s.selectivity[1] - true) < 0.06 and s.rows["lead"] == c.count()
    path = f"file://{tmp_path}/calls"
    stats = ingest(c, path, ["d", "bt"], 6)
    assert stats.rows == c.count() and stats.columns["d"]["min"] == "0"
    assert same_bag(spark.read.parquet(f"{path}/data"), c) and spark.read.parquet(f"{path}/stats").count() == len(c.columns)
    assert selectivity_from_quantiles([1, 2, 3], [2, 3, 4], RelOp.LT) > 0.6 > selectivity_from_quantiles([1, 2, 3], [2, 3, 4], RelOp.GE)


def test_asof_and_band(spark):
    a = spark.createDataFrame([(1, 5), (1, 9), (2, 5)], "k int, t int")
    b = spark.createDataFrame([(1, 5, "x"), (1, 7, "y")], "k int, t int, v string")
    assert sorted(map(tuple, join_asof(a, b, "k", "t", ["v"]).collect()), key=str) == sorted([(1, 5, None), (1, 9, "y"), (2, 5, None)], key=str)
    assert (1, 5, "x") in set(map(tuple, join_asof(a, b, "k", "t", ["v"], inclusive=True).collect()))
    x, y = spark.range(40).select(F.col("id").alias("x")), spark.range(40).select((F.col("id") * 2).alias("y"))
    assert same_bag(band_join(x, y, "x", "y", -3, 4), x.crossJoin(y).where("y >= x - 3 AND y <= x + 4"))


@pytest.mark.parametrize("op", ["<", ">=", "=", "<>"])
def test_cells_without_answers_are_left_out(spark, op):
    a, b = (spark.createDataFrame([(k, (k * 7 + s) % 50) for k in range(60)], "rid bigint, v bigint") for s in (0, 3))
    q = multi_join(a=a, b=b).on(f"a.v {op} b.v").build()
    cuts = {x: ("v", [5, 10, 20, 30, 40, 45, 48]) for x in "ab"}
    pruned = chain_join(q, None, 6, bits=3, coord="range", bounds=cuts, prune=True)
    assert same_bag(pruned, B.brute_force(q))
    live = live_cells((3, 3), [[(k, k + 1) for k in range(8)]] * 2, [(0, op, 1)]).sum()
    assert live == {"<": 36, ">=": 43, "=": 22, "<>": 64}[op]
    rest = assign_regions(2, 6, "hilbert", 3).restricted(live_cells((3, 3), [[(k, k + 1) for k in range(8)]] * 2, [(0, op, 1)]))
    assert rest.shares().sum() == live and rest.shares().max() - rest.shares().min() <= 1


@pytest.mark.parametrize("on", [["l.a < r.a"], ["l.a >= r.a", "l.x <> r.x"], ["l.a = r.a", "l.t <= r.t"], ["l.x <> r.x"], ["l.x <= r.x"], ["l.x = r.x"], ["l.x < r.a", "l.a >= r.a"], ["r.s > l.s", "l.a <= r.a"]])
def test_sorted_pairs(spark, on):
    left, right = spark.createDataFrame(rows(1, 30), SCHEMA), spark.createDataFrame(rows(2, 30), SCHEMA)
    q = multi_join(l=left, r=right).on(*on).build()
    assert same_bag(sorted_pairs(q, k=5), B.brute_force(q))


def test_table_function(spark, sf):
    got = {(r["alias"], r["c"], r["region"]) for r in Q.regions_by_table_function(spark, sf).collect()}
    a = assign_regions(2, 5, "hilbert", 3)
    assert got == {(x, c, r) for x, routes in zip(("left", "right"), a.routes, strict=True) for c, rs in enumerate(routes) for r in rs}
