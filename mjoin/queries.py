"""All named queries of the engine, with the DuckDB SQL that must give the same rows."""

from __future__ import annotations

import time
import uuid
from dataclasses import replace

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from . import baselines as B
from . import metrics as M
from . import streaming as S
from .api import MultiJoinEngine
from .exec.grouped import weigh, weighted
from .exec.merge import count_by, hydrate, per_id
from .exec.single_job import chain_join, co_partitioned, sorted_pairs
from .functions import hilbert_expr, register_regions_of, selectivity_agg, sign_keys, zorder_expr
from .operators import anti_join, band_join, join_asof, salted_join, semi_join, top_k_by
from .partition.assign import assign_regions, copies_by_relation, partition_score
from .partition.reducers import best_fitted, delta_curve
from .plan.graph import JoinGraph
from .plan.cover import exact_cover, greedy_cover
from .plan.planner import Planner, explain, trail_table
from .plan.schedule import merge_plan, schedule_jobs
from .plan.trails import build_pruned_trails, enumerate_trails
from .query import multi_join
from .sources import calls, legs, load, materialise, plain_load, scale_calls, scratch, table_load
from .stats import collect_statistics, estimate_rows, ingest, quantiles
from .workloads import calls as C
from .workloads import synthetic as Y
from .workloads import tpch as T

QUERIES: dict = {}
ORACLE: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if sql:
            ORACLE[name] = sql
        return fn

    return add


# ---- workloads over call records and journeys ---------------------------------------------------------------------------


def _counted(build, **options):
    return lambda spark, sf: MultiJoinEngine(spark).counts(build(C.relation(spark, sf)), "lead", "id", **options)


def _grouped(build):
    return lambda spark, sf: MultiJoinEngine(spark).grouped_counts(build(C.relation(spark, sf)), "lead", "id")


#: All calls take part. The printed forms have up to 1e13 combinations at sf0.01, so their numbers are taken by groups, here and
#: in SQL; the strategies below give out all combinations of w1, or of w3 with one subscriber.
W1_SQL = C.GROUPED_SQL["w1"]
W3_SAME_SQL = C.counts_sql("lead mid tail peer", C.W3_WHERE + C.SAME_ID)
W4_SAME_SQL = C.counts_sql("lead mid tail peer", C.W4_WHERE + C.SAME_ID)

query("calls_w1", W1_SQL)(_grouped(C.w1))
query("calls_w2", C.GROUPED_SQL["w2"])(_grouped(C.w2))
query("calls_w3", C.GROUPED_SQL["w3"])(_grouped(lambda c: C.three_days(c, "=", False)))
query("calls_w3_same_id", W3_SAME_SQL)(_counted(lambda c: C.three_days(c, "=", True)))
query("calls_w4", C.GROUPED_SQL["w4"])(_grouped(lambda c: C.three_days(c, "<>", False)))
query("calls_w4_same_id", W4_SAME_SQL)(_counted(lambda c: C.three_days(c, "<>", True)))


def _one_job(build, how: str):
    """The workload as one job: hash joins where equalities allow, or a cube in any case; or as the planner has it."""

    def run(spark, sf):
        q, engine = build(C.relation(spark, sf)), MultiJoinEngine(spark)
        return engine.run(q) if how == "planned" else engine.single(q, method=how)

    return run


for _name, _op in (("w1", "="), ("w2", "<>")):
    query(f"calls_{_name}_concurrent", C.concurrent_sql(_op))(_one_job(lambda c, op=_op: C.concurrent(c, op), "auto"))
    query(f"calls_{_name}_concurrent_cube", C.concurrent_sql(_op))(_one_job(lambda c, op=_op: C.concurrent(c, op), "cube"))
    query(f"calls_{_name}_concurrent_planned", C.concurrent_sql(_op))(_one_job(lambda c, op=_op: C.concurrent(c, op), "planned"))


def _cube_counts(build):
    def run(spark, sf):
        ids = MultiJoinEngine(spark).single(build(C.relation(spark, sf)), method="cube")
        return ids.groupBy("id").agg(F.count("*").alias("n"))

    return run


query("calls_w3_same_id_cube", W3_SAME_SQL)(_cube_counts(lambda c: C.three_days(c, "=", True)))
query("calls_w3_same_id_planned", W3_SAME_SQL)(_counted(lambda c: C.three_days(c, "=", True), infer=False))
query("calls_w4_same_id_cube", W4_SAME_SQL)(_cube_counts(lambda c: C.three_days(c, "<>", True)))
query("calls_w4_same_id_planned", W4_SAME_SQL)(_counted(lambda c: C.three_days(c, "<>", True), infer=False))


@query("itinerary", C.ITINERARY_SQL)
def itinerary(spark, sf):
    return MultiJoinEngine(spark).run(C.itinerary(spark, sf))


LEGS_BAND_SQL = f"""{C.LEGS_SQL} SELECT a.rid AS a_rid, b.rid AS b_rid FROM legs a, legs b WHERE a.leg = 'signup' AND b.leg = 'view'
AND epoch(b.dep) >= epoch(a.arr) + 300 AND epoch(b.dep) <= epoch(a.arr) + 3600"""


@query("legs_band", LEGS_BAND_SQL)
def legs_band(spark, sf):
    leg = legs(spark, sf)
    a = leg.where("leg = 'signup'").select(F.col("rid").alias("a_rid"), F.col("arr").cast("timestamp").cast("double").alias("x"))
    b = leg.where("leg = 'view'").select(F.col("rid").alias("b_rid"), F.col("dep").cast("timestamp").cast("double").alias("y"))
    return band_join(a, b, "x", "y", 300, 3600).select("a_rid", "b_rid")


for _name, _star in T.STARS.items():
    query(_name, _star.sql())(_star.run)


@query("unequal_star", T.STARS["unequal_star"].sql())
def unequal_star(spark, sf):
    """Its answer is the numbers by nation, so the joined rows are not given out."""
    return MultiJoinEngine(spark).grouped_counts(T.STARS["unequal_star"].query(spark, sf), "n", "n_nationkey", "nation")


for _name, _star in T.FORMS.items():
    for _how in ("cube", "planned"):
        query(f"{_name}_{_how}", T.SQL.get(_name) or _star.sql())(lambda spark, sf, star=_star, how=_how: star.run(spark, sf, how))
for _name, _sql in T.SQL.items():
    query(_name, _sql)(lambda spark, sf, sql=_sql: T.run_sql(spark, sf, sql))

HOURS = [1] * 7 + [3] * 12 + [2] * 5


@query("scaled_calls", f"{C.CALLS_SQL} SELECT id, (count(*) * 3)::BIGINT AS n FROM calls GROUP BY id")
def scaled_calls(spark, sf):
    return scale_calls(calls(spark, sf), 3, HOURS).groupBy("id").agg(F.count("*").alias("n"))


# ---- one workload by every curve, number of regions and strategy ---------------------------------------------------------


def _single(k: int, curve: str = "hilbert", **options):
    def run(spark, sf):
        return _w1_by(C.relation(spark, sf), k, curve=curve, **options)

    return run


def _w1_by(c, k: int, **options):
    """All combinations of w1 in one job; they are counted by id in it, and only the numbers are written."""
    q = C.w1(c)
    with co_partitioned(c.sparkSession):
        return count_by(q, materialise(per_id("lead")(chain_join(q, None, k, **options))), "lead", "id", "id")


for _curve in ("hilbert", "zorder", "grid", "rowmajor", "random", "auto"):
    query(f"w1_single_{_curve}", W1_SQL)(_single(7, _curve))
for _k in (1, 5, 9):
    query(f"w1_k{_k}", W1_SQL)(_single(_k))
query("w1_dense_coord", W1_SQL)(_single(7, coord="dense"))
query("w1_pairwise", W1_SQL)(_counted(C.w1, strategy="pairwise"))
query("w1_planned", W1_SQL)(_counted(C.w1))
query("w3_single", W3_SAME_SQL)(_counted(lambda c: C.three_days(c, "=", True), strategy="single", infer=False))
query("w3_planned", W3_SAME_SQL)(_counted(lambda c: C.three_days(c, "=", True)))
query("w3_jobs_forced", W3_SAME_SQL)(_counted(lambda c: C.three_days(c, "=", True), jobs=[[1, 2, 3, 5, 6], [4, 7]]))


@query("w1_range_coord", W1_SQL)
def w1_range_coord(spark, sf):
    c = C.relation(spark, sf)
    cuts = {"lead": ("bt", quantiles(c, "bt", 16)), "mid": ("bt", quantiles(c, "bt", 16))}
    return _w1_by(c, 7, coord="range", bounds=cuts)


@query("w1_range_pruned", W1_SQL)
def w1_range_pruned(spark, sf):
    c = C.relation(spark, sf)
    cuts = {"lead": ("bt", quantiles(c, "bt", 16)), "mid": ("bt", quantiles(c, "bt", 16))}
    return _w1_by(c, 7, coord="range", bounds=cuts, prune=True)


@query("w1_sorted_pairs", f"{C.CALLS_SQL} SELECT lead.id AS id, count(*)::BIGINT AS n FROM calls lead, calls mid WHERE lead.bt <= mid.bt AND lead.l >= mid.l AND lead.bsc <> mid.bsc GROUP BY lead.id")
def w1_sorted_pairs(spark, sf):
    c = C.relation(spark, sf)
    q = multi_join(lead=c, mid=c).on("lead.bt <= mid.bt", "lead.l >= mid.l", "lead.bsc <> mid.bsc").build()
    return count_by(q, sorted_pairs(q, None, 7, counted=True), "lead", "id", "id")


@query("regions_by_table_function")
def regions_by_table_function(spark, sf):
    """Events by their coordinate (n), and its copies in each relation by the table function; tests hold them against the routed rows."""
    a = assign_regions(2, 5, "hilbert", 3)
    register_regions_of(spark, a, ["left", "right"])
    load(spark, sf, "events").groupBy(F.pmod("event_id", F.lit(8)).cast("int").alias("c")).agg(F.count("*").alias("n")).createOrReplaceTempView("mjoin_coords")
    return spark.sql("SELECT x.alias, c, n, region FROM (SELECT explode(array('left', 'right')) AS alias) x, mjoin_coords, LATERAL regions_of(x.alias, c)")


# ---- baselines -----------------------------------------------------------------------------------------------------------


def _weighed(fn, build=C.w1):
    """The method over distinct values with weights: every combination of values is visited, equal rows at once."""

    def run(spark, sf):
        q = weighted(build(C.relation(spark, sf)), "lead", "id")
        with co_partitioned(spark):
            return materialise(weigh(fn(q), "lead"), "weighed")

    return run


query("native", W1_SQL)(_weighed(lambda q: B.native(q, "lead")))
query("op_by_op", W1_SQL)(_weighed(lambda q: B.op_by_op(q, sums="lead")))
query("correlation_merge", W1_SQL)(_weighed(lambda q: B.correlation_merge(q, sums="lead")))
query("correlation_input_only", W1_SQL)(_weighed(lambda q: B.correlation_merge(q, ("input",), "lead")))
query("correlation_transit_only", W1_SQL)(_weighed(lambda q: B.correlation_merge(q, ("transit",), "lead")))
query("correlation_flow_only", W1_SQL)(_weighed(lambda q: B.correlation_merge(q, ("flow",), "lead")))
query("pairwise_rect", W1_SQL)(_weighed(lambda q: B.pairwise_rect(q, sums="lead")))
query("pairwise_scheduled", W1_SQL)(_weighed(lambda q: B.pairwise_scheduled(q, sums="lead")))
query("replicate_all", W1_SQL)(_weighed(lambda q: B.replicate_all(q, sums="lead")))
query("w1_balanced_bits", W1_SQL)(_weighed(lambda q: chain_join(q, None, 6, bits="balanced", hint="shuffle_hash", sums="lead")))


#: Methods that visit whole products, over whole small tables.
for _name, _fn in (("dataflow", B.dataflow), ("brute_force", B.brute_force)):
    query(_name, T.NEAR_NATIONS.sql())(lambda spark, sf, fn=_fn: hydrate(q := T.NEAR_NATIONS.query(spark, sf), fn(q)))

SHARES_SQL = """SELECT o_orderkey, count(*)::BIGINT AS n FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey
WHERE c_mktsegment = 'BUILDING' GROUP BY o_orderkey"""


@query("shares_equi", SHARES_SQL)
def shares_equi(spark, sf):
    c, o, li = (load(spark, sf, t) for t in ("customer", "orders", "lineitem"))
    q = multi_join(c=c.where("c_mktsegment = 'BUILDING'"), o=o, l=li).on("c.c_custkey = o.o_custkey", "o.o_orderkey = l.l_orderkey").rid(c="c_custkey", o="o_orderkey", l="l_linenumber").build()
    return B.shares_equi(q, 8).groupBy(F.col("o__rid").alias("o_orderkey")).agg(F.count("*").alias("n"))


@query("hash_equi", "SELECT o_orderkey, l_linenumber, l_quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderstatus = 'F'")
def hash_equi(spark, sf):
    o, li = load(spark, sf, "orders").where("o_orderstatus = 'F'").select("o_orderkey"), load(spark, sf, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_linenumber", "l_quantity")
    return B.hash_equi(o, li, "o_orderkey")


#: Least cosine of alike vectors, planes of a key, and the share of alike pairs that must share a key.
ALIKE, KEY_PLANES, KEY_RECALL = 0.3, 4, 0.95


def planes(n: int, dims: int) -> list[list[float]]:
    """Random directions, the same each time."""
    return np.random.default_rng(7).normal(size=(n, dims)).round(6).tolist()


ALIKE_SQL = f"""SELECT x.vec_id AS left_rid, y.vec_id AS right_rid FROM (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings) x,
(SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings) y
WHERE x.vec_id < y.vec_id AND list_dot_product(x.e, y.e) >= {ALIKE} * sqrt(list_dot_product(x.e, x.e) * list_dot_product(y.e, y.e))"""


@query("alike_pairs", ALIKE_SQL)
def alike_pairs(spark, sf):
    """All pairs of embeddings of the cosine or more, by pairs of blocks: the exact way beside key_set."""
    return B.block_pairs(load(spark, sf, "embeddings"), "vec_id", "embedding", ALIKE)


@query("key_set")
def key_set(spark, sf):
    """Pairs of embeddings of the cosine or more that share a side of the planes in some band; all verified.

    Bands are as many as give pairs at the threshold the recall; key_set_recall measures it against alike_pairs.
    """
    e = load(spark, sf, "embeddings")
    dims = (e.select(F.size("embedding").alias("n")).first() or {"n": 1})["n"]
    bands = B.bands_for(ALIKE, KEY_PLANES, KEY_RECALL)
    return B.key_set_pairs(e, "vec_id", sign_keys(F.col("embedding"), planes(bands * KEY_PLANES, dims), bands), "embedding", ALIKE)


@query("key_set_recall")
def key_set_recall(spark, sf):
    """Pairs found by keys, all alike pairs, and the share found."""
    found, every = key_set(spark, sf), alike_pairs(spark, sf)
    both = found.join(every, ["left_rid", "right_rid"]).agg(F.count("*").alias("found"))
    return both.crossJoin(every.agg(F.count("*").alias("alike"))).withColumn("recall", F.col("found") / F.greatest("alike", F.lit(1)))


# ---- measures ------------------------------------------------------------------------------------------------------------


def _events(spark, sf) -> int:
    """Rows of events, by reading a column of them."""
    return load(spark, sf, "events").agg(F.count("event_id")).first()[0]


@query("score_table")
def score_table(spark, sf):
    """Scores of joins of 2 to 4 copies of events."""
    n = _events(spark, sf)
    rows = [(m, k, curve, partition_score(assign_regions(m, k, curve, b), [n] * m)) for m, b in ((2, 4), (3, 3), (4, 2)) for k in (1, 2, 4, 8, 16) for curve in ("hilbert", "zorder", "rowmajor", "grid")]
    return spark.createDataFrame(rows, "m int, k int, curve string, score double")


@query("score_powers", "SELECT m::INT AS m, k::INT AS k, (copies * n)::DOUBLE AS score FROM (SELECT count(event_id) AS n FROM events), (VALUES (2, 4, 4), (2, 16, 8), (3, 2, 5), (3, 4, 8), (3, 8, 12), (3, 16, 20), (4, 2, 7), (4, 4, 12), (4, 8, 20), (4, 16, 32)) v(m, k, copies)")
def score_powers(spark, sf):
    n = _events(spark, sf)
    rows = [(m, k, float(partition_score(assign_regions(m, k, "hilbert", b), [n] * m))) for m, b, ks in ((2, 4, (4, 16)), (3, 3, (2, 4, 8, 16)), (4, 2, (2, 4, 8, 16))) for k in ks]
    return spark.createDataFrame(rows, "m int, k int, score double")


@query("copies_by_relation")
def copies_measured(spark, sf):
    q = C.w1(C.relation(spark, sf))
    sent = M.copies(M.routed(q, 7))
    a, order = assign_regions(3, 7), ["lead", "mid", "tail"]
    expected = spark.createDataFrame(list(zip(order, copies_by_relation(a, [1.0] * 3), strict=True)), "alias string, predicted_factor double")
    return sent.join(expected, "alias").withColumn("factor", F.col("copies") / F.col("rows"))


@query("region_skew")
def region_skew(spark, sf):
    return M.region_skew(M.routed(C.w1(C.relation(spark, sf)), 7))


@query("delta_scan", "SELECT k::INT AS k, round(0.4 * 3 * n * pow(k, 2.0 / 3) + 0.6 * n * n * n / k, 3) AS delta FROM range(1, 65) t(k), (SELECT count(event_id) / 1000.0::DOUBLE AS n FROM events)")
def delta_scan(spark, sf):
    """The curve for a join of three copies of events, in thousands of rows."""
    n = _events(spark, sf) / 1000
    return spark.createDataFrame([(k, round(delta_curve(k, [n] * 3), 3)) for k in range(1, 65)], "k int, delta double")


@query("cost_model_grid", Y.COST_GRID_SQL)
def cost_model_grid(spark, sf):
    rows = [(*r[:4], *(round(x, 6) for x in r[4:])) for r in Y.cost_grid(_events(spark, sf))]
    return spark.createDataFrame(rows, "maps int, slots int, reducers int, c2 double, map_phase double, copy_phase double, reduce_phase double, total double")


@query("schedule_example", "SELECT method, round(makespan * n, 6)::DOUBLE AS makespan, round(ended * n, 6)::DOUBLE AS ended FROM (SELECT count(event_id) / 1000.0::DOUBLE AS n FROM events), (VALUES ('eps', 9, 11), ('exact', 9, 11), ('greedy', 9, 11), ('parallel', 9, 11), ('serial', 21, 23)) v(method, makespan, ended)")
def schedule_example(spark, sf):
    """The example's jobs over events: its times are those of a thousand rows."""
    rows, n = [], _events(spark, sf) / 1000
    tasks = [replace(t, options=tuple((units, seconds * n) for units, seconds in t.options)) for t in Y.EXAMPLE_TASKS]
    for method in ("eps", "exact", "greedy", "parallel", "serial"):
        s = merge_plan(schedule_jobs(tasks, 16, method), tasks, lambda a, b: 2.0 * n)
        rows.append((method, round(float(s.makespan), 6), round(float(s.end), 6)))
    return spark.createDataFrame(rows, "method string, makespan double, ended double")


#: Six conditions between kinds of events, those whose kinds follow each other most often in a subscriber's calls; and their trails
#: by a recursive query: walks that use no condition twice, one for each pair of ends and set of conditions.
TRAILS_SQL = """WITH RECURSIVE x AS (SELECT event_type AS t, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS u FROM events),
e AS (SELECT least(t, u) AS a, greatest(t, u) AS b, (row_number() OVER (ORDER BY count(*) DESC, least(t, u), greatest(t, u)))::INT AS k FROM x WHERE t <> u GROUP BY least(t, u), greatest(t, u) QUALIFY k <= 6),
d AS (SELECT a, b, k FROM e UNION ALL SELECT b, a, k FROM e),
w(s, t, used) AS (SELECT a, b, [k] FROM d UNION SELECT s, d.b, list_sort(list_append(used, d.k)) FROM w JOIN d ON w.t = d.a AND NOT list_contains(used, d.k))
SELECT DISTINCT least(s, t) AS src, greatest(s, t) AS dst, array_to_string(used, ',') AS labels FROM w"""


def _kinds_graph(spark, sf) -> JoinGraph:
    """The graph of TRAILS_SQL: kinds of events and the six conditions between them."""
    after = F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    x = load(spark, sf, "events").select(F.col("event_type").alias("t"), after.alias("u")).where("t <> u")
    pairs = x.groupBy(F.least("t", "u").alias("a"), F.greatest("t", "u").alias("b")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "a", "b").limit(6).collect()
    return JoinGraph(tuple(sorted({v for r in pairs for v in (r["a"], r["b"])})), {k: (r["a"], r["b"]) for k, r in enumerate(pairs, 1)})


@query("trail_graph_example", TRAILS_SQL)
def trail_graph_example(spark, sf):
    rows = [(t.src, t.dst, ",".join(map(str, sorted(t.labels)))) for t in enumerate_trails(_kinds_graph(spark, sf))]
    return spark.createDataFrame(rows, "src string, dst string, labels string")


def _example_coster(spark, sf):
    """Costs of jobs of the example graph, whose relations are the events of five groups of subscribers, in thousands of rows."""
    n = {f"R{r['g'] + 1}": r["n"] / 1000 for r in load(spark, sf, "events").groupBy(F.pmod("user_id", F.lit(5)).alias("g")).agg(F.count("event_id").alias("n")).collect()}

    def cost(labels):
        rows = sum(n.get(a, 0.0) for a in {a for k in labels for a in Y.EXAMPLE_GRAPH.edges[k]})
        return rows * len(labels) ** 0.5 + min(labels) / 10, len(labels)

    return cost


@query("pruned_trails_example")
def pruned_trails_example(spark, sf):
    return trail_table(spark, build_pruned_trails(Y.EXAMPLE_GRAPH, _example_coster(spark, sf)))


@query("cover_example")
def cover_example(spark, sf):
    kept = build_pruned_trails(Y.EXAMPLE_GRAPH, _example_coster(spark, sf)).kept
    rows = [(m, sorted(c.labels), c.weight) for m, f in (("greedy", greedy_cover), ("exact", exact_cover)) for c in f(kept, Y.EXAMPLE_GRAPH.edges)]
    return spark.createDataFrame(rows, "method string, labels array<int>, weight double")


FEATURES = {"w1": lambda c: C.w1(c), "w2": lambda c: C.w2(c), "w3": lambda c: C.three_days(c, "=", False), "w4": lambda c: C.three_days(c, "<>", False)}


@query("query_features", "SELECT v.*, n_rows FROM (VALUES ('w1', 3, 2, '<= >='), ('w2', 3, 2, '<= <> >='), ('w3', 4, 4, '< >'), ('w4', 4, 4, '< <> >')) v(workload, relations, pairs, operators), (SELECT count(event_id) AS n_rows FROM events)")
def query_features(spark, sf):
    """Features of the call queries and the rows of each of their relations."""
    c = C.relation(spark, sf)
    features = spark.createDataFrame([(k, *M.query_features(f(c))) for k, f in FEATURES.items()], "workload string, relations int, pairs int, operators string")
    return features.crossJoin(c.agg(F.count("rid").alias("n_rows")))


@query("selectivity_exact", f"""{C.CALLS_SQL}, c AS (SELECT * FROM calls), t AS (SELECT count(*) AS n FROM c),
s AS (SELECT bsc, d, count(*) AS w FROM c GROUP BY ALL), m AS (SELECT bt, l, sum(w) AS w FROM c JOIN s USING (bsc, d) GROUP BY ALL),
r AS (SELECT sum(m.w) AS n FROM c lead JOIN m ON lead.bt <= m.bt AND lead.l >= m.l) SELECT r.n::BIGINT AS n_rows, round(r.n::DOUBLE / (t.n::DOUBLE * t.n * t.n), 9) AS of_product, round(r.n::DOUBLE / t.n, 6) AS of_largest FROM r, t""")
def selectivity_exact(spark, sf):
    q = C.w1(C.relation(spark, sf))
    n = MultiJoinEngine(spark).grouped_counts(q, "lead", "id").agg(F.sum("n")).first()[0] or 0
    product, largest = M.selectivity(n, q)
    return spark.createDataFrame([(n, round(product, 9), round(largest, 6))], "n_rows bigint, of_product double, of_largest double")


@query("selectivity_sample")
def selectivity_sample(spark, sf):
    s = collect_statistics(C.w1(C.relation(spark, sf)))
    return spark.createDataFrame(sorted(s.selectivity.items()), "label int, selectivity double")


@query("selectivity_by_day", f"{C.CALLS_SQL} SELECT d, round(avg((l >= bsc)::INT), 9) AS share FROM calls GROUP BY d")
def selectivity_by_day(spark, sf):
    """Share of the calls of a day of at least as many minutes as their station's number, by the aggregate function."""
    return C.relation(spark, sf).groupBy("d").agg(selectivity_agg(">=")("l", "bsc").alias("share")).select("d", F.round("share", 9).alias("share"))


@query("plan_explain")
def plan_explain(spark, sf):
    return explain(spark, MultiJoinEngine(spark).plan(C.three_days(C.relation(spark, sf), "=", False)))


def _planned_queries(spark, sf) -> dict:
    """The call queries and the decision-support queries of the experiments, with their statistics."""
    c = C.relation(spark, sf)
    built = {name: build(c) for name, build in FEATURES.items()} | {name: star.query(spark, sf) for name, star in T.FORMS.items()}
    return {name: (q, collect_statistics(q)) for name, q in built.items()}


STRATEGIES = ("planned", "single", "pairwise")


@query("units_sweep")
def units_sweep(spark, sf):
    """Predicted makespan of the experiments' queries on 96 and 64 units and fewer, by strategy."""
    rows = []
    for name, (q, stats) in _planned_queries(spark, sf).items():
        for units in (4, 16, 64, 96):
            for strategy in STRATEGIES:
                p = MultiJoinEngine(spark, units).planner.plan(q, units, stats, strategy)
                rows.append((name, units, strategy, p.cost, len(p.jobs)))
    return spark.createDataFrame(rows, "workload string, units int, strategy string, seconds double, jobs int")


@query("scale_sweep")
def scale_sweep(spark, sf):
    """Predicted seconds of the call queries for 1, 5 and 25 times the calls (as from 20 to 100 and 500 GB) on 64 and 96 units."""
    c, rows = C.relation(spark, sf), []
    for name, build in FEATURES.items():
        q = build(c)
        stats = collect_statistics(q)
        for factor in (1, 5, 25):
            more = replace(stats, rows={a: n * factor for a, n in stats.rows.items()})
            for units in (64, 96):
                for strategy in STRATEGIES:
                    rows.append((name, factor, units, strategy, MultiJoinEngine(spark, units).planner.plan(q, units, more, strategy).cost))
    return spark.createDataFrame(rows, "workload string, factor int, units int, strategy string, seconds double")


@query("plan_jobs")
def plan_jobs(spark, sf):
    """Jobs of each plan, the rows that they are expected to write before the last merge, and how each job joins."""
    rows = []
    for name, (q, stats) in _planned_queries(spark, sf).items():
        for strategy in STRATEGIES:
            p = MultiJoinEngine(spark, 64).planner.plan(q, 64, stats, strategy)
            between = sum(estimate_rows(q, stats, c.labels) for c in p.jobs) if len(p.jobs) > 1 else 0.0
            rows.append((name, strategy, len(p.jobs), between, ",".join(sorted(p.methods.values()))))
    return spark.createDataFrame(rows, "workload string, strategy string, jobs int, rows_between double, methods string")


@query("prediction_error")
def prediction_error(spark, sf):
    """Seconds of the jobs of w3 with one subscriber as planned and as measured."""
    q, rows = C.three_days(C.relation(spark, sf), "=", True), []
    for strategy in STRATEGIES:
        engine = MultiJoinEngine(spark)
        t = time.perf_counter()
        engine.counts(q, "lead", "id", strategy=strategy).count()
        rows.append((strategy, engine.last[0].cost, time.perf_counter() - t))
    return spark.createDataFrame(rows, "strategy string, predicted double, measured double")


@query("load_report")
def load_report(spark, sf):
    """Seconds of a plain copy, a table of the warehouse, a copy with statistics and range layout, and I/O rates."""
    c = calls(spark, sf)
    rows, table = [], f"mjoin_load_{uuid.uuid4().hex[:8]}"
    for name, action in (("plain", lambda: plain_load(c, scratch(spark, "load"))), ("table", lambda: table_load(c, table)), ("statistics", lambda: ingest(c, scratch(spark, "load"), ["d", "bt"], 8))):
        t = time.perf_counter()
        action()
        rows.append((name, time.perf_counter() - t))
    spark.sql(f"DROP TABLE IF EXISTS {table}")
    rates = M.io_probe(c, scratch(spark, "load-io"))
    rows += [(k, float(v)) for k, v in rates.items()]
    return spark.createDataFrame(rows, "measure string, value double")


SQL_FRONT = "SELECT a.s_suppkey AS skey, b.c_custkey AS ckey FROM supplier a, customer b WHERE a.s_acctbal < b.c_acctbal AND a.s_acctbal + 20 > b.c_acctbal AND b.c_mktsegment = 'BUILDING'"


@query("sql_front", SQL_FRONT)
def sql_front(spark, sf):
    tables = {t: load(spark, sf, t) for t in ("supplier", "customer")}
    return MultiJoinEngine(spark).sql(SQL_FRONT, tables, {"a": "s_suppkey", "b": "c_custkey"})


@query("controlled_output", "WITH e AS (SELECT event_id % 50 AS key FROM events) SELECT a.key AS key, (count(*) * count(*))::BIGINT AS n FROM e a GROUP BY a.key")
def controlled_output(spark, sf):
    """Numbers of the probe join's pairs by key: rows of a key count once, with their number as weight."""
    return Y.controlled_counts(spark, sf, 50)


@query("calibration")
def calibration(spark, sf):
    _, rows = Y.calibrate(spark, sf, [200, 1000], [2, 8])
    return spark.createDataFrame(rows, "groups int, reducers int, n_rows bigint, measured double, predicted double")


@query("calibration_curves")
def calibration_curves(spark, sf):
    """The fitted spill and connection curves, and the cost of w3 with one subscriber planned with them."""
    params, _ = Y.calibrate(spark, sf, [200, 1000], [2, 8])
    rows = [("spill", x, y) for x, y in params.spill.points] + [("connect", x, y) for x, y in params.connect.points]
    plan = MultiJoinEngine(spark, planner=Planner(params)).plan(C.three_days(C.relation(spark, sf), "=", True))
    return spark.createDataFrame([*rows, ("planned", float(len(plan.jobs)), float(plan.cost))], "curve string, x double, seconds double")


@query("best_reducers")
def best_reducers(spark, sf):
    """Fastest number of reducers of the sample join by copies of its input, and the number that the fit gives."""
    size = 24.0 * load(spark, sf, "events").count()
    best, fit = Y.best_reducers(Y.measure_grid(spark, sf, [1, 4, 16], [2, 4, 8, 16]), size)
    return spark.createDataFrame([(f, r, best_fitted(f * size, fit)) for f, r in best], "factor int, best int, fitted int")


#: Both curves over a 16 by 16 grid: one digit of base four a level, the square turned as the level's quadrant asks.
HILBERT_SQL = """WITH RECURSIVE g AS (SELECT (range // 16)::INT AS x, (range % 16)::INT AS y FROM range(256)),
w(x0, y0, x, y, s, h, z) AS (SELECT x, y, x, y, 8, 0::BIGINT, 0::BIGINT FROM g UNION ALL
SELECT x0, y0, CASE WHEN qy = 0 THEN (CASE WHEN qx = 1 THEN s - 1 - ly ELSE ly END) ELSE lx END, CASE WHEN qy = 0 THEN (CASE WHEN qx = 1 THEN s - 1 - lx ELSE lx END) ELSE ly END,
s // 2, h * 4 + xor(3 * qx, qy), z * 4 + {first} * 2 + {second}
FROM (SELECT *, (x // s) % 2 AS qx, (y // s) % 2 AS qy, x % s AS lx, y % s AS ly, (x0 // s) % 2 AS ox, (y0 // s) % 2 AS oy FROM w WHERE s > 0))
SELECT x0 AS x, y0 AS y, h AS hilbert, z AS zorder FROM w WHERE s = 0"""


@query("hilbert_positions", f"SELECT event_id, x, y, hilbert, zorder FROM events JOIN ({HILBERT_SQL.format(first='ox', second='oy')}) p ON p.x = user_id % 16 AND p.y = event_id % 16")
def hilbert_positions(spark, sf):
    """Positions of events on a 16 by 16 grid by SQL expressions."""
    grid = load(spark, sf, "events").select("event_id", (F.col("user_id") % 16).cast("int").alias("x"), (F.col("event_id") % 16).cast("int").alias("y"))
    return grid.withColumn("hilbert", hilbert_expr([F.col("x"), F.col("y")], 4)).withColumn("zorder", zorder_expr([F.col("x"), F.col("y")], 4))


# ---- relational operators ------------------------------------------------------------------------------------------------


def sql_operator(name: str, text: str, duck: str | None = None):
    """One text for both engines unless DuckDB needs its own."""
    query(name, duck or text)(lambda spark, sf: T.run_sql(spark, sf, text))


@query("op_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > c_acctbal * 40)")
def op_semi(spark, sf):
    c, o = load(spark, sf, "customer"), load(spark, sf, "orders")
    return semi_join(c, o, (c.c_custkey == o.o_custkey) & (o.o_totalprice > c.c_acctbal * 40)).select("c_custkey")


@query("op_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > c_acctbal * 40)")
def op_anti(spark, sf):
    c, o = load(spark, sf, "customer"), load(spark, sf, "orders")
    return anti_join(c, o, (c.c_custkey == o.o_custkey) & (o.o_totalprice > c.c_acctbal * 40)).select("c_custkey")


@query("op_asof", f"""{C.CALLS_SQL}, t AS (SELECT rid, id, d * 86400 + bt AS tm, bsc FROM calls), b AS (SELECT id, tm, max(bsc) AS bsc FROM t GROUP BY id, tm)
SELECT a.rid AS rid, coalesce(b.bsc, -1)::INT AS asof_bsc FROM t a ASOF LEFT JOIN b ON a.id = b.id AND a.tm > b.tm""")
def op_asof(spark, sf):
    t = calls(spark, sf).select("rid", "id", (F.col("d") * 86400 + F.col("bt")).alias("at"), "bsc")
    last = t.groupBy("id", "at").agg(F.max("bsc").alias("bsc"))
    return join_asof(t.select("rid", "id", "at"), last, "id", "at", ["bsc"]).select("rid", F.coalesce("asof_bsc", F.lit(-1)).alias("asof_bsc"))


@query("op_salted", "SELECT event_type, (count(*) * 2)::BIGINT AS n FROM events GROUP BY event_type")
def op_salted(spark, sf):
    e = load(spark, sf, "events").select("event_id", "event_type")
    kinds = e.select("event_type").distinct().withColumn("x", F.explode(F.array(F.lit(1), F.lit(2))))
    return salted_join(e, kinds, "event_type", 8).groupBy("event_type").agg(F.count("*").alias("n"))


@query("op_topk", "SELECT o_custkey, o_orderkey, o_totalprice FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def op_topk(spark, sf):
    return top_k_by(load(spark, sf, "orders"), "o_custkey", [F.col("o_totalprice").desc(), F.col("o_orderkey")], 2).select("o_custkey", "o_orderkey", "o_totalprice")


sql_operator("op_outer_left", "SELECT s_suppkey, count(c_custkey) AS n FROM supplier LEFT JOIN customer ON s_nationkey = c_nationkey AND c_acctbal > s_acctbal GROUP BY s_suppkey")
sql_operator("op_outer_full", "SELECT coalesce(s_suppkey, -1) AS s_suppkey, coalesce(c_custkey, -1) AS c_custkey FROM supplier FULL JOIN customer ON s_suppkey = c_custkey AND s_acctbal < c_acctbal")
sql_operator("op_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping(o_orderstatus) AS g FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
sql_operator("op_rollup", "SELECT coalesce(seg, 'all') AS seg, coalesce(nat, -1) AS nat, n FROM (SELECT c_mktsegment AS seg, c_nationkey AS nat, count(*) AS n FROM customer GROUP BY ROLLUP (c_mktsegment, c_nationkey)) x")
sql_operator("op_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
sql_operator("op_rank", "SELECT p_partkey, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS r, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS dr, ntile(4) OVER (ORDER BY p_partkey) AS q FROM part")
sql_operator("op_lag", "SELECT event_id, coalesce(lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id), -1) AS before, coalesce(lead(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id), -1) AS later FROM events")
sql_operator("op_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_totalprice RANGE BETWEEN 10000 PRECEDING AND 10000 FOLLOWING) AS near FROM orders")
sql_operator("op_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
sql_operator("op_intersect_all", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
sql_operator("op_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
sql_operator("op_scalar_subquery", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.9 FROM orders)")
sql_operator("op_exists", "SELECT n_name FROM nation WHERE EXISTS (SELECT 1 FROM supplier WHERE s_nationkey = n_nationkey AND s_acctbal < 0)")
sql_operator("op_in", "SELECT c_custkey FROM customer WHERE c_nationkey IN (SELECT s_nationkey FROM supplier WHERE s_acctbal > 9000)")
sql_operator("op_lateral", "SELECT n_nationkey, x.s_suppkey FROM nation, LATERAL (SELECT s_suppkey FROM supplier WHERE s_nationkey = n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 1) x")
sql_operator("op_count_distinct", "SELECT user_id, count(DISTINCT event_type) AS kinds, count(DISTINCT CAST(ts AS DATE)) AS days FROM events GROUP BY user_id")
sql_operator("op_having", "SELECT l_orderkey, sum(l_quantity) AS q FROM lineitem GROUP BY l_orderkey HAVING sum(l_quantity) >= 250")
sql_operator("op_null_safe", "SELECT a.n_nationkey FROM nation a JOIN nation b ON a.n_nationkey + 1 <=> b.n_nationkey", "SELECT a.n_nationkey FROM nation a JOIN nation b ON a.n_nationkey + 1 IS NOT DISTINCT FROM b.n_nationkey")
sql_operator("op_predicates", "SELECT p_partkey FROM part WHERE (p_size BETWEEN 5 AND 15 AND p_brand IN ('Brand#12', 'Brand#23')) OR (p_name LIKE '%red%' AND NOT p_size > 40) OR p_type IS NULL")
sql_operator("op_pivot", "SELECT * FROM (SELECT o_orderpriority, o_orderstatus FROM orders) PIVOT (count(*) FOR o_orderstatus IN ('F' AS f, 'O' AS o, 'P' AS p))",
             "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY o_orderpriority")
sql_operator("op_percentile", "SELECT l_returnflag, round(percentile(l_quantity, 0.5), 6) AS med FROM lineitem GROUP BY l_returnflag", "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS med FROM lineitem GROUP BY l_returnflag")
sql_operator("op_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
sql_operator("op_array", "SELECT vec_id, size(embedding) AS n, round(aggregate(embedding, 0D, (s, x) -> s + x), 4) AS total FROM embeddings", "SELECT vec_id, len(embedding)::INT AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE)), 4) AS total FROM embeddings")
sql_operator("op_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, datediff(DATE'2002-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders", "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, date_diff('day', CAST(o_orderdate AS DATE), DATE '2002-01-01')::INT AS days FROM orders")
sql_operator("op_math", "SELECT s_suppkey, CAST(floor(s_acctbal) AS BIGINT) AS lo, CAST(ceil(s_acctbal) AS BIGINT) AS hi, greatest(s_acctbal, 0) AS pos, round(sqrt(abs(s_acctbal)), 6) AS root FROM supplier")
sql_operator("op_string", "SELECT c_custkey, substring(c_name, 1, 8) AS head, lower(c_mktsegment) AS seg, length(c_name) AS n, concat_ws('-', c_name, c_mktsegment) AS both FROM customer")
sql_operator("op_conversation_steps", "SELECT a.conv_id, a.turn, min(b.turn) AS later FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.turn < b.turn GROUP BY a.conv_id, a.turn")


# ---- streams -------------------------------------------------------------------------------------------------------------


def _call_stream(spark, sf):
    e = load(spark, sf, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("id"), F.get_json_object("props", "$.k").cast("int").alias("bsc"), F.col("value").alias("l"))
    return S.file_stream(spark, e, 4, "40 days")


@query("stream_station_load", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, CAST(json_extract_string(props, '$.k') AS INT) AS bsc, count(*)::BIGINT AS calls FROM events GROUP BY ALL")
def stream_station_load(spark, sf):
    out = S.finish(S.station_load(_call_stream(spark, sf), "1 day"), "complete")
    return out.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "bsc", "calls")


@query("stream_session", """WITH x AS (SELECT user_id AS id, ts, ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR AS fresh FROM events),
y AS (SELECT id, sum(CASE WHEN fresh THEN 1 ELSE 0 END) OVER (PARTITION BY id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM x) SELECT id, count(*)::BIGINT AS calls FROM y GROUP BY id, s""")
def stream_session(spark, sf):
    return S.finish(S.sessions(_call_stream(spark, sf), "6 hours"), "complete").select("id", "calls")


@query("stream_interval_chain", f"{C.LEGS_SQL} SELECT a.rid AS a_rid, b.rid AS b_rid FROM legs a, legs b WHERE a.leg = 'signup' AND b.leg = 'view' AND a.arr + INTERVAL 5 MINUTE < b.dep AND b.dep < a.arr + INTERVAL 60 MINUTE")
def stream_interval_chain(spark, sf):
    leg = legs(spark, sf)
    a = S.file_stream(spark, leg.where("leg = 'signup'").select(F.col("rid").alias("a_rid"), F.col("arr").cast("timestamp").alias("arr")), 3, "40 days", "arr")
    b = S.file_stream(spark, leg.where("leg = 'view'").select(F.col("rid").alias("b_rid"), F.col("dep").cast("timestamp").alias("dep")), 3, "40 days", "dep")
    # a bounded replay: the watermark spans all of it, so that no row is late whatever order its files come in
    return S.finish(S.interval_edge(a, b, "arr", "dep", 300, 3600)).select("a_rid", "b_rid")


@query("stream_streak", f"""{C.CALLS_SQL}, x AS (SELECT DISTINCT id, d FROM calls) SELECT a.id AS id, c.d AS day FROM x a JOIN x b ON a.id = b.id AND b.d = a.d + 1 JOIN x c ON c.id = b.id AND c.d = b.d + 1""")
def stream_streak(spark, sf):
    c = calls(spark, sf).select("id", "d")
    return S.finish(S.streaks(S.file_stream(spark, c, 4, None, "d"))).select("id", "day")


@query("stream_dedup", "SELECT user_id AS id, json_extract_string(props, '$.k')::INT AS bsc FROM events GROUP BY ALL")
def stream_dedup(spark, sf):
    s = S.file_stream(spark, load(spark, sf, "events").select(F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("id"), F.get_json_object("props", "$.k").cast("int").alias("bsc")), 4, "60 days")
    return S.finish(S.dedup(s, "id", "bsc")).select("id", "bsc")


@query("stream_static", "SELECT event_id, n_nationkey FROM events JOIN nation ON user_id % 25 < n_nationkey AND n_nationkey < user_id % 25 + 3")
def stream_static(spark, sf):
    s, n = S.file_stream(spark, load(spark, sf, "events").select("event_id", "user_id", "ts"), 4), load(spark, sf, "nation")
    return S.finish(S.join_static(s, n, (F.col("user_id") % 25 < F.col("n_nationkey")) & (F.col("n_nationkey") < F.col("user_id") % 25 + 3))).select("event_id", "n_nationkey")


@query("stream_deltas", C.concurrent_sql("="))
def stream_deltas(spark, sf):
    c = C.relation(spark, sf)
    return S.foreach_batch(C.concurrent(c, "="), "lead", S.file_stream(spark, c, 3, None, "bt"))
