"""SQL text, daily files, loads, event logs, calibration, functions and deltas."""

import datetime as dt
import json

import numpy as np
import pytest
from mjoin import metrics as M
from mjoin.api import MultiJoinEngine
from mjoin.exec.single_job import answer
from mjoin.functions import hilbert_udf, sign_keys
from mjoin.operators import same_bag, top_k_by
from mjoin.partition.curves import cells, hilbert_index
from mjoin.query import band, multi_join
from mjoin.sources import calls, plain_load, read_daily, table_load
from mjoin.sqlfront import parse_sql, split_outside
from mjoin.streaming import deltas
from mjoin.workloads.calls import w1
from mjoin.workloads.synthetic import calibrate, controlled_self_join, measure_grid
from pyspark.sql import functions as F


def test_sql_text(spark, sf):
    c = calls(spark, sf)
    text = "SELECT lead.id AS id, mid.rid FROM calls lead, calls AS mid WHERE lead.bt <= mid.bt AND lead.d BETWEEN 1 AND 2 AND (mid.kind = 'a AND b' OR mid.d < 2) AND mid.d > lead.d + 0"
    q = parse_sql(spark, text, {"calls": c})
    assert [p.sql() for p in q.predicates] == ["lead.bt <= mid.bt", "mid.d > lead.d + 0"]
    assert q.filters == {"lead": "d BETWEEN 1 AND 2", "mid": "(kind = 'a AND b' OR d < 2)"} and [s[0] for s in q.select] == ["id", "mid_rid"]
    c.createOrReplaceTempView("calls")
    assert same_bag(MultiJoinEngine(spark, 4).sql(text), spark.sql(text.replace("mid.rid FROM", "mid.rid AS mid_rid FROM")))
    assert split_outside("a AND (b AND c) AND 'x AND y'", r"\bAND\b") == ["a", "(b AND c)", "'x AND y'"]
    for bad in ("SELECT a.x FROM t a GROUP BY a.x", "SELECT a.x FROM t a JOIN u b ON a.x = b.x", "DELETE FROM t"):
        with pytest.raises(ValueError):
            parse_sql(spark, bad, {"t": c, "u": c})


def test_daily_files_and_loads(spark, sf, tmp_path):
    for day in (1, 2):
        (tmp_path / f"calls-2008-10-0{day}.csv").write_text(f"7,{day}00\n8,{day}50\n")
    rows = read_daily(spark, f"file://{tmp_path}", "id bigint, l int").collect()
    assert sorted((r["id"], r["l"], r["day"]) for r in rows) == [(7, 100, dt.date(2008, 10, 1)), (7, 200, dt.date(2008, 10, 2)), (8, 150, dt.date(2008, 10, 1)), (8, 250, dt.date(2008, 10, 2))]
    c = calls(spark, sf)
    plain_load(c, f"file://{tmp_path}/plain")
    assert same_bag(spark.read.parquet(f"file://{tmp_path}/plain"), c)
    spark.sql("DROP TABLE IF EXISTS mjoin_loaded")
    table_load(c, "mjoin_loaded")
    assert same_bag(spark.table("mjoin_loaded"), c)
    spark.sql("DROP TABLE mjoin_loaded")
    assert M.io_probe(c, f"file://{tmp_path}/io")["bytes"] > 0


def test_band_conditions():
    assert band(1, "a.arr", "b.dep", "5", "60") == ["a.arr + 5 < b.dep", "b.dep < a.arr + 60"]
    assert band(1, "a.x", "b.y", "1", "2", closed=True)[0] == "a.x + 1 <= b.y"


def test_event_log_history(spark, tmp_path):
    task = {"Event": "SparkListenerTaskEnd", "Stage ID": 3, "Task Metrics": {"Executor Run Time": 1500, "Disk Bytes Spilled": 7, "Shuffle Write Metrics": {"Shuffle Bytes Written": 100}}}
    (tmp_path / "log").write_text("\n".join(json.dumps(e) for e in (task, task, {"Event": "Other"})))
    r = M.read_event_log(spark, f"file://{tmp_path}/log").first()
    assert (r["stage"], r["tasks"], r["seconds"], r["written"], r["spilled"]) == (3, 2, 3.0, 200, 14)


def test_measures():
    assert M.speedup(3.0, 2.0) == 1.5 and M.saving(3.0, 1.5) == 0.5 and M.cost_error(3.0, 2.0) == 0.5
    assert len(M.timed(lambda: None, repeat=2)) == 2 and json.loads(M.dumps([{"a": 1}])) == {"a": 1}


def test_calibration_and_probes(spark, sf):
    params, rows = calibrate(spark, sf, [20, 100], [1, 4])
    n = calls(spark, sf).count()
    assert params.c1 > 0 and len(rows) == 4 and {r[2] for r in rows} == {n * n // g for g in (20, 100)}
    assert controlled_self_join(spark, sf, 10).count() == n * n // 10
    assert len(measure_grid(spark, sf, [1, 2], [2])) == 2


def test_hilbert_in_arrow_batches(spark):
    grid = cells((3, 3, 3))
    df = spark.createDataFrame([(g.tolist(),) for g in grid], "c array<int>")
    got = df.select("c", hilbert_udf(3)(F.col("c")).alias("h")).collect()
    assert [r["h"] for r in got] == hilbert_index(np.array([r["c"] for r in got]), 3).tolist()


def test_sign_keys_and_top_k(spark):
    df = spark.createDataFrame([(1, [1.0, -1.0]), (2, [-1.0, 1.0])], "k int, v array<double>")
    keys = {r["k"]: r["s"] for r in df.select("k", sign_keys(F.col("v"), [[1.0, 0.0], [0.0, 1.0]], 2).alias("s")).collect()}
    assert keys == {1: [1, 2], 2: [0, 3]}
    assert top_k_by(spark.range(10).withColumn("g", F.col("id") % 2), "g", [F.col("id").desc()], 2).count() == 4


def test_deltas_add_up(spark, sf):
    c = calls(spark, sf).where("d < 3")
    q = w1(c)
    old, new = c.where("rid % 3 <> 0"), c.where("rid % 3 = 0")
    first = answer(type(q)({a: old for a in q.relations}, q.predicates, q.select), 3)
    assert same_bag(first.unionByName(deltas(q, "lead", old, new, 3)), answer(q, 3))
    assert multi_join(a=c, b=c).on("a.bt < b.bt").build().rid_of("a") == "rid"
