"""Measures of plans and runs."""

from __future__ import annotations

import json
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..exec.single_job import draw_coord, prepare, region_names, relations_of, route, side_names
from ..operators import same_bag
from ..partition.assign import RegionAssignment, assign_regions, copies_by_relation, duplication_factor, is_balanced, partition_score
from ..partition.reducers import delta
from ..plan.cover import greedy_ratio
from ..plan.graph import JoinGraph
from ..query import MultiJoinQuery

__all__ = ["check_work", "copies", "copies_by_relation", "cost_error", "delta", "duplication_factor", "greedy_ratio", "io_probe", "is_balanced", "partition_score", "plan_stats", "query_features", "region_skew", "routed", "same_bag", "saving", "selectivity", "speedup", "timed"]


def routed(q: MultiJoinQuery, k: int, curve: str = "hilbert", bits=None, seed: int = 0) -> DataFrame:
    """alias, rid and region of every copy that a single job would send."""
    labels = frozenset(p.label for p in q.predicates)
    order, names = relations_of(q, labels), side_names(q, labels)
    a, regions, out = assign_regions(len(order), k, curve, bits), region_names(k), None
    for i, alias in enumerate(order):
        df = prepare(q, alias, names).withColumn(f"{alias}__c", draw_coord(alias, a.bits[i], seed))
        df = route(df, alias, a.routes[i], regions, k)
        table = F.create_map(*[x for r, n in enumerate(regions) for x in (F.lit(n), F.lit(r))])
        df = df.select(F.lit(alias).alias("alias"), F.col(f"{alias}__rid").alias("rid"), table[F.col(f"{alias}__region")].alias("region"))
        out = df if out is None else out.unionByName(df)
    return out


def copies(sent: DataFrame) -> DataFrame:
    """Copies of each relation, measured."""
    return sent.groupBy("alias").agg(F.count("*").alias("copies"), F.countDistinct("rid").alias("rows"))


def region_skew(sent: DataFrame) -> DataFrame:
    """Rows of the largest region, their mean and standard deviation."""
    return sent.groupBy("region").agg(F.count("*").alias("n")).agg(F.count("*").alias("regions"), F.max("n").alias("most"), F.avg("n").alias("mean"), F.stddev_pop("n").alias("sigma"))


def check_work(a: RegionAssignment) -> tuple[int, float]:
    """Cells of the largest region, and largest over mean."""
    n = a.shares()
    return int(n.max()), float(n.max() / n.mean())


def cost_error(estimated: float, measured: float) -> float:
    return abs(estimated - measured) / measured


def speedup(base: float, ours: float) -> float:
    return base / ours


def saving(base: float, ours: float) -> float:
    return 1 - ours / base


def selectivity(result_rows: int, q: MultiJoinQuery) -> tuple[float, float]:
    """Result rows over the product of all inputs, and over the largest input."""
    counts = [q.filtered(a).count() for a in q.relations]
    product = 1
    for n in counts:
        product *= n
    return result_rows / product if product else 0.0, result_rows / max(counts) if max(counts) else 0.0


def query_features(q: MultiJoinQuery) -> tuple[int, int, str]:
    """Relations, joined pairs, and the operators other than equality."""
    return len(q.relations), len(JoinGraph.bundled(q)[0].edges), " ".join(sorted({p.op.value for p in q.predicates if p.op.value != "="}))


def plan_stats(build) -> dict:
    """Seconds to build a pruned trail graph, and trails kept and dropped."""
    t = time.perf_counter()
    g = build()
    return {"seconds": time.perf_counter() - t, "kept": len(g.kept), "dropped": len(g.dropped)}


def timed(action, repeat: int = 3, warm: int = 1) -> list[float]:
    for _ in range(warm):
        action()
    out = []
    for _ in range(repeat):
        t = time.perf_counter()
        action()
        out.append(time.perf_counter() - t)
    return out


def io_probe(df: DataFrame, path: str) -> dict:
    """MB/s of writing df and reading it again."""
    t = time.perf_counter()
    df.write.mode("overwrite").parquet(path)
    wrote = time.perf_counter() - t
    back = df.sparkSession.read.parquet(path)
    jvm = df.sparkSession.sparkContext._jvm
    fs_path = jvm.org.apache.hadoop.fs.Path(path)
    size = fs_path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).getContentSummary(fs_path).getLength()
    t = time.perf_counter()
    back.write.format("noop").mode("overwrite").save()
    return {"bytes": size, "write_mb_s": size / 1e6 / wrote, "read_mb_s": size / 1e6 / (time.perf_counter() - t)}


def read_event_log(spark: SparkSession, path: str) -> DataFrame:
    """stage, seconds, shuffle bytes written and read, spilled bytes of a Spark event log: the history that calibration reads."""
    log = spark.read.text(path)
    kind = F.get_json_object("value", "$.Event")
    rows = log.where(kind == "SparkListenerTaskEnd")
    number = lambda p: F.coalesce(F.get_json_object("value", p).cast("long"), F.lit(0))
    return rows.groupBy(F.get_json_object("value", "$['Stage ID']").cast("int").alias("stage")).agg(
        F.count("*").alias("tasks"), F.sum(number("$['Task Metrics']['Executor Run Time']") / 1000).alias("seconds"),
        F.sum(number("$['Task Metrics']['Shuffle Write Metrics']['Shuffle Bytes Written']")).alias("written"),
        F.sum(number("$['Task Metrics']['Disk Bytes Spilled']")).alias("spilled"),
    )


def dumps(history: list[dict]) -> str:
    return "\n".join(json.dumps(h) for h in history)
