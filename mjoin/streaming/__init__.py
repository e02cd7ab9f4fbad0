"""Streams of calls and legs: interval joins, station loads, streaks, deltas of any query."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..exec.single_job import answer, co_partitioned
from ..query import MultiJoinQuery
from ..sources import materialise, scratch


def file_stream(spark: SparkSession, df: DataFrame, parts: int = 4, watermark: str | None = None, at: str = "ts") -> DataFrame:
    """df as a stream: written by ranges of time, oldest first, and read some files a batch; rows without a time come first.

    Each range keeps as many files as it has partitions, so that no task holds a range.
    """
    path = scratch(spark, "stream")
    bounds = df.agg(F.percentile_approx(at, [k / parts for k in range(1, parts)] or [0.5], 10_000).alias("q")).first()["q"] or []
    # one write after another: the source takes files by their time of change
    for lo, hi in zip([None, *bounds], [*bounds, None], strict=True):
        above = F.lit(True) if lo is None else F.col(at) > F.lit(lo)
        upto = F.lit(True) if hi is None else F.col(at) <= F.lit(hi)
        inside = F.coalesce(above & upto, F.lit(lo is None))
        df.where(inside).write.mode("append").parquet(path)
    files = max(1, len(spark.read.schema(df.schema).parquet(path).inputFiles()) // parts)
    out = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", files).parquet(path)
    return out.withWatermark(at, watermark) if watermark else out


def late_rows(query) -> int:
    """Rows that a finished streaming query dropped because they came behind its watermark, summed over its batches."""
    return sum(s["numRowsDroppedByWatermark"] for p in query.recentProgress for s in p["stateOperators"])


def finish(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run over all that is there, and the rows that came out (complete mode: of the last batch)."""
    spark = stream.sparkSession
    if mode != "append":
        held: list[DataFrame] = []

        def keep(batch: DataFrame, _: int) -> None:
            held.append(materialise(batch, "stream-batch"))

        q = stream.writeStream.outputMode(mode).option("checkpointLocation", scratch(spark, "stream-state")).trigger(availableNow=True).foreachBatch(keep).start()
        q.awaitTermination()
        return held[-1] if held else spark.createDataFrame([], stream.schema)
    path = scratch(spark, "stream-out")
    q = stream.writeStream.outputMode("append").option("checkpointLocation", scratch(spark, "stream-state")).trigger(availableNow=True).format("parquet").start(path)
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def interval_edge(left: DataFrame, right: DataFrame, arr: str, dep: str, low: int, high: int) -> DataFrame:
    """Stream-stream inner join arr + low < dep < arr + high (seconds, 0 <= low < high); watermarks on both sides bound the state.

    Streams join by equality only: time is cut into buckets of high seconds, and a left row goes to its own and the next.
    """
    seconds = lambda c: F.floor(F.col(c).cast("double") / high).cast("bigint")
    a = left.withColumn("bucket_", F.explode(F.array(seconds(arr), seconds(arr) + 1)))
    b = right.withColumn("bucket_of_", seconds(dep))
    near = f"bucket_ = bucket_of_ AND {dep} > {arr} + INTERVAL {low} SECONDS AND {dep} < {arr} + INTERVAL {high} SECONDS"
    return a.join(b, F.expr(near)).drop("bucket_", "bucket_of_")


def join_static(stream: DataFrame, static: DataFrame, condition: F.Column) -> DataFrame:
    """Every new row against a static relation, which is filtered and projected once and read again by each batch."""
    return stream.join(materialise(static, "static"), condition)


def deltas(q: MultiJoinQuery, alias: str, old: DataFrame, new: DataFrame, k: int = 4) -> DataFrame:
    """What a query gains when new rows join the old ones of a relation that may stand under several aliases.

    Aliases of the grown relation are new or old in all ways but all-old; each way is one job.
    """
    same = [a for a, df in q.relations.items() if df is q.relations[alias]]
    out = None
    for n in range(1, 1 << len(same)):
        rel = dict(q.relations) | {a: (new if n >> i & 1 else old) for i, a in enumerate(same)}
        part = answer(MultiJoinQuery(rel, q.predicates, q.select, q.filters, q.rid), k)
        out = part if out is None else out.unionByName(part)
    return out


def foreach_batch(q: MultiJoinQuery, alias: str, stream: DataFrame, k: int = 4) -> DataFrame:
    """A query over a growing relation: each batch adds its deltas; the sum of them is the query over all rows.

    Rows and deltas of a batch are written under its number, and a batch meets only those of smaller numbers: a batch that
    is run again after a failure overwrites its own and counts nothing twice.
    """
    spark = stream.sparkSession
    seen, out = scratch(spark, "delta-seen"), scratch(spark, "delta-out")
    step = lambda batch, number: delta_step(q, alias, batch, number, seen, out, k)
    stream.writeStream.option("checkpointLocation", scratch(spark, "delta-state")).trigger(availableNow=True).foreachBatch(step).start().awaitTermination()
    return spark.read.parquet(out).drop("batch")


def delta_step(q: MultiJoinQuery, alias: str, batch: DataFrame, number: int, seen: str, out: str, k: int) -> None:
    spark = batch.sparkSession
    batch.write.mode("overwrite").parquet(f"{seen}/batch={number}")
    new = spark.read.schema(batch.schema).parquet(f"{seen}/batch={number}")
    # the folders' numbers come as a column; the batch's own and any later ones are left out
    old = spark.read.schema(batch.schema).option("basePath", seen).parquet(f"{seen}/batch=*").where(F.col("batch") < number).drop("batch")
    with co_partitioned(spark):
        deltas(q, alias, old, new, k).write.mode("overwrite").parquet(f"{out}/batch={number}")


def station_load(stream: DataFrame, window: str, slide: str | None = None) -> DataFrame:
    """Calls and minutes by station and window of time."""
    return stream.groupBy(F.window("ts", window, slide or window), "bsc").agg(F.count("*").alias("calls"), F.sum("l").alias("minutes"))


def sessions(stream: DataFrame, gap: str) -> DataFrame:
    return stream.groupBy(F.session_window("ts", gap), "id").agg(F.count("*").alias("calls"))


def dedup(stream: DataFrame, *keys: str) -> DataFrame:
    """First row of each key within the watermark."""
    return stream.dropDuplicatesWithinWatermark(list(keys))


def streaks(stream: DataFrame, days: int = 3) -> DataFrame:
    """(id, day) on which a subscriber has had calls on so many days in a row; state is the last day and the run of it.

    Days must come in order for an id, as file_stream gives them; a day that comes late ends no run.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        last, run = state.get if state.exists else (-(10**6), 0)
        out = []
        for day in sorted({int(d) for f in frames for d in f["d"]}):
            if day > last:
                run = run + 1 if day == last + 1 else 1
                last = day
                if run >= days:
                    out.append((int(key[0]), day))
        state.update((last, run))
        yield pd.DataFrame(out, columns=["id", "day"])

    return stream.groupBy("id").applyInPandasWithState(step, "id bigint, day int", "last int, run int", "append", "NoTimeout")
