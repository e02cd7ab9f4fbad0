"""Tables, views and scratch folders."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_daily(spark: SparkSession, path: str, schema: str, pattern: str = r"(\d{4}-\d{2}-\d{2})", sep: str = ",") -> DataFrame:
    """Delimited files of one day each, with the day of each file's name as a column day; the schema is given, not inferred."""
    df = spark.read.csv(path, schema=schema, sep=sep)
    return df.withColumn("day", F.to_date(F.regexp_extract(F.col("_metadata.file_name"), pattern, 1)))


def json_field(column: str, name: str, kind: str = "int") -> F.Column:
    return F.get_json_object(F.col(column), f"$.{name}").cast(kind)


def shared_dir(spark: SparkSession) -> str:
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    path = os.path.join(tempfile.gettempdir(), "mjoin-jobs")
    os.makedirs(path, exist_ok=True)
    return f"file://{path}"


def scratch(spark: SparkSession, label: str) -> str:
    """A new folder in the shared one; goes when the driver ends."""
    path = f"{shared_dir(spark)}/mjoin-{label}-{uuid.uuid4().hex[:12]}"
    atexit.register(_remove, spark, path)
    return path


def _remove(spark: SparkSession, path: str) -> None:
    try:
        target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # the session may be over
        pass


def materialise(df: DataFrame, label: str = "job") -> DataFrame:
    """Write once and read again: a restart point of later jobs."""
    path = scratch(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def calls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Call records from events: rid, subscriber id, day d, second of the day bt, minutes l, station bsc, kind."""
    e = load(spark, sf_dir, "events")
    day = F.to_date("ts")
    return e.select(
        F.col("event_id").alias("rid"), F.col("user_id").alias("id"), F.datediff(day, F.lit("2024-01-01").cast("date")).alias("d"),
        (F.hour("ts") * 3600 + F.minute("ts") * 60 + F.second("ts")).cast("bigint").alias("bt"), F.col("value").alias("l"), json_field("props", "k").alias("bsc"), F.col("event_type").alias("kind"),
    )


def legs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Legs of journeys from events: rid, leg, dep and arr (dep and whole minutes of value)."""
    e = load(spark, sf_dir, "events")
    minutes = F.floor("value").cast("int")
    return e.select(F.col("event_id").alias("rid"), F.col("event_type").alias("leg"), F.col("ts").alias("dep"), (F.col("ts") + F.make_dt_interval(mins=minutes)).alias("arr"))


def dense_ids(df: DataFrame, name: str, *keys: str) -> DataFrame:
    """df with a dense id in the order of keys (all columns break ties): a sort by ranges, then offsets of the partitions.

    Only the row counts of the partitions come to the driver. Equal rows get any of their ids.
    """
    order = [*keys, *(c for c in df.columns if c not in keys)]
    part = materialise(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("part_", F.spark_partition_id()).withColumn("n_", F.monotonically_increasing_id() - F.shiftleft(F.spark_partition_id().cast("bigint"), 33)), "ids")
    before, rows = 0, []
    for r in sorted(part.groupBy("part_").count().collect(), key=lambda r: r["part_"]):
        rows.append((r["part_"], before))
        before += r["count"]
    offsets = df.sparkSession.createDataFrame(rows, "part_ int, before_ bigint")
    return part.join(F.broadcast(offsets), "part_").withColumn(name, F.col("n_") + F.col("before_")).drop("part_", "n_", "before_")


def lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with a row id: its key pair repeats, so a hash of all columns is not enough where rows are equal."""
    return dense_ids(load(spark, sf_dir, "lineitem"), "rid", "l_orderkey", "l_linenumber")


def scale_calls(base: DataFrame, factor: int, hour_weights: list[float]) -> DataFrame:
    """factor copies of every call with a new rid and a begin drawn (by hash) from hour weights over the day."""
    total, cuts, run = sum(hour_weights), [], 0.0
    for w in hour_weights:
        run += w
        cuts.append(run / total)
    u = F.pmod(F.xxhash64(F.lit("hour"), "rid"), F.lit(1 << 40)) / float(1 << 40)
    hour = sum((F.when(u >= c, 1).otherwise(0) for c in cuts[:-1]), F.lit(0))
    if factor < 1:
        return base.limit(0)
    copies = base.withColumn("copy_", F.explode(F.sequence(F.lit(0), F.lit(factor - 1)))).withColumn("rid", F.col("rid") * factor + F.col("copy_"))
    return copies.withColumn("bt", (hour * 3600 + F.pmod(F.xxhash64(F.lit("second"), "rid"), F.lit(3600))).cast("bigint")).drop("copy_")


def plain_load(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").parquet(path)


def table_load(df: DataFrame, name: str) -> None:
    df.write.mode("overwrite").saveAsTable(name)
