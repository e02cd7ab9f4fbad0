"""Mixing sources to target weights by capped water-filling and seeded repetitions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import settle

#: Weights of the sources in code point order, repeating; the most epochs; the seed of the sampling.
WEIGHTS = (5, 2, 1)
MAX_EPOCHS = 3
SEED = "mix-1"
_BUCKET_HEX = 3
_SMALL = 10_000


def word_count(text) -> F.Column:
    """Number of runs of anything but tab to carriage return and space; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights=WEIGHTS, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """source, source_size, weight, target of a table (source, size): shares of all words by weight under caps.

    Clamping each source above max_epochs times its size and sharing the excess by weight until none is above ends
    at one water level: sources in order of cap over weight are full as long as the level that the others would
    get exceeds theirs. That order is one window over the sources (not the rows). The null source comes last in
    code point order and is a source of its own. An empty table gives no rows; sources without words get target 0.
    """
    by = sizes.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"))
    rank = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    w = F.element_at(F.array(*map(F.lit, weights)), (rank % len(weights) + 1).cast("int")).cast("long")
    by = by.withColumn("weight", w).withColumn("cap", max_epochs * F.col("source_size"))
    order = Window.orderBy((F.col("cap").cast("double") / F.col("weight")), F.col("source").asc_nulls_last())
    every = Window.partitionBy()
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    left = F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0))
    open_weight = F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0))
    by = by.withColumn("left", left).withColumn("open_weight", open_weight)
    full = F.col("cap") * F.col("open_weight") <= F.col("left") * F.col("weight")
    # The first source that is not full sets the level for itself and all after it.
    first = F.min(F.when(~full, F.struct((F.col("cap").cast("double") / F.col("weight")).alias("o"), F.col("source").isNull().alias("z"), F.col("source").alias("s"), F.col("left").alias("l"), F.col("open_weight").alias("w")))).over(every)
    by = by.withColumn("full", full).withColumn("level", first)
    target = F.when(F.col("full"), F.col("cap").cast("double")).otherwise((F.col("level.l") * F.col("weight")).cast("double") / F.col("level.w").cast("double"))
    return by.select("source", "source_size", "weight", target.alias("target"))


def _with_source_key(df: DataFrame) -> DataFrame:
    """A join key for sources that is never null."""
    return df.withColumn("source_key", F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("-")))


def _hash_key(seed: str) -> F.Column:
    return F.md5(F.concat(F.lit(seed + ":"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary"))


class MixPlan:
    """Sizes of the rows, the targets of the sources, and the hash bucket in which each target runs out."""

    def __init__(self, docs: DataFrame, weights=WEIGHTS, max_epochs: int = MAX_EPOCHS, seed: str = SEED):
        self.max_epochs, self.seed = max_epochs, seed
        rows = settle(docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), _hash_key(seed).alias("key")), "mix")
        self.rows = _with_source_key(rows.withColumn("bucket", F.substring("key", 1, _BUCKET_HEX)))
        targets = _with_source_key(source_targets(rows, weights, max_epochs))
        whole = F.when(F.col("source_size") > 0, F.least(F.lit(max_epochs), F.floor(F.col("target") / F.col("source_size")))).otherwise(0).cast("long")
        targets = targets.withColumn("whole", whole).withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size")).drop("source")
        sums = self.rows.groupBy("source_key", "bucket").agg(F.sum("size").cast("long").alias("in_bucket"))
        before = Window.partitionBy("source_key").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
        sums = sums.withColumn("edge_before", F.coalesce(F.sum("in_bucket").over(before), F.lit(0)))
        edge = sums.join(targets, "source_key").where((F.col("edge_before") <= F.col("rest")) & (F.col("rest") < F.col("edge_before") + F.col("in_bucket")))
        self.plan = settle(targets.join(edge.select("source_key", F.col("bucket").alias("edge"), "edge_before"), "source_key", "left"), "mix-plan")
        # Beyond so many sources a shuffled join, whose hot sources AQE splits.
        self.few = self.plan.count() <= _SMALL

    def joined(self, df: DataFrame) -> DataFrame:
        return df.join(F.broadcast(self.plan) if self.few else self.plan, "source_key")

    def split(self, df: DataFrame) -> tuple[DataFrame, DataFrame]:
        """Rows of the buckets in which targets run out, and the others with their decision extra."""
        both = self.joined(df)
        at_edge = F.coalesce(F.col("bucket") == F.col("edge"), F.lit(False))
        extra = (F.col("rest") > 0) & (F.col("whole") < self.max_epochs) & (F.col("edge").isNull() | (F.col("bucket") < F.col("edge")))
        return both.where(at_edge), both.where(~at_edge).withColumn("extra", extra.cast("long"))

    def decided(self) -> tuple[DataFrame, DataFrame]:
        cut, others = self.split(self.rows)
        before = Window.partitionBy("source_key").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
        run = F.coalesce(F.sum("size").over(before), F.lit(0))
        fits = (F.col("rest") > 0) & (F.col("whole") < self.max_epochs) & (2 * (F.col("edge_before") + run) + F.col("size") <= 2 * F.col("rest"))
        return cut.withColumn("extra", fits.cast("long")), others


def mix(docs: DataFrame, **options) -> DataFrame:
    """doc_id, source, size, source_size, target, repeats, taken of every row of docs.

    A document is taken whole floor(target / source_size) times; the rest of the target is filled with documents
    once more, in the order of a seeded hash of doc_id, while at least half of the document fits. Only the documents
    of the hash bucket in which the rest runs out are sorted: buckets are summed first, so no source, however hot,
    meets in one task. Reruns agree. Null text has size 0, null doc_id hashes as the empty text, null source is a
    source; repeated rows count each and are ordered by size; an empty table gives an empty result.
    """
    cut, others = MixPlan(docs, **options).decided()
    out = cut.unionByName(others).withColumn("repeats", F.col("whole") + F.col("extra"))
    return out.select("doc_id", "source", "size", "source_size", "target", "repeats", (F.col("repeats") * F.col("size")).cast("long").alias("taken"))


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs, each as often as the mix takes it; rows not taken go, all columns stay.

    Whole texts are read once more and not shuffled, but for those of the buckets in which targets run out. There
    rows of equal doc_id all follow the least taken of them.
    """
    made = MixPlan(docs, **options)
    names = docs.columns
    renamed = docs.select(F.struct(*[docs[c] for c in names]).alias("row_"), "doc_id", "source")
    keyed = _with_source_key(renamed.withColumn("bucket", F.substring(_hash_key(made.seed), 1, _BUCKET_HEX)))
    cut_texts, others = made.split(keyed)
    cut = made.decided()[0].groupBy(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("id_")).agg(F.min("extra").alias("extra"))
    cut_texts = cut_texts.withColumn("id_", F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).join(cut, "id_")
    cols = ["row_", (F.col("whole") + F.col("extra")).cast("int").alias("repeats_")]
    out = others.select(*cols).unionByName(cut_texts.select(*cols)).where("repeats_ > 0")
    return out.withColumn("n_", F.explode(F.sequence(F.lit(1), F.col("repeats_")))).select("row_.*")


#: The same in DuckDB, over the view documents.
MIX_SQL = r"""
WITH d AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
                  md5('mix-1:' || coalesce(doc_id::VARCHAR, '')) AS key FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
w AS (SELECT *, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS weight FROM s),
p AS (SELECT *, 3 * source_size AS cap,
        sum(source_size) OVER () - coalesce(sum(3 * source_size) OVER (ORDER BY (3 * source_size)::DOUBLE / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS left_over,
        sum(weight) OVER () - coalesce(sum(weight) OVER (ORDER BY (3 * source_size)::DOUBLE / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS open_weight FROM w),
f AS (SELECT *, cap * open_weight <= left_over * weight AS is_full FROM p),
l AS (SELECT left_over, open_weight FROM f WHERE NOT is_full ORDER BY cap::DOUBLE / weight, source NULLS LAST LIMIT 1),
t AS (SELECT f.source, f.source_size, CASE WHEN is_full THEN cap::DOUBLE ELSE (l.left_over * weight)::DOUBLE / l.open_weight::DOUBLE END AS target FROM f LEFT JOIN l ON true),
e AS (SELECT *, CASE WHEN source_size > 0 THEN least(3, floor(target / source_size)) ELSE 0 END::BIGINT AS whole FROM t),
r AS (SELECT d.*, e.source_size, e.target, e.whole, e.target - e.whole * e.source_size AS rest,
        coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS run
      FROM d JOIN e ON d.source IS NOT DISTINCT FROM e.source)
SELECT doc_id, source, size, source_size, target,
       (whole + CASE WHEN whole < 3 AND rest > 0 AND 2 * run + size <= 2 * rest THEN 1 ELSE 0 END)::BIGINT AS repeats,
       (size * (whole + CASE WHEN whole < 3 AND rest > 0 AND 2 * run + size <= 2 * rest THEN 1 ELSE 0 END))::BIGINT AS taken FROM r
"""
