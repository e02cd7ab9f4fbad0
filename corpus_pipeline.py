"""A corpus pipeline of five stages, each an operator of mjoin.llm; every stage gets what its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from mjoin.llm import decontaminate, mixing, ngram_join, token_files, toxicity
from mjoin.llm.common import load, settle_alone
from mjoin.llm.queries import vocabulary


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows predicted toxic go; the classifier learns from the labelled rows of docs that aren't held out."""
    return toxicity.without_toxic(docs, toxicity.fit(docs, load(spark, sf_dir, "labels")))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each class of near copies stays, that of the least doc_id."""
    return ngram_join.one_of_each(docs)


def cut_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of the benchmark are cut out of the texts; rows with no other word go."""
    return decontaminate.decontaminated(docs, load(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows stand as often as the mix takes them."""
    return mixing.mixed_documents(docs)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files of the mix, and the digest of what they hold."""
    return token_files.token_table(docs, vocabulary())


STAGES = [
    ("toxicity", drop_toxic),
    ("ngram_join", drop_near_copies),
    ("decontamination", cut_benchmark),
    ("mixing", mix_sources),
    ("token_files", write_tokens),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result but the last is written and read again by the next stage.

    Null and empty texts pass the first three stages (they are not toxic, no copies, and hold no passage), have size 0
    in the mix and one end id in the token files; an empty table gives no rows.
    """
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = settle_alone(spark, lambda stage=stage, docs=docs: stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)


#: A fitted classifier and a vocabulary are beyond SQL: tests hold every stage against brute force.
ORACLE_SQL = None
QUERIES = {"pipeline": run}
ORACLE: dict[str, str] = {}
