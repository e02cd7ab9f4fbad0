import os

import pytest
from pyspark.sql import SparkSession

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


@pytest.fixture(scope="session")
def spark():
    session = (
        SparkSession.builder.master("local[8]")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.driver.memory", "4g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    session.sparkContext.environment.setdefault("PYTHONPATH", ROOT)
    return session


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"


DOC_SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls in every column, empty and very long texts, ties, repeated rows, and columns with clashing names."""
    rows = [
        (1, "alpha beta gamma delta epsilon zeta", "en", "a", 35),
        (1, "alpha beta gamma delta epsilon zeta", "en", "a", 35),
        (2, "", "en", "a", 0),
        (3, None, None, None, None),
        (None, "a row without an id", "en", "b", 19),
        (4, "   \n\t ", "en", "b", 6),
        (5, "wort " * 60_000, "de", "c", 300_000),
        (6, "x", None, None, 1),
        (7, "alpha beta gamma delta epsilon zeta", "fr", "c", 35),
    ]
    extra = "size int, key string, toxic_ int, row_ string, part int, hit int"
    return spark.createDataFrame([r + (1, "k", 1, "r", 2, 3) for r in rows], f"{DOC_SCHEMA}, {extra}")


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOC_SCHEMA)
