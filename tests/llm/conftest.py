import os
import sys

import pytest
from pyspark.sql import SparkSession

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__)))))
DATA = os.environ.get("CHARTREL_TESTDATA", "/root/testdata")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, key string, kept boolean, score double, lines string, twin int, rep int, __x int"


@pytest.fixture(scope="session")
def spark():
    s = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s


def frame(spark, rows):
    """Documents of (doc_id, text[, lang, source]) with further columns whose names operators use inside."""
    full = [(*r, *[None] * (4 - len(r)))[:4] for r in rows]
    return spark.createDataFrame([(*r, None if r[1] is None else len(r[1]), 7, "k", True, 0.5, "l", 1, 2, 3) for r in full], SCHEMA)


LONG = " ".join(f"word{i % 977} of line {i % 13}" + ("\n" if i % 40 == 0 else "") for i in range(40_000))
EDGE = [
    (1, "One plain text with a few more words than ten in it, mail a.b@c.example.org now.", "en", "s1"), (2, None, "en", "s1"), (3, "", "de", None), (4, " \n\t ", None, "s2"),
    (5, LONG, "en", "s2"), (6, "same text here for the tie of two rows at least today", "en", "s3"), (7, "same text here for the tie of two rows at least today", "en", "s3"),
    (7, "same text here for the tie of two rows at least today", "en", "s3"), (None, "no id but a text with words", "en", "s3"), (8, "日本語テキスト。" * 50, "ja", "s3"), (9, "!!! ??? ***", "en", "s1"), (10, "x" * 50_000, None, None),
]


@pytest.fixture(scope="session")
def edge(spark):
    return frame(spark, EDGE).cache()


@pytest.fixture(scope="session")
def none(spark):
    return frame(spark, [])


@pytest.fixture(scope="session")
def small():
    return f"{DATA}/sf0.001"


@pytest.fixture(scope="session")
def mid():
    return f"{DATA}/sf0.01"
