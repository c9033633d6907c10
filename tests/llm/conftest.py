import sys
from pathlib import Path

import pytest
from pyspark.sql import SparkSession

sys.path.insert(0, str(Path(__file__).resolve().parents[2]))
DATA = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    conf = {"spark.sql.shuffle.partitions": "4", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.session.timeZone": "UTC", "spark.driver.memory": "4g"}
    s = SparkSession.builder.master("local[4]").config(map=conf).getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    return s


#: Nulls, empty and very long texts, ties and repeated rows, with columns of clashing names.
ODD_SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, size int, kept string, label string"


def odd_rows():
    long = " ".join(f"word{i % 997} tail{i % 1013}" for i in range(30_000))
    rows = [(1, None), (2, ""), (3, " \n\t "), (4, "one"), (5, long), (5, long), (6, "Same text here, again."), (6, "Same text here, again."), (None, "no id at all but some words"), (7, "A.\x00bé\U0001f600 z")]
    return [(i, t, "en" if n % 2 else None, None if n % 3 else "s", 1, "k", 1, "x", "y") for n, (i, t) in enumerate(rows)]


@pytest.fixture(scope="session")
def odd(spark):
    return spark.createDataFrame(odd_rows(), ODD_SCHEMA)


@pytest.fixture(scope="session")
def docs(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet")
