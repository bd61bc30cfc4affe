import pytest
from pyspark.sql import SparkSession


@pytest.fixture(scope="session")
def spark():
    session = (
        SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "4g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    return session


#: Awkward rows: null and empty texts, ties, repeated rows, odd white space, control strings, a null key.
ODD_ROWS = [
    (1, "one two three", "a"), (2, None, "a"), (3, "", None), (4, "one two three", "a"), (4, "one two three", "a"), (4, "other", "b"),
    (None, "no id", "b"), (5, " lead  and\ttab\n\n end ", "c"), (6, "<|endoftext|> x y　z", "c"), (7, "é" * 300 + " \U0001f600 don't", "a"), (8, "word " * 5000, "a"),
]


@pytest.fixture(scope="session")
def odd(spark):
    return spark.createDataFrame([(*r, "x", 1) for r in ODD_ROWS], "doc_id long, text string, source string, lang string, n_chars long")
