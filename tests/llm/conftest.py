import pytest
from pyspark.sql import functions as F


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty and wordless texts, a long text, repeated rows, ties, columns of other meaning."""
    long = "alpha beta gamma delta epsilon zeta eta theta " * 3000
    rows = [
        (1, "The quick brown fox jumps over the lazy dog near the river bank today"), (2, None), (3, ""), (4, "   \n\t "), (5, "!!! ??? ..."), (6, long), (7, long), (7, long),
        (None, "The quick brown fox jumps over the lazy dog near the river bank today"), (8, "Ünïcödé 日本語 emoji 🎉 \u0000 end"), (9, "one two three"), (10, "one two three"), (11, "x▁y z"),
    ]
    return spark.createDataFrame(rows, "doc_id long, text string").select("*", F.lit("z").alias("id"), F.lit(3).alias("hash"), F.lit(1).alias("n_tokens"), F.lit("k").alias("key"), F.lit(1).alias("node"))


@pytest.fixture(scope="session")
def no_docs(odd):
    return odd.filter("false")


@pytest.fixture(scope="session")
def docs(spark):
    return spark.read.parquet("/root/testdata/sf0.01/documents.parquet")


@pytest.fixture(scope="session")
def texts(docs):
    return {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}
