import pytest
from cases import odd_rows
from pyspark.sql import types as T

DOCUMENTS = T.StructType(
    [
        T.StructField("doc_id", T.LongType()),
        T.StructField("text", T.StringType()),
        T.StructField("lang", T.StringType()),
        T.StructField("source", T.StringType()),
        T.StructField("n_chars", T.LongType()),
        # names that operators use inside
        T.StructField("size", T.StringType()),
        T.StructField("h", T.StringType()),
        T.StructField("fp", T.StringType()),
        T.StructField("key", T.StringType()),
        T.StructField("score", T.StringType()),
    ]
)


@pytest.fixture(scope="session")
def documents(spark):
    def make(rows):
        """rows: (doc_id, text[, lang[, source]])"""
        full = [(*r, *([None] * (4 - len(r))), 0, "x", "x", "x", "x", "x") for r in rows]
        return spark.createDataFrame(full, DOCUMENTS)

    return make


@pytest.fixture(scope="session")
def odd(documents):
    return documents(odd_rows())


@pytest.fixture(scope="session")
def empty(documents):
    return documents([])
