import hashlib

import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def make_docs(spark):
    """Documents from (doc_id, text) pairs, in the schema of the table."""

    def make(pairs, extra=()):
        df = spark.createDataFrame([(i, t, None, "s", None) for i, t in pairs], DOCS)
        for name in extra:  # columns whose names an operator might use itself
            from pyspark.sql import functions as F

            df = df.withColumn(name, F.lit("x"))
        return df

    return make


@pytest.fixture(scope="session")
def sha():
    return lambda b: hashlib.sha256(b).hexdigest()


#: Null, empty, blank, short, repeated rows, equal texts, special strings, letters beyond ASCII, a long text.
EDGE = [
    (1, None), (2, ""), (3, "  \n\t "), (4, "Hello"), (4, "Hello"), (5, "hELLO"), (None, "hello"), (6, "<|endoftext|> a<|endoftext|>"), (7, "naïve café ünïcode 日本語 🙂🙂"),
    (8, "word " * 20_000), (9, "a" * 5_000), (10, "x\r\n\r\ny  z   \n\n"), (-3, "negative id"),
]


@pytest.fixture(scope="session")
def edge():
    return EDGE
