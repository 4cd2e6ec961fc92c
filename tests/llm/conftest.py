import pytest

LONG = "lorem ipsum dolor " * 4000
TEXTS = [
    (1, "The quick brown fox jumps over the lazy dog and runs away from it all today"), (2, "The quick brown fox jumps over the lazy dog and runs away from it all today"),
    (3, None), (4, ""), (5, "   "), (6, "one"), (7, "Ünïcödé wörds 日本語 <|endoftext|> x<|startoftext|>y"), (8, LONG), (8, LONG), (None, "no id at all"),
    (9, "alpha beta\nalpha beta\n" * 30), (10, "!!! ... ???"),
]


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls, empty and very long texts, repeated rows, and extra columns with names that operators use inside."""
    rows = [(i, t, "junk", 7, None) for i, t in TEXTS]
    return spark.createDataFrame(rows, "doc_id bigint, text string, key string, class int, component string").repartition(3)


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], "doc_id bigint, text string")
