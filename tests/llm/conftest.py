import pytest

LONG = " ".join(f"word{i % 997}x{i}" for i in range(30_000))
DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, kept boolean, score double, component_id string"


@pytest.fixture(scope="session")
def odd_rows():
    """Nulls in every column, empty, blank and very long texts, ties, repeated rows, marks and many scripts."""
    base = "the quick brown fox jumps over the lazy dog and runs far away from here " * 6
    texts = [None, "", "  \n\t ", "one", "one two three", base, base, base + "now", base.replace(" ", "\n\n"), LONG, LONG + " tail", "Ünïcödé ß 日本語 テスト Ω", "12 34 !! ##", "Licensed under the Apache License, Version 2.0.", "a\x1cb\x85c d", "x" * 5000]
    rows = [(i, t, ["en", None, "de"][i % 3], ["s0", "s1", None][i % 3], None if i % 4 else 1, True, 0.5, "c") for i, t in enumerate(texts)]
    return [*rows, rows[5], rows[5], (None, base, None, None, None, None, None, None)]


@pytest.fixture(scope="session")
def odd(spark, odd_rows):
    return spark.createDataFrame(odd_rows, DOCS).repartition(3).cache()


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="session")
def labels(spark):
    return spark.createDataFrame([(5, 1, 0), (6, 1, 0), (9, 1, None), (12, 0, 0), (12, 0, 0), (13, None, None), (None, 1, 0)], "doc_id bigint, quality int, toxic int")
