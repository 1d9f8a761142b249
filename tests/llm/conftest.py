import pytest

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, score double, rank int, s string, n_words string"
LONG = " ".join(f"w{i % 700}x{i % 13}" for i in range(30_000))


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls, empty, blank and very long texts, repeated rows, clashing columns."""
    texts = [None, "", " \n\t ", "Hello World again and again " * 12, "hello world again and again " * 12, LONG, LONG + " end", "a\nb\nc\nd", "x\na\nb\nc\ny", "don't  we'll\t'S\n", "é" * 300, "one two three four five"]
    rows = [(i, t, None, None if i % 3 == 0 else f"s{i % 4}", None, 0.5, 1, "q", "z") for i, t in enumerate(texts)]
    rows += [rows[3], rows[5], rows[0]]
    return spark.createDataFrame(rows, DOCS).repartition(3)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOCS)
