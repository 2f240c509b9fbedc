import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, shard int, tokens string"


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls, empty and long texts, ties, repeated rows, and columns with clashing names."""
    long = " ".join(f"word{i % 977} other{i}" for i in range(30_000))
    rows = [
        (1, "The quick brown fox jumps over the lazy dog and runs far away from here today", "en", "a", 10, 5, 1, "x"),
        (2, "The quick brown fox jumps over the lazy dog and runs far away from here today", "en", "a", 10, 5, 1, "x"),
        (2, "The quick brown fox jumps over the lazy dog and runs far away from here today", "en", "a", 10, 5, 1, "x"),
        (3, None, None, None, None, None, None, None),
        (4, "", "en", None, 0, 0, 0, ""),
        (5, " \n\t\r\n ", "en", "a", 0, 0, 0, ""),
        (6, long, "de", "b", 1, 1, 1, "y"),
        (7, long + " end", "de", "b", 1, 1, 1, "y"),
        (None, "no id here but some words that stand in a line of text", "en", "a", 1, 1, 1, "z"),
        (9, "one word é日本😀 'tis it's we'll\n\n  two   three", "en", "c", 1, 1, 1, "z"),
        (10, "a b c", "en", "c", 1, 1, 1, "z"),
        (11, "A B C", "en", "c", 1, 1, 1, "z"),
        (None, "a b c", "en", "c", 1, 1, 1, "z"),
    ]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], SCHEMA)
