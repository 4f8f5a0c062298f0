import pytest

DATA = "/root/testdata"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, place int, slot string"


@pytest.fixture(scope="session")
def small(spark):
    return spark.read.parquet(f"{DATA}/sf0.001/documents.parquet")


@pytest.fixture(scope="session")
def labels(spark):
    return spark.read.parquet(f"{DATA}/sf0.001/labels.parquet")


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls in every column, empty, blank and long texts, ties, repeated rows, columns with clashing names."""
    rows = [
        (1, "The quick brown fox jumps over the lazy dog", "en", "a", 43, 1, "x"),
        (1, "The quick brown fox jumps over the lazy dog", "en", "a", 43, 1, "x"),
        (2, "the  QUICK brown fox\njumps over the lazy dog ", "en", "b", 46, 1, "x"),
        (3, None, None, None, None, None, None),
        (None, "lost words without an id", "en", "b", 24, 2, "y"),
        (None, None, None, None, None, None, None),
        (4, "", "de", "c", 0, 3, "z"),
        (5, " \t\n", "de", "c", 3, 3, "z"),
        (6, "one two three", "fr", None, 13, 3, "z"),
        (7, "one two three", "fr", "d", 13, 3, "z"),
        (8, " ".join(f"w{i % 977}" for i in range(30_000)), "en", "a", 0, 4, "q"),
        (9, "x" * 200_000, "en", "a", 200_000, 4, "q"),
        (-5, "café café ß İ \U0001f600  end", "en", "e", 20, 5, "r"),
    ]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="session")
def empty(odd):
    return odd.limit(0)


@pytest.fixture(scope="session")
def odd_labels(spark):
    return spark.createDataFrame([(1, 1, 0), (1, 1, 0), (6, 0, 1), (None, 1, None), (99, None, 0)], "doc_id long, quality int, toxic int")
