import pytest

#: Null ids and texts, empty, white-space-only, very long, repeated rows, ties, and names that clash with working columns.
ROWS = [
    (1, None, None, "a", 0, "x"),
    (2, "", "en", None, 0, "x"),
    (3, " \t\n ", "en", "a", 3, "x"),
    (4, "the same text of a few words", "en", "a", 28, None),
    (5, "the same text of a few words", "en", "a", 28, "x"),
    (5, "the same text of a few words", "en", "a", 28, "x"),
    (None, "a text without an id, é 日本 😀", "fr", "b", None, "x"),
    (7, "word " * 20_000, "en", "b", 100_000, "x"),
    (8, "x" * 30_000, None, "b", 30_000, "x"),
    (9, "!!! ??? 123 <|endoftext|>", "de", "b", 1, "x"),
    (10, "don't I'll 're\r\nnew  line\x1cend\x85", "en", "b", 1, "x"),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, bucket string"


@pytest.fixture(scope="session")
def odd(spark):
    """Documents with every nuisance, and clashing extra columns."""
    df = spark.createDataFrame(ROWS, SCHEMA)
    for name in ("fp", "block", "origin", "score", "held_out", "anchor", "key", "words", "body", "part"):
        df = df.withColumn(name, df["bucket"])
    return df


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def texts():
    return ROWS
