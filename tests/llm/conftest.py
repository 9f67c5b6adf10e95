import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double"


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty and long texts, ties, repeated rows, a clashing extra column."""
    long = " ".join(f"w{i % 97}x{i % 31}" for i in range(9000))
    rows = [
        (1, "One two three four five six seven eight nine ten. Mail a.b@c.org now", "en", "s1", 10, 0.5),
        (2, "one two THREE four five six seven eight nine ten. mail A.B@c.org now", "en", "s1", 10, None),
        (3, None, None, None, None, None),
        (4, "", "en", "s2", 0, 1.0),
        (5, long, "de", "s2", len(long), 1.0),
        (5, long, "de", "s2", len(long), 1.0),
        (None, "token = abcdef12 and 10.0.0.1", "en", "s3", 1, 1.0),
        (7, "a b", "fr", "s3", 3, 1.0),
        (8, "A  B", "fr", "s3", 4, 1.0),
        (9, "😀 12 34 <|endoftext|> été\x1cx  \n\n  y", "fr", "s3", 4, 1.0),
    ]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], DOCS)
