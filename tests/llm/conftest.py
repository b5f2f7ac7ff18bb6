import pytest

#: Rows that every operator on documents has to take: nulls, blanks, ties, repeats, a long one.
ROWS = [
    (1, "The quick brown fox jumps over the lazy dog near the river bank today", "en", "a", 3),
    (2, "the QUICK brown fox jumps over the lazy dog near the river bank today", "en", "a", 3),
    (3, None, "en", "b", None),
    (4, "", None, None, 0),
    (5, " \n\t ", "de", "b", 3),
    (None, "ein kleiner Text über Straßen und Äpfel", "de", "b", 9),
    (None, None, None, None, None),
    (7, "kurz", "de", "b", 4),
    (7, "kurz", "de", "b", 4),
    (8, "12 34 ... !!", "en", "b", 4),
    (9, "word " * 30000, "en", "c", 9),
    (10, "é à ü ß  x", "fr", "c", 9),
    (11, "one two\x0bthreé <|endoftext|> it's 'S", "fr", "c", 9),
]


@pytest.fixture(scope="session")
def rows():
    return ROWS


@pytest.fixture(scope="session")
def docs(spark):
    # further columns whose names the operators use themselves
    frame = spark.createDataFrame(ROWS, "doc_id long, text string, lang string, source string, n_chars long")
    return frame.selectExpr("*", "1 AS row", "'x' AS k", "2 AS c", "3 AS n", "'y' AS score", "0 AS kept", "1 AS w", "2 AS pos", "'z' AS h", "'g' AS _gone", "4 AS _k", "5 AS _d", "6 AS k1", "7 AS m", "'q' AS name", "8 AS item_id")


@pytest.fixture(scope="session")
def empty(docs):
    return docs.where("false")
