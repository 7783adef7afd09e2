import pytest

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, size string, _hash int"

#: Null columns, empty and long texts, copies that differ in case, ties, repeated rows, markup, special strings.
ROWS = [
    (1, "The quick brown fox jumps over the lazy dog", "en", "a", 1, "x", 1),
    (2, "the QUICK brown fox jumps over the lazy dog", "en", "b", 1, None, 2),
    (2, "the QUICK brown fox jumps over the lazy dog", "en", "b", 1, None, 2),
    (3, None, None, None, None, None, None),
    (4, "", "de", "a", 0, "y", 4),
    (5, " \t\n ", "de", None, 3, "y", 4),
    (None, "Ein kurzer Satz ohne Nummer", "de", "b", 1, "z", 5),
    (7, "word " * 3000, "en", "a", 1, "z", 6),
    (8, "ÀÉÎ ünï 中文 🎉 don't <|endoftext|>  two  spaces\x85\xa0x", "fr", "c", 1, "z", 7),
    (9, "one two three", None, "c", 1, "z", 8),
    (10, "one two three", "en", "c", 1, "z", 8),
    (11, "12345 67890 !!", "en", "c", 1, "z", 8),
]


@pytest.fixture(scope="session")
def odd(spark):
    """Documents of every awkward kind, with extra columns whose names clash with results and internals."""
    return spark.createDataFrame(ROWS, SCHEMA)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def documents(spark, small):
    return spark.read.parquet(f"{small}/documents.parquet")
