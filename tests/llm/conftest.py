import pytest

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, fp bigint, row string, label int, n_words string, digest string"


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls in every column, empty and very long texts, repeated rows, ties, and extra columns whose names operators use inside."""
    long = " ".join(f"word{i % 977} thing{i % 31}" for i in range(60_000))
    same = "the same text of a few words that is long enough to count " * 6
    rows = [
        (1, "", "en", "a", 0), (2, None, "en", "a", None), (3, long, "en", None, len(long)), (4, same, None, "b", len(same)), (4, same, None, "b", len(same)),
        (5, same, "de", "b", len(same)), (6, same + "x", "de", "b", 1), (None, same, "de", "b", 7), (7, "  \n\t ", None, None, 5), (8, "é" * 50_000, "fr", "c", 50_000),
        (9, "Released under the MIT License.\nToken = 'abcdefghijkl' AKIAABCDEFGHIJKLMN 0123456789abcdef0123", "en", "c", 9), (10, "\U0001f600   a\x00b \x85c", "en", "c", 9),
    ]
    return spark.createDataFrame([(*r, 7, "r", 1, "n", "d") for r in rows], SCHEMA)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], SCHEMA)
