import pytest

#: Nulls in every column, empty and blank texts, ties, repeated rows, a long text, and columns whose names clash with the operators' own.
LONG = " ".join(f"word{i % 997} und{i % 89}" for i in range(6_000))
ROWS = [
    (1, "The cat sat on the mat. It was a fine day for all of us here today.\nThe cat sat on the mat.", "en", "a", 3),
    (2, "The cat sat on the mat. It was a fine day for all of us here today.\nThe cat sat on the mat.", "en", "a", 3),
    (2, "The cat sat on the mat. It was a fine day for all of us here today.\nThe cat sat on the mat.", "en", "a", 3),
    (3, "", "en", None, 0),
    (4, None, None, "b", None),
    (5, "   \n\t ", "de", "b", 5),
    (6, "einzeln", None, None, 7),
    (7, LONG, "de", "a", len(LONG)),
    (None, "ein Text ohne Nummer, aber mit vielen Wörtern darin", "de", "c", 9),
    (8, "naïve ▁ 漢字 \U0001f600 end", "fr", "c", 1),
]
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, h bigint, fp string, size string, words string, y string"


@pytest.fixture(scope="session")
def odd(spark):
    return spark.createDataFrame([(*r, 0, "f", "s", "w", "y") for r in ROWS], SCHEMA).cache()


@pytest.fixture(scope="session")
def nothing(odd):
    return odd.limit(0)


@pytest.fixture(scope="session")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")
