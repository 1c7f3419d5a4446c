import pytest


SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls, empty and long texts, ties, repeated rows, and extra columns with clashing names."""
    words = " ".join(f"w{i}" for i in range(160))
    long_text = " ".join(f"Word{i % 977},{i}" for i in range(6000)) + " tail  end\n\n x."
    rows = [
        (0, words, "en", "a", 1),
        (1, words, "en", "a", 1),
        (2, words + " more", "en", None, 1),
        (3, "", "de", "b", 0),
        (4, None, None, "b", None),
        (5, long_text, "fr", "c", 1),
        (6, " \t\n", None, None, 3),
        (7, "Ünïcode ÀB ça 日本語 <|endoftext|> x", "fr", "c", 9),
        (8, "12 345 !!", "es", "a", 9),
        (9, "one", "es", "a", 3),
        (9, "one", "es", "a", 3),
        (None, "one", "es", "a", 3),
        (None, None, None, None, None),
        (10, "head " + words[:400] + " foot", "en", "é", 5),
        (11, long_text + " changed", "fr", "c", 1),
    ]
    extra = [(*r, "x", 7, b"y", 1, 2, 3) for r in rows]
    return spark.createDataFrame(extra, SCHEMA + ", t string, fp long, part binary, size int, bucket int, n int")


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def sample_docs(spark):
    return spark.read.parquet("/root/testdata/sf0.001/documents.parquet")


