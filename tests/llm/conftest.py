import pytest


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls, empty and long texts, ties, repeated rows, an id that is null, and columns that clash with inner names."""
    long = " ".join(f"w{i % 977}x{i % 31}" for i in range(12_000))
    shared = " ".join(f"share{i}" for i in range(60))
    edited = " ".join(f"share{i}" if i != 30 else "other" for i in range(60))
    rows = [
        (1, shared, "en"), (2, shared, "en"), (3, "before the copy " + shared + " and after", "en"), (4, edited, None), (5, None, "fr"), (6, "", "fr"), (7, "   \n\t ", None),
        (8, "one two", "de"), (9, "One  two", "de"), (10, long, "en"), (10, long, "en"), (11, "tail " + long[5000:20000], "en"), (None, shared, "en"), (12, "ünï çødé ünï çødé " * 30, "es"),
        (13, "x " * 70, "en"), (14, "a" * 300, None),
    ]
    return spark.createDataFrame([(i, t, g, "s", 7, "b", 3, "c", b"d", 0) for i, t, g in rows], "doc_id long, text string, lang string, source string, n_chars long, body string, bucket int, c string, digest binary, hub int")


@pytest.fixture(scope="session")
def no_docs(odd_docs):
    return odd_docs.limit(0)
