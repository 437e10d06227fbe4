import pytest

#: Names that the operators use themselves, as columns of the input.
CLASHES = ("k1", "_k1", "_k2", "_row", "fp", "label", "uid", "host", "_in", "at", "b", "ids", "n_words", "kept")


@pytest.fixture(scope="session")
def messy(spark):
    """Null ids and texts, empty, white and very long texts, repeated rows, ties and clashing columns."""
    long = " ".join(f"w{i % 977}x{i}" for i in range(60000))
    prose = " ".join(f"Word{i} and" for i in range(60))
    rows = [
        (1, prose, "en", "s"), (2, prose, "en", "s"), (2, prose, "en", "s"), (3, None, None, None), (None, prose + " tail", "de", "s"), (None, None, "de", "s"),
        (4, "", "en", "s"), (5, " \n\t ", "en", None), (6, long, "fr", "t"), (7, "é ÉCOLE \U0001f600 mail bob@x.org, +1 (212) 555-0100, 4539 1488 0343 6467; 10.0.0.1", "fr", "t"),
    ]
    df = spark.createDataFrame([(*r, len(r[1] or "")) for r in rows], "doc_id long, text string, lang string, source string, n_chars long")
    from pyspark.sql import functions as F

    return df.withColumns({c: F.lit(f"own {c}") for c in CLASHES})


@pytest.fixture(scope="session")
def nothing(messy):
    return messy.limit(0)
