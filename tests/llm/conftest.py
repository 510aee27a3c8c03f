import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long, run string, key int"


@pytest.fixture(scope="session")
def hard(spark):
    """Nulls in any column, empty and long texts, ties, repeated rows, and extra columns with clashing names."""
    line = "a line that several documents share"
    near = " ".join(f"word{i}" for i in range(200))
    rows = [
        (1, None, None, None, None),
        (2, "", "en", "a", 0),
        (3, "", "en", "a", 0),
        (None, "text without an id", "en", "a", 18),
        (None, f"{line}\nmore", "en", None, 20),
        (4, near, "en", "a", len(near)),
        (5, near, "en", "a", len(near)),
        (5, near, "en", "a", len(near)),
        (6, near + " tail", "en", "b", len(near) + 5),
        (7, f"{line}\n{line}\nx\n", "en", "b", 80),
        (8, f"  {line.upper()} \nown line of eight", "de", "b", 80),
        (9, " \t\n\n", "de", "b", 4),
        (10, "123 456", "fr", "c", 7),
        (11, "véry lông " * 30000, "fr", "c", 300000),
        (-12, "tiny", "es", "c", 4),
        (2**62, "tiny", "es", "c", 4),
    ]
    return spark.createDataFrame([(*r, "clash", 1) for r in rows], DOCS).cache()


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOCS)


def rows_of(df):
    return sorted(map(tuple, df.collect()), key=repr)
