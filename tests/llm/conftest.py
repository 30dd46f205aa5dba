import pytest

#: Null, empty, blank, tied, repeated and very long texts; extra columns with clashing names.
ODD = [
    (1, None, "en", "a", 0),
    (2, "", "en", "a", 0),
    (3, " \t\n", "de", "b", 3),
    (4, "one two three four five", "en", "a", 23),
    (4, "one two three four five", "en", "a", 23),
    (5, "one two three four five", "en", None, 23),
    (6, "Größe 東京 naïve", "de", "b", 16),
    (7, "word " * 30_000, "en", "c", 150_000),
    (8, "x" * 50_000, "en", "c", 50_000),
    (None, "no id here", None, None, None),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def odd(spark):
    extra = ", score double, component_id long, size long, a long, key string, pattern string, copies long, first string, _score double, _judged string, fingerprint long, head string, id long, _size long"
    rows = [(*r, 0.5, 1, 2, 3, "k", "p", 4, "f", 0.5, "j", 5, "h", 6, 7) for r in ODD]
    return spark.createDataFrame(rows, SCHEMA + extra)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], SCHEMA)
