import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double, shard int, node string, host string"
LONG = "lorem ipsum dolor " * 20_000


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls everywhere, empty and very long texts, repeated rows, and columns whose names operators also use."""
    rows = [
        (1, "Mail jo.doe@mail.example.com, the the the", "en", "a", 40, 0.5, 1, "n", "h"), (1, "Mail jo.doe@mail.example.com, the the the", "en", "a", 40, 0.5, 1, "n", "h"),
        (None, "no key here, but words", "en", None, None, None, None, None, None), (2, None, None, None, None, None, None, None, None), (2, None, None, None, None, None, None, None, None),
        (3, "", "de", "a", 0, None, None, None, None), (4, LONG, "en", "a", len(LONG), None, None, None, None), (5, "\t \n", "en", "a", 3, None, None, None, None),
        (6, "x", None, "a", 1, None, None, None, None), (7, "日本語 текст ñandú \U0001f600", "xx", "a", 1, None, None, None, None), (8, "1234 5678 !!", "en", "a", 1, None, None, None, None),
    ]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="session")
def none(odd):
    return odd.limit(0)


@pytest.fixture(scope="session")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (4, 0, 1), (3, None, None), (None, 1, 1), (99, 0, 0)], "doc_id long, quality int, toxic int")
