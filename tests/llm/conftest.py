import pytest

#: doc_id, text, lang, source, n_chars, and columns whose names clash with those inside operators.
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, batch int, size string, row string, score double"


def document(i, text, source="s"):
    return (i, text, "en", source, None if text is None else len(text), 7, "big", "r", 0.5)


@pytest.fixture(scope="session")
def make(spark):
    def build(rows):
        return spark.createDataFrame([document(*r) for r in rows], SCHEMA)

    return build


@pytest.fixture(scope="session")
def odd(make):
    """Nulls, empty and long texts, repeated rows and ids."""
    words = " ".join(f"w{i % 997}" for i in range(20000))
    copy = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen"
    return make([(1, None), (2, ""), (3, "   \n\t"), (4, copy), (5, copy), (5, copy), (6, copy + " x", None), (None, "a null id " * 20), (7, words), (8, words + " tail", "t"), (9, "é" * 300), (9, "two texts with one id")])


@pytest.fixture(scope="session")
def nothing(make):
    return make([])
