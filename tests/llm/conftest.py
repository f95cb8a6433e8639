import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def odd(spark):
    """Documents with nulls, empty and long texts, repeated texts, and no words."""
    long = " ".join(f"word{i % 977}x" for i in range(30_000))
    texts = [None, "", " ", "one", "The quick brown fox jumps over the lazy dog again and again.", "The quick brown fox jumps over the lazy dog again and again.", "!!! ???", "!!!", long, "日本語のテキスト🙂 é́", "\x1c\x85 odd spaces here", "a@b.co, 4111 1111 1111 1111, +1 (275) 555-7228, 10.0.0.1", None]
    rows = [(i, t, "en", "s", None if t is None else len(t)) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], DOCS)
