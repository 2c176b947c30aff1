import pytest

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, id long, size string, gone string, bucket int, _h string, _rest string, weight double, key string, times int"


def document(doc_id, text, lang="en", source="a"):
    return (doc_id, text, lang, source, len(text or ""), 7, "x", None, 3, "h", "r", 0.5, "k", 9)


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls in any column, empty and very long texts, ties, repeated rows, and further columns with clashing names."""
    long_text = " ".join(f"word{i % 977}x{i // 977}" for i in range(30_000))
    rows = [
        document(1, None),
        document(2, ""),
        document(3, " \t\n "),
        document(4, "one"),
        document(5, "one"),
        document(6, long_text, "en", "b"),
        document(7, long_text + " end", None, None),
        document(8, "Ünï çödé 日本語 😀 \u0000 nul", "fr", "c"),
        document(9, "12 34 !!", "fr", "c"),
        document(10, "one two three four five six seven", "de", "a"),
        document(10, "one two three four five six seven", "de", "a"),
        document(None, "one two three four five six seven", "de", "a"),
        document(None, None, None, None),
    ]
    return spark.createDataFrame(rows, COLUMNS)


@pytest.fixture(scope="session")
def empty(odd):
    return odd.limit(0)


@pytest.fixture(scope="session")
def docs(spark, tiny):
    return spark.read.parquet(f"{tiny}/documents.parquet")


@pytest.fixture(scope="session")
def texts(docs):
    return {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
