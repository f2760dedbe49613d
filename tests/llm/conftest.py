import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def odd(spark):
    """Nulls in every column, empty and long texts, repeats, clashing columns."""
    words = " ".join(f"word{i % 700}" for i in range(30_000))
    rows = [
        (1, "one two three four five six", "en", "a", 27), (2, None, None, None, None), (3, "", "en", "a", 0), (None, "lonely text here", "en", "b", 16),
        (5, words, "en", "b", len(words)), (6, words, "fr", None, len(words)), (7, "  \t\n ", "en", "c", 5), (8, "héllo wörld 日本語 😀 ﬁ", "de", "c", 21),
        (9, "one two three four five six", "en", "a", 27), (9, "one two three four five six", "en", "a", 27), (11, "▁ odd  marks\r\nhere <s> <0x41>", "en", "d", 30), (12, "x", "en", "d", 1),
    ]
    df = spark.createDataFrame(rows, SCHEMA)
    for c in ("size", "target", "ids", "media", "n_bytes", "key", "rank", "chunk", "shard", "_id", "_times", "_turn", "_row", "id_", "times_", "row_", "GONE_", "mark"):
        df = df.selectExpr("*", f"'clash' as {c}")
    return df.repartition(3).cache()


@pytest.fixture(scope="session")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (5, 1, 0), (3, 0, 1), (None, 1, 1), (8, None, None)], "doc_id long, quality int, toxic int")
