import pytest

LONG = "lorem ipsum dolor " * 20_000


@pytest.fixture(scope="session")
def edge_docs(spark):
    """Nulls everywhere, empty and very long texts, ties, repeated rows, extra columns with clashing names."""
    rows = [
        (1, "one two three four five six seven eight nine ten\nshort", "en", "a", 1), (1, "one two three four five six seven eight nine ten\nshort", "en", "a", 1),
        (2, None, None, None, None), (None, "text without an id that is still text", "en", "a", 3), (3, "", "en", "b", 0), (4, LONG, "en", "b", 5),
        (5, "one two three four five six seven eight nine ten\nother", "de", "a", 1), (6, " \t\n ", "fr", None, 4), (None, None, None, None, None), (7, "été 😀 \u0000 x", "fr", "c", 9),
    ]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for c in ("row_key", "fp", "host", "line", "h", "shard", "part", "size", "units", "spans", "component_id", "hits", "rank", "ids"):
        from pyspark.sql import functions as F

        df = df.withColumn(c, F.lit(None).cast("string"))
    return df
