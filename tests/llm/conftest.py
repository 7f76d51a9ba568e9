import pytest

SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int", "benchmark": "item_id long, text string",
    "pages": "page_id long, url string, html string", "embeddings": "vec_id long, embedding array<float>, label int",
}


@pytest.fixture
def tables(spark, tmp_path):
    """Writes given rows as tables, the others empty; returns the folder."""

    def write(**rows):
        for name, schema in SCHEMAS.items():
            spark.createDataFrame(rows.get(name, []), schema).coalesce(2).write.parquet(f"{tmp_path}/{name}.parquet")
        return str(tmp_path)

    return write


LONG = "word " * 30_000 + "x" * 200_000


@pytest.fixture
def odd():
    """Nulls in any column, empty and very long texts, repeated rows and ids."""
    return [
        (1, None, None, None, None), (2, "", "en", "a", 0), (3, "   \n\t ", "en", None, 5), (None, "a row without an id at all", "en", "a", 1), (None, None, None, None, None),
        (4, LONG, "en", "a", len(LONG)), (5, "one two three four", "en", "b", 18), (5, "one two three four", "en", "b", 18), (6, "one two three four", "en", "b", 18),
        (7, "éè \U0001f600 ünïcode\x0btabs\x0cfeeds \x1c not a space", "fr", "b", 3), (5, "same id other text", "en", "a", 18),
    ]
