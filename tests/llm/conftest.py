import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def documents(spark):
    """A frame of (doc_id, text) or (doc_id, text, source) rows, with the columns of the table."""

    def make(rows):
        return spark.createDataFrame([(r[0], r[1], "en", r[2] if len(r) > 2 else "s", None if r[1] is None else len(r[1])) for r in rows], SCHEMA)

    return make


#: Rows that every operator must take: nulls, empty and long texts, repeated rows, odd characters.
ODD = [
    (1, None, None),
    (2, "", "a"),
    (None, "a text without an id", "a"),
    (None, None, None),
    (3, "the same row twice\nand a second line that is long enough", "a"),
    (3, "the same row twice\nand a second line that is long enough", "a"),
    (4, "word " * 30_000, "b"),
    (5, "x" * 100_000, "b"),
    (6, "\n\t \u00a0 \u2003", "b"),
    (7, "é漢字🎉 ñ " * 20, None),
    (8, "\x00\x01 control", "c"),
]
