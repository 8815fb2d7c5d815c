import pytest
from pyspark.sql import types as T

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def docs(spark):
    """Makes a documents frame of (doc_id, text) or (doc_id, text, source) rows."""

    def make(rows):
        full = [(r[0], r[1], "en", r[2] if len(r) > 2 else "s", None if r[1] is None else len(r[1])) for r in rows]
        return spark.createDataFrame(full, DOCS)

    return make


#: Nulls, empties, blanks, ties, repeats, non-ASCII, a very long text.
HARD = [(1, None), (2, ""), (3, "  \n\t"), (4, "one"), (4, "one"), (5, "one two three"), (None, "null id text"), (6, "漢字 テスト 😀"), (7, "a b c d e " * 4000), (8, "one two three"), (9, "\x00 odd ﻿")]
