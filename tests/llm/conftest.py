from __future__ import annotations

import pytest

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def empty_docs(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty and very long texts, ties, repeated rows, and extra columns with clashing names."""
    long_text = " ".join(f"word{i % 977}" for i in range(30_000))
    rows = [
        (1, "plain text of several words here", "en", "a", 32), (2, None, "en", "a", None), (3, "", None, "b", 0), (None, "text without an id but words", "en", None, 27), (None, None, None, None, None),
        (4, long_text, "en", "b", len(long_text)), (5, "x" * 100_000, "en", "c", 100_000), (6, " \n\t ", "en", "c", 4), (1, "plain text of several words here", "en", "a", 32), (7, "plain text of several words here", "en", "b", 32),
        (8, "line one\nline two\nline three\nline four", "en", "b", 38), (9, "line one\nline two\nline three\nline four", "en", "a", 38), (10, "é ü ñ 中文 \U0001f600", "xx", "d", 11),
    ]
    full = [(*r, i, f"b{i}", "s", 0.5, "t") for i, r in enumerate(rows)]
    return spark.createDataFrame(full, SCHEMA + ", slot int, bucket string, size string, score double, digest string").persist()
