from __future__ import annotations

import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def odd_documents(spark):
    """Nulls in every column, empty, blank and long texts, ties, repeated rows, and extra columns with clashing names."""
    long_text = " ".join(f"word{i % 97} other{i}" for i in range(6000))
    rows = [
        (1, "The quick brown fox jumps over the lazy dog and runs away from it all day long in the sun today.", "en", "a", 10),
        (1, "The quick brown fox jumps over the lazy dog and runs away from it all day long in the sun today.", "en", "a", 10),
        (2, None, None, None, None),
        (None, "no id here but words", "en", "b", 4),
        (None, None, None, None, None),
        (3, "", "en", "b", 0),
        (4, " \t\n\x0b\x0c\r ", "de", "b", 7),
        (5, long_text, "en", None, len(long_text)),
        (6, "x" * 5000, "fr", "c", 5000),
        (7, "naïve café ΑΣ ß İ 你好 世界 \U0001f600 end\x1cq don't I'LL", "xx", "c", 1),
        (8, "<|endoftext|> a<|startoftext|>b </s>[INST] ok [/INST]", "en", "d", 1),
        (9, "same same same same same same same same same same same same same same same same same same same same same same", "en", "a", 1),
        (10, "line one\nline two\nline one\n\n  \nline one", "en", "a", 1),
    ]
    df = spark.createDataFrame(rows, DOCS)
    return df.selectExpr("*", "1 as fp", "'k' as word", "2 as size", "'z' as ids", "0 as span", "0 as block", "1.5 as score")


@pytest.fixture(scope="session")
def no_documents(spark):
    return spark.createDataFrame([], DOCS)
