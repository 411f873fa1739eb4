import re
from collections import Counter

import pytest

WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls in every column, empty and long texts, repeated rows, and further columns that clash with the operators' own names."""
    rows = [
        (0, "the of and " * 40, "en", "a", 5, "x"),
        (1, None, "en", "a", None, "x"),
        (2, "", None, None, 0, None),
        (3, " \n\t ", "de", "b", 3, "x"),
        (4, "the of and " * 40, "en", None, 5, "x"),
        (4, "the of and " * 40, "en", None, 5, "x"),
        (5, "word" * 30_000 + " é漢😀   end", "fr", "b", 1, "x"),
        (None, "no id at all", "en", "c", 1, "x"),
        (6, "12 34 !!", "en", "c", 1, "x"),
        (7, "und die der " * 30 + "\n" + "und die der " * 30, "de", "c", 1, "x"),
    ]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, size string")


@pytest.fixture(scope="session")
def empty_docs(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")


def rows_of(df):
    return Counter(tuple(r) for r in df.collect())
