from __future__ import annotations

import pandas as pd
import pytest


@pytest.fixture(scope="session")
def texts(spark, sf_small) -> pd.DataFrame:
    return spark.read.parquet(f"{sf_small}/documents.parquet").select("doc_id", "text", "lang", "source").toPandas().sort_values("doc_id")


@pytest.fixture(scope="session")
def odd(spark):
    """Null ids and texts, blank and repeated rows, one id with two texts, clashing names."""
    rows = [
        (1, "alpha beta gamma delta epsilon zeta", "en", None, 1, "x"),
        (1, "alpha beta gamma delta epsilon zeta", "en", None, 1, "x"),
        (2, None, None, "s", None, None),
        (3, "", "fr", "s", 0, "y"),
        (4, " \n\t ", "fr", "s", 4, "y"),
        (None, "alpha beta gamma delta epsilon zeta", None, "t", 9, "z"),
        (5, "one two", "en", "t", 7, "z"),
        (5, "quite another text for the very same number", "en", "t", 7, "z"),
        (6, "lang " * 30_000, "en", "u", 5, "z"),
    ]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, size string")


@pytest.fixture(scope="session")
def empty(odd):
    return odd.filter("false")
