from __future__ import annotations

import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def docs_of(spark):
    """Documents from texts; ids count from 0, other columns are filled in."""

    def make(texts, **more):
        rows = [(k, t, more.get("lang", "en"), more.get("source", "s"), None if t is None else len(t)) for k, t in enumerate(texts)]
        return spark.createDataFrame(rows, DOCS)

    return make


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], DOCS)
