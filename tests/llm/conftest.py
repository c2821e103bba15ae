from __future__ import annotations

import pytest


@pytest.fixture(scope="session")
def docs_of(spark):
    """A documents table from (doc_id, text[, source]) rows, with columns of clashing names."""

    def make(rows):
        full = [(*r, "s0")[:3] for r in rows]
        return spark.createDataFrame([(i, t, "en", s, None if t is None else len(t), 7, 7) for i, t, s in full], "doc_id bigint, text string, lang string, source string, n_chars bigint, size int, label int")

    return make
