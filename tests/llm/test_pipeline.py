"""The pipeline's stages on odd rows, each against what it promises."""

from __future__ import annotations

import pytest

import corpus_pipeline as pipe

LONG = " ".join(f"w{k % 977}" for k in range(60_000))
BASE = " ".join(f"base{k}" for k in range(40))
ODD = [
    (1, None, "a"), (2, "", "a"), (3, " \t\n ", None), (None, "no id\nno id", "b"), (None, None, None), (4, "said twice and twice again", "b"), (4, "said twice and twice again", "b"),
    (5, LONG, "c"), (6, BASE, "a"), (7, BASE + " x", "b"), (8, BASE, None), (9, "one line of eight words or a few more\none line of eight words or a few more", "a"),
]
KEEPING = [s for s in pipe.STAGES[:-1]]


@pytest.fixture(scope="module")
def docs(spark):
    """Odd rows with columns whose names stages might use themselves."""
    rows = [(i, t, "en", s, None if t is None else len(t), 1, 2, "x", 3, "y") for i, t, s in ODD]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint, size int, label int, component string, mark int, words string")


def told(df):
    return sorted((str(r.doc_id), str(r.text), str(r.source)) for r in df.collect())


@pytest.mark.parametrize("name,stage", KEEPING, ids=[n for n, _ in KEEPING])
def test_stages_keep_columns_and_take_empty_tables(spark, sf, docs, name, stage):
    out = stage(spark, docs, sf)
    assert out.columns == docs.columns and 0 < out.count() <= len(ODD)
    assert stage(spark, docs.limit(0), sf).count() == 0


def test_lines(spark, sf, docs):
    out = {(r.doc_id, r.source): r for r in pipe.line_stage(spark, docs, sf).collect()}
    assert out[9, "a"].text == "one line of eight words or a few more" and out[9, "a"].n_chars == 37
    assert out[None, "b"].text == "no id\nno id" and out[1, "a"].text is None and out[1, "a"].n_chars is None
    assert out[7, "b"].text == "" and out[8, None].text == "" and out[6, "a"].text == BASE and out[3, None].text == " \t\n "
    assert out[4, "b"].text == "said twice and twice again"


def test_near_duplicates(spark, sf, docs):
    kept = told(pipe.near_duplicate_stage(spark, docs, sf))
    gone = [("7", BASE + " x", "b"), ("8", BASE, "None")]
    assert kept == sorted(x for x in ((str(i), str(t), str(s)) for i, t, s in ODD) if x not in gone)


def test_benchmark(spark, sf, docs):
    item = spark.read.parquet(f"{sf}/benchmark.parquet").orderBy("item_id").first().text
    more = docs.union(spark.createDataFrame([(50, item, "en", "a", 9, 1, 2, "x", 3, "y"), (50, item, "en", "a", 9, 1, 2, "x", 3, "y"), (51, f"{item} {LONG}", "en", "a", 9, 1, 2, "x", 3, "y")], docs.schema))
    kept = told(pipe.benchmark_stage(spark, more, sf))
    assert kept == sorted([(str(i), str(t), str(s)) for i, t, s in ODD] + [("51", f"{item} {LONG}", "a")])


def test_mixing(spark, sf, docs):
    pieces = pipe.mixing_stage(spark, docs, sf).collect()
    texts = {i: (t or "").split() for i, t, _ in ODD}
    assert pieces and {p.doc_id for p in pieces} <= {4, 5, 6, 7, 8, 9, None}
    assert all(p.text.split() == texts[p.doc_id][p.first_word : p.first_word + p.n_words] for p in pieces if p.doc_id is not None)
    assert pipe.mixing_stage(spark, docs.limit(0), sf).count() == 0


def test_run_leaves_one_folder(spark, sf):
    from pathlib import Path
    from urllib.parse import urlparse

    from sparsegrid.plans.lineage import ensure_checkpoint_dir

    shared = Path(urlparse(ensure_checkpoint_dir(spark)).path)
    before = set(shared.glob("corpus-*"))
    assert pipe.run(spark, sf).count() > 0
    (made,) = set(shared.glob("corpus-*")) - before
    assert [p.name for p in made.iterdir() if p.is_dir()] == ["3"]
