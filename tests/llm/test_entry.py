"""The registered queries against their SQL, the pipeline's stages, and the guard of the entry module."""

from __future__ import annotations

import ast
from pathlib import Path

import duckdb
import pytest

import __spark_entry__ as entry
import corpus_pipeline as pipe

ROOT = Path(__file__).resolve().parents[2]


def test_names():
    names = [n for n in entry.queries() if n.startswith("op")]
    assert sorted({int(n[2:].split("_")[0]) for n in names}) == list(range(1, 11)) and len(names) == 10
    assert "pipeline" in entry.queries() and set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["op1_line_dedup", "op4_ngram_join", "op5_chat_format", "op7_decontaminate", "mix_targets", "personal_base_counts", "url_listed_rules"])
def test_query_equals_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "benchmark", "conversations", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want = con.execute(entry.oracle_sql()[name]).df()
    got = entry.queries()[name](spark, sf).toPandas()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    assert sorted(map(str, got[cols].values.tolist())) == sorted(map(str, want[cols].values.tolist()))


def test_pipeline(spark, sf):
    assert [n for n, _ in pipe.STAGES] == ["quality classifier", "line dedup", "n-gram Jaccard join", "benchmark decontamination", "mixing sources"]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    for _, stage in pipe.STAGES[:-1]:
        before, docs = docs.count(), stage(spark, docs, sf)
        assert docs.columns == columns and 0 < docs.count() <= before
    assert pipe.run(spark, sf).count() > 0


def test_the_engine_does_not_import_the_subpackage():
    for path in (ROOT / "sparsegrid").rglob("*.py"):
        if "llm" in path.relative_to(ROOT / "sparsegrid").parts:
            continue
        for node in ast.walk(ast.parse(path.read_text())):
            names = [a.name for a in node.names] if isinstance(node, ast.Import) else [node.module or ""] if isinstance(node, ast.ImportFrom) else []
            assert not any("sparsegrid.llm" in n or "corpus_pipeline" in n for n in names), path
