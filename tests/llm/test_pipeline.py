from __future__ import annotations

import importlib.util
import sys
from pathlib import Path

import pytest

pytestmark = pytest.mark.skipif(importlib.util.find_spec("corpus_pipeline") is None, reason="no pipeline here")


def test_stages_take_effect(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet").cache()
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5
    sizes = []
    columns = docs.columns
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf)
        sizes.append(out.count())
        if k < 4:
            assert out.columns == columns
        assert stage(spark, docs.where("false"), sf).count() == 0
    assert sizes[0] < docs.count() and sizes[1] == docs.count() and sizes[2] < docs.count() and sizes[3] < docs.count() and sizes[4] == docs.count()


def test_run(spark, sf):
    import corpus_pipeline

    got = corpus_pipeline.run(spark, sf)
    assert 0 < got.count() < spark.read.parquet(f"{sf}/documents.parquet").count()
    assert {"doc_id", "text", "taken"} <= set(got.columns)
    assert got.select("doc_id").distinct().count() == got.count()


def test_registry():
    import __spark_entry__ as e

    names = set(e.queries())
    assert "pipeline" in names and all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11))
    assert str(Path(__file__).resolve().parents[2]) in sys.path
