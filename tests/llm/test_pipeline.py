"""The pipeline's stages on the smallest tables, each against its own input."""

from __future__ import annotations

import corpus_pipeline as pipeline
from logsketch.llm import line_dedup
from logsketch.llm.common import table


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    ids = {r.doc_id for r in docs.select("doc_id").collect()}
    for name, stage in pipeline.STAGES[:-1]:
        docs = table(stage(spark, docs, sf), name)
        assert docs.columns == columns
        now = {r.doc_id for r in docs.select("doc_id").collect()}
        assert now <= ids and docs.count() == len(now)
        ids = now
    packed = pipeline.STAGES[-1][1](spark, docs, sf).toPandas()
    assert set(packed.doc_id) == ids
    bench = [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    assert not any(b in r.text for r in docs.collect() for b in bench)


def test_run_equals_the_stages(spark, sf):
    out = pipeline.run(spark, sf)
    assert out.columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"] and out.count() > 0


def test_texts_lose_their_lines_once(spark, monkeypatch):
    """A second Python step in one task doubles an executor's workers, and all of them come to hold the tokenizer."""
    docs = spark.createDataFrame([(1, "a b\nx", 5), (2, "a b\ny", 5), (3, "a b", 3), (4, " ", 1)], "doc_id long, text string, n_chars long").selectExpr("doc_id", "text", "'en' lang", "'s' source", "n_chars")
    monkeypatch.setattr(line_dedup, "repeated_lines", lambda docs: spark.createDataFrame([(2, 0), (3, 0)], "doc_id long, line int"))
    out = pipeline.dedup_lines(spark, docs, "")
    assert out._jdf.queryExecution().executedPlan().toString().count("ArrowEvalPython [") == 1
    assert sorted((r.doc_id, r.text, r.n_chars) for r in out.collect()) == [(1, "a b\nx", 5), (2, "y", 1), (4, " ", 1)]
