"""What bounds the memory of workers and readers."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from logsketch.llm import common, lm_score


def test_a_file_holds_few_chunks(spark, monkeypatch):
    """A reader decodes all of a file's chunks at once."""
    made = []
    monkeypatch.setattr(lm_score, "table", lambda *a: made.append(common.table(*a)) or made[-1])
    docs = spark.range(700).coalesce(1).select(F.col("id").alias("doc_id"), F.repeat(F.concat(F.lit("word"), "id", F.lit(" ")), 4000).alias("text"), (F.col("id") < 9).alias("aim"))
    assert lm_score.score(docs, "aim").count() == 700
    assert made[0].count() > lm_score.FILE
    assert max(r["count"] for r in made[0].groupBy(F.input_file_name()).count().collect()) <= lm_score.FILE


def test_batches_are_small_only_inside(spark):
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name)

    def sizes(batches):
        import pyarrow as pa

        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows])], names=["n"])

    rows = spark.range(0, 40, 1, 1).select(F.repeat(F.lit("x"), 1 << 20).alias("text"))
    with pytest.raises(ValueError), common.small_batches(spark):
        most = rows.mapInArrow(sizes, "n long").agg(F.max("n")).first()[0]
        raise ValueError
    assert most <= 9 and spark.conf.get(name) == before
