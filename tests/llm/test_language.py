"""Languages that few rows declare."""

from __future__ import annotations

import random

from pyspark.sql import functions as F

from logsketch.llm import language


def test_rare_language_stays_known(spark):
    """Neither its share nor rows in other languages decide whether a declared language has a model."""
    r = random.Random(4)
    make = lambda w, n: [" ".join(r.choice(w) for _ in range(12)) for _ in range(n)]
    english, finnish, basque = ["house", "garden", "with", "the", "weather"], ["yksi", "kaksi", "kolme", "hyvää", "päivää"], ["zazpi", "etxea", "gizona", "bat", "ikastola"]
    rows = [(t, "en") for t in make(english, 30_000)] + [(t, "fi") for t in make(finnish, 25)] + [(t, "eu") for t in make(basque, 2)]
    df = spark.createDataFrame([(k, t, g, "h") for k, (t, g) in enumerate(rows)], "doc_id long, text string, lang string, source string")
    out = language.identify(df).where("lang <> 'en'").collect()
    assert len(out) == 27 and all(x.accepted and x.language == x.lang for x in out)
    assert all(x.text_language == "fi" for x in out if x.lang == "fi")


def test_wrong_declarations_are_overruled_by_the_text(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet").where("length(text) > 200")
    names = sorted(r.lang for r in d.select("lang").distinct().collect())
    other = F.element_at(F.array(*map(F.lit, names)), (F.array_position(F.array(*map(F.lit, names)), F.col("lang")) % len(names) + 1).cast("int"))
    wrong = d.withColumn("truth", F.col("lang")).withColumn("lang", F.when(F.col("doc_id") % 20 == 3, other).otherwise(F.col("lang")))
    out = language.identify(wrong, host=None).where("lang <> truth").toPandas()
    assert len(out) > 3 and (out.language == out.truth).mean() > 0.9


def test_any_column_names(spark):
    df = spark.createDataFrame([(k, "the house of the garden " * 3, "en", "h", 1, "x", 2.0) for k in range(30)], "doc_id long, text string, lang string, _host string, _ll int, `a.b` string, posterior double")
    out = language.identify(df, host="_host")
    assert out.columns == ["doc_id", "text", "lang", "_host", "_ll", "a.b", "language", "posterior", "accepted", "text_language"]
    assert {(r._host, r._ll, r["a.b"], r.language) for r in out.collect()} == {("h", 1, "x", "en")}
