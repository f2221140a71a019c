"""Texts are neither written nor shuffled where only a few of them change."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from logsketch.llm import language, line_dedup
from logsketch.llm.sketch import parted


@pytest.fixture
def plain(spark):
    """Plans as they are made, without what a run changes in them."""
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    yield
    spark.conf.unset("spark.sql.adaptive.enabled")


def branches(df) -> list[str]:
    """The plan below each child of the topmost union."""
    lines = df._jdf.queryExecution().executedPlan().toString().split("\n")
    at = next(k for k, x in enumerate(lines) if "Union" in x)
    column = len(lines[at].split("Union")[0].rstrip("* (0123456789)"))
    found: list[list[str]] = []
    for x in lines[at + 1 :]:
        if x[column : column + 2] in (":-", "+-"):
            found.append([])
        found[-1].append(x)
    return ["\n".join(x) for x in found]


def documents(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "'en' lang", "'s' source", "cast(length(text) as long) n_chars")


def test_parted(spark):
    rows = spark.createDataFrame([(k, "x") for k in range(-500, 500)] + [(None, "x"), (7, "y")], "k long, `a.b` string")
    for cells, most in ((1 << 24, 8), (64, 1002)):
        keys = spark.createDataFrame([(3,), (7,), (None,), (-9,)], "k long").select(F.xxhash64("k"))
        clear, hit = parted(rows, F.xxhash64("k"), keys, cells)
        assert clear.columns == hit.columns == rows.columns
        found = [r.k for r in hit.collect()]
        assert sorted(map(str, found + [r.k for r in clear.collect()])) == sorted(str(r.k) for r in rows.collect())
        assert {3, 7, None, -9} <= set(found) and found.count(7) == 2 and len(found) <= most
    clear, hit = parted(rows, F.xxhash64("k"), keys.limit(0))
    assert clear.count() == 1002 and hit.count() == 0


def test_lines(spark, plain):
    docs = documents(spark, [(k, f"own {k}\nx y z") for k in range(9)] + [(None, "x y z")])
    out = line_dedup.without_lines(docs, spark.createDataFrame([(2, 1), (4, 0), (4, 1)], "doc_id long, line int"))
    got = {r.doc_id: (r.text, r.n_lines, r.n_removed) for r in out.collect()}
    assert got == {k: (f"own {k}\nx y z", 2, 0) for k in (0, 1, 3, 5, 6, 7, 8)} | {2: ("own 2", 2, 1), 4: ("", 2, 2), None: ("x y z", 1, 0)}
    assert any("hashpartitioning" not in x for x in branches(out))


def test_near_duplicates(spark, plain):
    same = " ".join(f"w{k}" for k in range(40))
    rows = [(1, same), (2, same + " more"), (3, "a b c d e f"), (3, "a b c d e f"), (4, "g h i j k l"), (4, "m n o p q r"), (5, "s t u v w x"), (None, same), (None, same), (6, None)]
    out = pipeline.dedup_near(spark, documents(spark, rows), "")
    assert sorted(map(str, ((r.doc_id, r.text) for r in out.collect()))) == sorted(map(str, [(1, same), (3, "a b c d e f"), (4, "g h i j k l"), (4, "m n o p q r"), (5, "s t u v w x"), (None, same), (6, None)]))
    assert any("hashpartitioning" not in x for x in branches(out))


def test_languages_are_told_without_writing_texts(spark, monkeypatch):
    written = []
    monkeypatch.setattr(language, "table", lambda df, what, *a, put=language.table: written.append(df.schema.json()) or put(df, what, *a))
    rows = [(k, f"the house {k} stands on the hill and the river runs below") for k in range(30)] + [(30, "12 34"), (31, None), (None, "12 34"), (30, "the house stands on the hill")]
    docs = documents(spark, rows)
    out = pipeline.identify_language(spark, docs, "")
    assert written and not any('"text"' in x or '"_text"' in x for x in written)
    expected = language.identify(docs).where("accepted").select(*pipeline.COLUMNS)
    assert sorted(map(str, out.collect())) == sorted(map(str, expected.collect())) and 30 < out.count() < 34
