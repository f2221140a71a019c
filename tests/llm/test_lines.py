"""What op1 does with many lines at a time, without a row of Spark for each of them, equals what is done line by line."""

from __future__ import annotations

import collections
import random

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql import types as T

from logsketch.llm import line_dedup as L


def test_only_repeats_are_rows_of_their_own(spark, monkeypatch):
    written = {}
    monkeypatch.setattr(L, "table", lambda df, what, *a, put=L.table: written.setdefault(what, put(df, what, *a).cache()))
    rows = [(d, "\n".join(f"own words {d}.{k}" if k else "the same for all" for k in range(40))) for d in range(50)]
    monkeypatch.setattr(L, "release", lambda *a: None)
    L.repeated_lines(spark.createDataFrame(rows, "doc_id long, text string").coalesce(2))
    kinds = collections.Counter("repeat" if r.doc_id is not None else "sets" if r.sets is not None else "counts" for r in written["lines"].collect())
    assert kinds["repeat"] == 48 and kinds["sets"] == 2  # of 2,000 lines
    assert {(r.doc_id, r.line) for r in written["repeats"].collect()} == {(d, 0) for d in range(1, 50)}
    for df in written.values():
        df.unpersist()


def test_sets_are_told_apart_in_parts():
    """Also sets whose first digests are equal, the same line twice, and buckets that hold digests of both signs."""
    r = random.Random(9)
    rows = [(r.choice([-(1 << 63), -1, 0, 1, (1 << 63) - 1, r.randint(-(1 << 62), 1 << 62)]), r.randint(0, 2), r.randint(-3, 30), r.randint(0, 3)) for _ in range(400)]
    by = collections.defaultdict(list)
    for one, two, doc, line in rows:
        by[one, two].append((doc, line))
    lone = {x[0] for x in by.values() if len(x) == 1}
    expected = {at for x in by.values() for at in x if at != min(x)}
    firsts = {(*k, *min(x), len(x)) for k, x in by.items() if len(x) > 1}
    for parts, buckets in ((1, 1), (5, 3), (9, 16)):
        gone, blobs = set(), []
        for k in range(parts):
            one, two, doc, line = (np.array(x, np.int64) for x in zip(*rows[k::parts], strict=True))
            for batch in L._told_apart([(one, two, doc, np.ones(len(one), np.int64), line.astype(np.int32))]):
                gone |= {(x["doc_id"], x["line"]) for x in batch.to_pylist() if x["doc_id"] is not None}
                blobs += [x for x in batch.column("sets") if x.is_valid]
        assert lone and len(blobs) == parts
        dealt = pa.Table.from_batches(L._dealt(buckets)([pa.record_batch({"sets": pa.array([b.as_py() for b in blobs], pa.binary())})])).to_pandas()
        assert dealt["bucket"].between(0, buckets - 1).all()
        found = pd.concat([L._repeats(x) for _, x in dealt.groupby("bucket")])
        gone |= {(x.doc_id, x.line) for x in found[found["n"] == 0].itertuples()}
        assert gone == expected
        assert {(x.d1, x.d2, x.doc_id, x.line, x.n) for x in found[found["n"] > 0].itertuples()} == firsts


def test_words_of_pairs_are_compared_many_at_a_time(monkeypatch):
    r = np.random.default_rng(2)
    sets = [np.unique(r.integers(0, 40, size=r.integers(1, 30)).astype(np.uint64)) << np.uint64(24) for _ in range(60)]
    h, at = np.concatenate(sets), np.append(0, np.cumsum([len(x) for x in sets]))
    keep = np.array([k for k in range(60) if k % 7])
    cells = L._forty_bits(at, h | np.uint64(5), keep)
    assert [c.as_py() for c in cells] == [(sets[k] >> np.uint64(24)).view(np.uint8).reshape(-1, 8)[:, :5].tobytes() for k in keep]
    x, y = (r.integers(0, len(keep), 500) for _ in range(2))
    batch = pa.record_batch({"xd": np.arange(500), "xl": np.zeros(500, np.int32), "xw": cells.take(pa.array(x)), "yw": cells.take(pa.array(y))}).slice(3)
    expected = [k for k in range(3, 500) if 100 * len(np.intersect1d(a := sets[keep[x[k]]], b := sets[keep[y[k]]])) >= 30 * len(np.union1d(a, b))]
    for most in (1, 64, 1 << 20):
        monkeypatch.setattr(L, "AT_ONCE", most)
        assert [d for b in L._verify(30)([batch]) for d in b.column("doc_id").to_pylist()] == expected and len(expected) > 10


def test_candidates_whatever_the_order_of_blobs():
    r = random.Random(6)
    at = sorted({(r.randint(0, 30), r.randint(-4, 20), r.randint(0, 2)) for _ in range(400)}, key=lambda _: r.random())
    posts = [(*x, r.randint(5, 9), r.randint(0, 1), r.getrandbits(3), r.getrandbits(3), k) for k, x in enumerate(at)]

    def packed(parts):
        return pd.DataFrame([{"bucket": 0} | {f"c{k}": np.array(x, kind).tobytes() for k, (x, kind) in enumerate(zip(zip(*p, strict=True), L._KINDS, strict=True))} for p in parts])

    found = []
    for parts in ([posts], [posts[200:], posts[:50], posts[50:200]], [sorted(posts, key=lambda p: p[:3])]):
        rows = L._candidates(80)(packed(parts))
        found.append(sorted(map(tuple, rows.loc[rows["kind"] == L.PAIR, ["xd", "xl", "yd", "yl"]].to_numpy().tolist())))
    assert len(found[0]) > 50 and all((x, k) > (y, m) for x, k, y, m in found[0])
    assert found[0] == found[1] == found[2]


def test_texts_that_lose_few_lines_stay_out_of_python(spark, monkeypatch):
    texts = ["", "\n", "a\n\nb\n", "a\r\nb.*c\n\n", "x y\n\x85é\n𝄞 z", None, "one", "\n".join(map(str, range(200)))]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    r = random.Random(1)
    gone = [(d, k) for d, t in enumerate(texts[:7]) for k in range((t or "").count("\n") + 1) if r.random() < 0.6] + [(7, k) for k in range(1, 150)]
    expected = {d: None if t is None else "\n".join(x for k, x in enumerate(t.split("\n")) if (d, k) not in gone) for d, t in enumerate(texts)}
    removed = spark.createDataFrame(gone, "doc_id long, line int")
    lines = {d: 0 if t is None else t.count("\n") + 1 for d, t in enumerate(texts)}
    for few in (L.FEW, 0):
        monkeypatch.setattr(L, "FEW", few)
        out = L.without_lines(docs, removed).collect()
        assert {x.doc_id: x.text for x in out} == expected and {x.doc_id: x.n_lines for x in out} == lines
    monkeypatch.undo()
    monkeypatch.setattr(L, "_without", F.pandas_udf(lambda text, gone: text.map(lambda _: "seen by Python"), T.StringType(), F.PandasUDFType.SCALAR))
    assert {x.doc_id: x.text for x in L.without_lines(docs, removed).collect()} == expected | {7: "seen by Python"}
