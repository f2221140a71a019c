"""Joins and comparisons that do not grow with the square of their input, on edge cases."""

from __future__ import annotations

import duckdb
import numpy as np

from logsketch import registry
from logsketch.operators import distance


def test_theta_join_meets_in_bands(spark, tmp_path):
    balance = [0.0, 49.99, 50.0, 64.0, 113.99, 114.0, -0.01, -50.0, -50.01, 1e18, 1e18, 1e18, 1e300, float("inf"), 1e300, float("nan"), float("inf"), float("nan"), None, 63.99, 63.99, None]
    rows = [(k % 13, k % 2, b) for k, b in enumerate(balance)]  # a repeated key as well
    spark.createDataFrame(rows, "c_custkey long, c_nationkey int, c_acctbal double").write.parquet(f"{tmp_path}/customer.parquet")
    for name in ("nation", "region", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"):
        spark.createDataFrame([(1,)], "x int").write.parquet(f"{tmp_path}/{name}.parquet")
    got = registry.queries()["op_join_theta"](spark, str(tmp_path))
    c = duckdb.connect()
    c.execute(f"CREATE VIEW customer AS SELECT * FROM '{tmp_path}/customer.parquet/*.parquet'")
    assert "band" in got._jdf.queryExecution().optimizedPlan().toString()
    want = dict(c.execute(registry.oracle_sql()["op_join_theta"]).fetchall())
    assert len(want) == 2 and {r["c_nationkey"]: r["n"] for r in got.collect()} == want


def test_bags_within_one(spark):
    rng = np.random.default_rng(5)
    bags = {t: np.bincount(rng.integers(0, 4, rng.integers(1, 5)), minlength=4) for t in range(80)}
    rows = spark.createDataFrame([(t, f, int(n)) for t, b in bags.items() for f, n in enumerate(b) if n], "tree_id long, feature_id long, mult int")
    for tau in (0.5, 1.0):
        want = sorted((i, j, int(d)) for i in bags for j in bags if i < j and (d := ((bags[i] - bags[j]) ** 2).sum()) <= tau)
        got = distance.within(rows, tau)
        assert sorted((r["i"], r["j"], r["d2"]) for r in got.collect()) == want
        assert "near" not in got.columns and "leading" not in got._jdf.queryExecution().optimizedPlan().toString()


def test_vector_pairs(spark, monkeypatch):
    monkeypatch.setattr(distance, "BLOCK", 4)
    x = [[0.0, 0.0], [3.0, 4.0], None, [1.0], [float("nan"), 0.0], [1.0, None], [0.0, 1.0], [0.0, 0.0], [3.0, 4.5], []]
    got = distance.vector_pairs(spark.createDataFrame(list(enumerate(x)), "id long, v array<double>"))
    pairs = {(r["i"], r["j"]): r["d"] for r in got.collect()}
    assert len(pairs) == 45 and pairs[0, 1] == 5 and pairs[0, 7] == 0 and pairs[0, 2] is None and pairs[0, 3] is None and pairs[0, 5] is None and np.isnan(pairs[0, 4])
    near = distance.vector_pairs(spark.createDataFrame(list(enumerate(x)), "id long, v array<double>"), 1.0)
    assert sorted((r["i"], r["j"]) for r in near.collect()) == [(0, 6), (0, 7), (1, 8), (6, 7)]
