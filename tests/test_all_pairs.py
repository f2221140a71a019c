"""All pairs of any number of vectors."""

from __future__ import annotations

import numpy as np

from logsketch import workloads
from logsketch.operators import distance


def test_more_vectors_than_a_bound(spark, sf, monkeypatch):
    monkeypatch.setattr(distance, "MOST", 100)
    monkeypatch.setattr(distance, "BLOCK", 64)
    n = spark.read.parquet(f"{sf}/embeddings.parquet").count()
    got = workloads.w_embedding_distance(spark, sf)
    assert n > 100 and got.count() == got.select("i", "j").distinct().count() == n * (n - 1) // 2


def test_digits():
    d = np.array([0.0, 0.4999995, 1.2345678, 1.25, 2.5e-7, 5e-7, 1e300, np.inf, np.nan])
    got = distance.rounded(d, 6)
    assert got[:6].tolist() == [0.0, 0.5, 1.234568, 1.25, 0.0, 1e-6] and got[6] == 1e300 and np.isinf(got[7]) and np.isnan(got[8])
