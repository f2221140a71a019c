"""The phases do their work once."""

from __future__ import annotations

import numpy as np
import pytest

from logsketch.operators import audit, distance, fptree, linkage
from logsketch.operators.relabel import feature_bag


def test_skeletons_read_the_log_once(spark):
    rows = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            rows.add(b.num_rows)
            yield b

    log = spark.createDataFrame([(f"SELECT a{k % 7} FROM t WHERE b = {k}", None) for k in range(100)], "sql string, ts timestamp")
    found = audit.skeletons(log.mapInArrow(count, log.schema))
    assert rows.value == 100 and sorted((r["skel_id"], r["skel_text"], r["n_stmt"]) for r in found.collect()) == [(k, f"SELECT a{k} FROM t WHERE b = ?", 15 if k < 2 else 14) for k in range(7)]


def test_bags_and_prefixes_are_made_once(spark):
    own = spark.createDataFrame([(1, n, f) for n in range(3) for f in "ab"] + [(1, 0, "a"), (2, 0, "c")], "tree_id long, node_id int, feature_key string")
    bag = feature_bag(own)
    assert bag._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0].count("Exchange hashpartitioning") == 1
    assert sorted(tuple(r) for r in bag.collect()) == [(1, "a", 3), (1, "b", 3), (2, "c", 1)]
    tree = fptree.fp_tree(spark.createDataFrame([(0, 1, ["x", "y"]), (0, 2, ["x"]), (0, 3, [])], "cluster long, set_id long, items array<string>"))
    assert tree._jdf.queryExecution().optimizedPlan().toString().count("md5") == 1
    rows = {(r["depth"], r["item"]): r for r in tree.collect()}
    assert len(rows) == 2 and rows[1, "x"]["count"] == 2 and rows[1, "x"]["parent_key"] == "" and rows[2, "y"]["parent_key"] == rows[1, "x"]["node_key"]


@pytest.mark.parametrize("large", [1, 5000])
def test_matrix_of_bags(large):
    rng = np.random.default_rng(2)
    items = [[(f"f{f}", int(m) * large) for f, m in enumerate(rng.integers(0, 3, 12)) if m] + [(f"own{k}", 2)] for k in range(40)]
    whole = [dict(x) for x in items]
    want = [[sum((a.get(f, 0) - b.get(f, 0)) ** 2 for f in a.keys() | b.keys()) for b in whole] for a in whole]
    assert distance.matrix(items).tolist() == want


@pytest.mark.parametrize("link", ["complete", "single", "average", "centroid"])
def test_merges_of_bags(spark, link):
    rng = np.random.default_rng(4)
    x = rng.integers(0, 4, (30, 5)) + np.eye(30, 5, dtype=int)
    bag = spark.createDataFrame([(t * 3, f, int(m)) for t, row in enumerate(x) for f, m in enumerate(row) if m], "tree_id long, feature_id long, mult int")
    d = ((x[:, None] - x[None]) ** 2).sum(axis=2).astype(float)
    want = linkage.agglomerate(np.sqrt(d) if link == "average" else d, link, np.arange(30) * 3, x if link == "centroid" else None)
    got = linkage.hierarchical(bag, link).orderBy("step").collect()
    assert [(r["left"], r["right"], r["size"]) for r in got] == [(a, b, s) for a, b, _, s in want]
    assert np.allclose([r["height"] for r in got], [h if link == "average" else h**0.5 for _, _, h, _ in want])
