"""Pairs of bags within one: what is shuffled does not hold bags again for each item."""

from __future__ import annotations

from logsketch.operators import distance


def test_bags_go_by_their_keys(spark):
    rows = spark.createDataFrame([(t, f"f{t % 3}", 1) for t in range(40)] + [(40, "f0", 2), (41, None, 1), (42, None, 1), (43, "0:", 1), (44, "", 1)], "tree_id long, feature_id string, mult int")
    got = distance.within(rows, 1.0)
    shuffled = [x for x in got._jdf.queryExecution().executedPlan().toString().split("\n") if "Exchange hashpartitioning" in x]
    assert not any("items" in x for x in shuffled)
    pairs = {(r["i"], r["j"]): r["d2"] for r in got.collect()}
    alike = {(i, j) for i in range(40) for j in range(i + 1, 40) if i % 3 == j % 3} | {(41, 42)}
    near = {(i, 40) for i in range(0, 40, 3)}
    assert {p for p, d in pairs.items() if d == 0} == alike and {p for p, d in pairs.items() if d == 1} == near and got.count() == len(pairs)
