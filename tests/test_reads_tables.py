"""Queries whose statements or examples come from the given tables."""

from __future__ import annotations

import pytest

from logsketch import registry, workloads
from logsketch.sources import logsynth


@pytest.mark.parametrize("name", ["w_common_feature_tree", "w_metric_ablation", "w_misaligned", "w_near_pair"])
def test_the_sample_is_read_each_time(spark, sf, monkeypatch, name):
    reads = []
    monkeypatch.setattr(logsynth, "query_log", lambda *a, f=logsynth.query_log: reads.append(a) or f(*a))
    for k in (1, 2):
        assert registry.queries()[name](spark, sf).count() and len(reads) == k


def test_statements_of_suppliers(spark, sf):
    rows = registry.queries()["op_statement_source"](spark, sf).collect()
    keys = [r[0] for r in spark.read.parquet(f"{sf}/supplier.parquet").select("s_suppkey").collect()]
    assert sorted(r["stmt_id"] for r in rows) == sorted(keys) and {r["root"] for r in rows} == {"SELECT"}


def test_lookups_of_customers(spark, sf):
    rows = registry.queries()["w_lookup_triplet"](spark, sf).collect()
    nations = spark.read.parquet(f"{sf}/customer.parquet").select("c_nationkey").distinct().count()
    assert len(rows) == 3 * nations
    assert all((r["d2_abstract"] == 0) == (r["pair"] == "ab") for r in rows)


def test_clauses_of_the_log(spark, sf):
    rows = registry.queries()["w_cnf_examples"](spark, sf).collect()
    assert {r["formula"] for r in rows} == {"or", "and"}
    assert any(" OR " in r["clause"] for r in rows if r["formula"] == "or") and not any(" OR " in r["clause"] for r in rows if r["formula"] == "and")
    assert max(r["n_structures"] for r in rows) <= 346


def test_shrinking_line_states(spark, sf):
    rows = {r["feature"]: r for r in workloads.w_shrink_example(spark, sf).collect()}
    assert all(r["kept_strict"] for r in rows.values()) and all(r["kept_nonstrict"] == ("(" in f) for f, r in rows.items())
