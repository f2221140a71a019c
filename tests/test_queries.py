"""Queries against their SQL on the smallest tables, and the shape of plans."""

from __future__ import annotations

import duckdb
import pytest
from pyspark.sql import functions as F

from logsketch import registry
from logsketch.functions import skeleton
from logsketch.plans.dialect import TABLES
from logsketch.sources import logsynth

SLOW = ("bench_", "w_log_summary", "w_feature_ablation", "w_kmeans", "w_role")
QUERIES, ORACLES = registry.queries(), registry.oracle_sql()


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    c.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, sf, duck, name):
    if name.startswith(SLOW):
        pytest.skip("run by bench.py")
    df = QUERIES[name](spark, sf)
    rows = df.collect()
    if name in ORACLES:
        want = duck.sql(ORACLES[name])
        order = sorted(df.columns)
        assert order == sorted(want.columns)
        got = sorted(tuple(str(r[c]) for c in order) for r in rows)
        place = [want.columns.index(c) for c in order]
        assert got == sorted(tuple(str(r[k]) for k in place) for r in want.fetchall())


def test_every_bit_changes_the_skeleton(spark, sf):
    log = logsynth.query_log(spark, sf).where("klass = 'SELECT'")
    assert log.select(skeleton.fingerprint(F.col("sql"))).distinct().count() == log.select("fam", "v").distinct().count() == 346


def test_scan_reads_what_it_needs(spark, sf):
    df = spark.read.parquet(f"{sf}/events.parquet").where("ts >= timestamp '2024-01-05 00:00:00'").groupBy("event_type").count()
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(ts), GreaterThanOrEqual(ts" in plan and "ReadSchema: struct<ts:timestamp_ntz,event_type:string>" in plan


def test_fingerprints_stay_in_the_jvm(spark, sf):
    plan = skeleton.skeleton_bag(logsynth.query_log(spark, sf))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and plan.count("HashAggregate") + plan.count("ObjectHashAggregate") + plan.count("SortAggregate") >= 2
