"""Deterministic identifiers of lists, bags and sets of identifiers, and the table that gives them dense numbers."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..tables import table


def _digest(tag: str, items: Column) -> Column:
    return F.sha2(F.concat(F.lit(f"{tag}("), F.array_join(items, ","), F.lit(")")), 256)


def list_digest(items: Column) -> Column:
    """Respects order and multiplicity."""
    return _digest("L", items)


def bag_digest(items: Column) -> Column:
    """Respects multiplicity only."""
    return _digest("B", F.array_sort(items))


def set_digest(items: Column) -> Column:
    """Respects neither."""
    return _digest("S", F.array_sort(F.array_distinct(items)))


def key(tag: str, items) -> str:
    """The same identifiers outside Spark."""
    items = list(items) if tag == "L" else sorted(items) if tag == "B" else sorted(set(items))
    return hashlib.sha256(f"{tag}({','.join(items)})".encode()).hexdigest()


class FeatureDict:
    """feature_key -> dense feature_id; appended to, never renumbered. Identity is content, so re-runs change nothing."""

    def __init__(self, rows: DataFrame | None = None):
        self.rows = rows

    def extend(self, features: DataFrame) -> FeatureDict:
        """features (feature_key, canonical): new keys get the next numbers in key order, without one task seeing all.

        Keys are range-partitioned and numbered within partitions; partition sizes (one row each) give the offsets."""
        new = features.groupBy("feature_key").agg(F.min("canonical").alias("canonical"))
        start = 0
        if self.rows is not None:
            new = new.join(self.rows.select("feature_key"), "feature_key", "left_anti")
            start = (self.rows.agg(F.max("feature_id")).first()[0] + 1) if self.rows.limit(1).count() else 0
        ranged = new.repartitionByRange("feature_key").sortWithinPartitions("feature_key").withColumn("_m", F.monotonically_increasing_id())
        ranged = table(ranged.withColumn("_p", F.shiftright("_m", 33).cast("int")).withColumn("_i", F.expr("_m & 8589934591")), "new-features")
        sizes = {r["_p"]: r["count"] for r in ranged.groupBy("_p").count().collect()}  # one row for each partition
        offsets, total = [], start
        for p in sorted(sizes):
            offsets.append((p, total))
            total += sizes[p]
        spark = features.sparkSession
        at = spark.createDataFrame(offsets or [(-1, 0)], "_p int, _o long")
        numbered = ranged.join(F.broadcast(at), "_p").select("feature_key", (F.col("_i") + F.col("_o")).alias("feature_id"), "canonical", F.lit(False).alias("unwanted"))
        return FeatureDict(numbered if self.rows is None else self.rows.unionByName(numbered))

    def mark_unwanted(self, condition: Column) -> FeatureDict:
        """Features that no bag gets any more."""
        return FeatureDict(self.rows.withColumn("unwanted", F.col("unwanted") | F.coalesce(condition, F.lit(False))))

    def assert_unique(self) -> None:
        twice = self.rows.groupBy("feature_key").count().where("count > 1").limit(1).count() + self.rows.groupBy("feature_id").count().where("count > 1").limit(1).count()
        if twice:
            raise AssertionError("an identifier was given twice")
