"""One query text for two engines: the few functions that Spark and DuckDB spell differently."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..functions import skeleton
from ..sources import logsynth

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


class Dialect:
    def __init__(self, spark: bool):
        self.spark = spark

    def pick(self, spark: str, duck: str) -> str:
        return spark if self.spark else duck

    def fp(self, x: str) -> str:
        if self.spark:
            return f"trim(regexp_replace(regexp_replace(regexp_replace({x}, r\"{skeleton.STRINGS}\", '?'), r'{skeleton.NUMBERS}', '?'), r'{skeleton.SPACES}', ' '))"
        return skeleton.fingerprint_sql(x)

    def epoch(self, x: str) -> str:
        return self.pick(f"unix_timestamp({x})", f"cast(floor(epoch({x})) AS bigint)")

    def items(self, x: str, distinct: bool = False) -> str:
        """Sorted values of a group as text."""
        if self.spark:
            return f"array_join(array_sort({'collect_set' if distinct else 'collect_list'}(cast({x} AS string))), ',')"
        return f"array_to_string(list_sort(list({'DISTINCT ' if distinct else ''}cast({x} AS string))), ',')"

    def sha(self, x: str) -> str:
        return self.pick(f"sha2({x}, 256)", f"sha256({x})")

    def words(self, x: str) -> str:
        return self.pick(f"split({x}, ' ')", f"string_split({x}, ' ')")

    def n(self, x: str) -> str:
        """Length of a list."""
        return self.pick(f"size({x})", f"cast(len({x}) AS int)")


SPARK, DUCK = Dialect(True), Dialect(False)
Text = Callable[[Dialect], str]


def with_log(body: str) -> str:
    """A query that may read the derived log as `log`."""
    log = f"log AS ({logsynth.log_sql()})"
    head = body.lstrip()
    if head.upper().startswith("WITH RECURSIVE"):
        return f"WITH RECURSIVE {log}, {head[len('WITH RECURSIVE') :]}"
    return f"WITH {log}, {head[5:]}" if head.upper().startswith("WITH ") else f"WITH {log} {head}"


def needs_log(body: str) -> bool:
    return " log" in body.replace("\n", " ")


def run(spark: SparkSession, sf_dir: str, text: Text) -> DataFrame:
    body = text(SPARK)
    body = with_log(body) if needs_log(body) else body
    for t in TABLES:
        if t in body:
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)
    return spark.sql(body)


def oracle(text: Text) -> str:
    body = text(DUCK)
    return with_log(body) if needs_log(body) else body
