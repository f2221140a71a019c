"""Logs and tables from files and back, and a reader that yields parsed statements."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

LOG = "stmt_id long, ts timestamp, user_id long, sql string"


def read_log(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = LOG) -> DataFrame:
    """A statement log; text files have one statement a line and no other column."""
    if fmt == "text":
        return spark.read.text(path).select(F.monotonically_increasing_id().alias("stmt_id"), F.lit(None).cast("timestamp").alias("ts"), F.lit(None).cast("long").alias("user_id"), F.col("value").alias("sql"))
    return spark.read.format(fmt).schema(schema).load(path)


def write_log(log: DataFrame, path: str, fmt: str = "parquet", by_day: bool = False) -> None:
    out = log.select("stmt_id", log["ts"].cast("timestamp").alias("ts"), "user_id", "sql")
    if fmt == "text":
        out.select(F.regexp_replace("sql", r"[\r\n]+", " ").alias("value")).write.mode("overwrite").text(path)
    elif by_day:
        out.withColumn("day", F.to_date("ts")).write.mode("overwrite").partitionBy("day").format(fmt).save(path)
    else:
        out.write.mode("overwrite").format(fmt).save(path)


def read_stream(spark: SparkSession, path: str, schema, files: int = 4) -> DataFrame:
    """A folder of Parquet files as a stream; streams need an explicit schema."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


class StatementSource(DataSource):
    """format("statementlog"): a look-up for each row of a Parquet table of suppliers, parsed as it is read. Option: path."""

    @classmethod
    def name(cls) -> str:
        return "statementlog"

    def schema(self) -> str:
        return "stmt_id long, sql string, root string, n_nodes int"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])


class _Reader(DataSourceReader):
    ROWS = 10_000  # of one partition

    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        import pyarrow.dataset as ds

        return [InputPartition((f.path, a)) for f in ds.dataset(self.path, format="parquet").get_fragments() for a in range(0, f.count_rows(), self.ROWS)]

    def read(self, partition):
        import pyarrow.parquet as pq

        from logsketch.functions import grammar

        path, first = partition.value
        for k, balance in zip(*(c.to_pylist() for c in pq.read_table(path, columns=["s_suppkey", "s_acctbal"]).slice(first, self.ROWS).columns), strict=True):
            sql = f"SELECT s_name FROM supplier WHERE s_suppkey = {k}" + (f" AND s_acctbal > {abs(int(balance or 0))}" if k % 3 == 0 else "")
            tree = grammar.parse(sql)
            yield k, sql, tree.atom, len(list(grammar.rows(tree)))
