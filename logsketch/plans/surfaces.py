"""Sources, sinks and user functions as queries with oracles."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import grammar, skeleton
from ..sources import files, logsynth
from ..tables import shared_folder, table
from .dialect import with_log

ORACLES: dict[str, str] = {}


def oracle(sql: str, log: bool = False):
    def wrap(f):
        ORACLES[f.__name__] = with_log(sql) if log else sql
        return f

    return wrap


def _folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/logsketch-{uuid.uuid4().hex}"


def _log(spark, sf_dir) -> DataFrame:
    return table(logsynth.query_log(spark, sf_dir), "log")


_FORMATS = ("parquet", "orc", "json", "csv", "text")


@oracle("SELECT f AS fmt, count(*) AS n FROM log, (VALUES " + ", ".join(f"('{f}')" for f in _FORMATS) + ") v(f) GROUP BY f", log=True)
def op_scan_formats(spark, sf_dir):
    log, out = _log(spark, sf_dir), None
    for fmt in _FORMATS:
        path = f"{_folder(spark)}/{fmt}"
        files.write_log(log, path, fmt)
        got = files.read_log(spark, path, fmt).agg(F.count("*").alias("n")).select(F.lit(fmt).alias("fmt"), "n")
        out = got if out is None else out.unionByName(got)
    return out


@oracle("SELECT count(*) AS n FROM log WHERE cast(ts AS date) = date '2024-01-05'", log=True)
def op_partitioned_sink(spark, sf_dir):
    path = f"{_folder(spark)}/days"
    files.write_log(_log(spark, sf_dir), path, by_day=True)
    return spark.read.parquet(path).where("day = date '2024-01-05'").agg(F.count("*").alias("n"))


@oracle("SELECT o_orderstatus, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderstatus")
def op_bucketed_sink(spark, sf_dir):
    """Both sides in buckets of the key: the join needs no exchange."""
    names = []
    for t, key in (("orders", "o_orderkey"), ("lineitem", "l_orderkey")):
        names.append(f"logsketch_{t}_{uuid.uuid4().hex}")
        spark.read.parquet(f"{sf_dir}/{t}.parquet").write.bucketBy(8, key).sortBy(key).option("path", f"{_folder(spark)}/{t}").saveAsTable(names[-1])
    o, li = (spark.table(n) for n in names)
    return o.hint("merge").join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


def op_statement_source(spark, sf_dir):
    spark.dataSource.register(files.StatementSource)
    return spark.read.format("statementlog").load(f"{sf_dir}/supplier.parquet")


@oracle("SELECT user_id, k AS event_type, n FROM (SELECT user_id, event_type AS k, count(*) AS n FROM events GROUP BY 1, 2) t")
def op_unpivot(spark, sf_dir):
    kinds = ["click", "error", "purchase", "signup", "view"]
    wide = spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("user_id").pivot("event_type", kinds).count()
    return wide.unpivot("user_id", kinds, "event_type", "n").where("n is not null")


@oracle("SELECT stmt_id, cast(length(sql) - length(replace(sql, ' ', '')) AS bigint) AS spaces FROM log", log=True)
def op_udf_arrow(spark, sf_dir):
    @F.pandas_udf("long")
    def spaces(s: pd.Series) -> pd.Series:
        return s.str.count(" ")

    return _log(spark, sf_dir).select("stmt_id", spaces("sql").alias("spaces"))


@oracle("SELECT event_type, round(max(value) - min(value), 6) AS spread FROM events GROUP BY event_type")
def op_udaf_pandas(spark, sf_dir):
    @F.pandas_udf("double")
    def spread(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("event_type").agg(F.round(spread("value"), 6).alias("spread"))


@oracle("SELECT stmt_id, cast(len(string_split(sql, ' ')) AS int) AS n FROM log WHERE klass IN ('DELETE', 'UNION')", log=True)
def op_udtf_tokens(spark, sf_dir):
    @F.udtf(returnType="n int")
    class CountTokens:
        def eval(self, sql: str):
            yield (len(sql.split(" ")),)

    spark.udtf.register("count_tokens", CountTokens)
    _log(spark, sf_dir).createOrReplaceTempView("logsketch_log")
    return spark.sql("SELECT stmt_id, n FROM logsketch_log, LATERAL count_tokens(sql) WHERE klass IN ('DELETE', 'UNION')")


@oracle("SELECT user_id, count(*) AS n, min(event_id) AS first_event FROM events GROUP BY user_id")
def op_apply_pandas(spark, sf_dir):
    def one(f: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"user_id": [f["user_id"].iloc[0]], "n": [len(f)], "first_event": [f["event_id"].min()]})

    return spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", "event_id").groupBy("user_id").applyInPandas(one, "user_id long, n long, first_event long")


@oracle("SELECT coalesce(a.user_id, b.user_id) AS user_id, coalesce(a.n, 0) AS errors, coalesce(b.n, 0) AS signups FROM (SELECT user_id, count(*) AS n FROM events WHERE event_type = 'error' GROUP BY 1) a FULL JOIN (SELECT user_id, count(*) AS n FROM events WHERE event_type = 'signup' GROUP BY 1) b ON a.user_id = b.user_id")
def op_cogroup(spark, sf_dir):
    e = spark.read.parquet(f"{sf_dir}/events.parquet").select("user_id", "event_type")

    def both(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"user_id": [key[0]], "errors": [len(a)], "signups": [len(b)]})

    return e.where("event_type = 'error'").groupBy("user_id").cogroup(e.where("event_type = 'signup'").groupBy("user_id")).applyInPandas(both, "user_id long, errors long, signups long")


def op_parse_noise(spark, sf_dir):
    """Prose and web pages through the parser: every text gets a reason, none fails."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(F.col("doc_id").alias("tree_id"), F.col("text").alias("sql"))
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select(F.col("page_id").alias("tree_id"), F.col("html").alias("sql"))
    return grammar.parse_statements(docs.unionByName(pages)).where("node_id < 0").groupBy(F.col("atom").alias("reason")).agg(F.count("*").alias("n"))


@oracle("SELECT count(*) AS n FROM log WHERE klass IN ('SELECT')", log=True)
def op_sql_functions(spark, sf_dir):
    """The functions that register() offers to SQL."""
    register(spark)
    _log(spark, sf_dir).createOrReplaceTempView("logsketch_log")
    return spark.sql("SELECT count(*) AS n FROM logsketch_log WHERE statement_root(sql) = 'SELECT'")


def register(spark: SparkSession) -> None:
    """statement_root(sql), skeleton_text(sql) and the table function parse_nodes(sql)."""

    def root(sql: str | None) -> str | None:
        try:
            return grammar.parse(sql).atom
        except grammar.Rejected:
            return None

    @F.pandas_udf("string")
    def statement_root(s: pd.Series) -> pd.Series:
        return s.map(root)

    @F.udtf(returnType="node_id int, parent_id int, child_idx int, atom string, is_const boolean, height int, last_desc int")
    class ParseNodes:
        def eval(self, sql: str):
            try:
                yield from grammar.rows(grammar.parse(sql))
            except grammar.Rejected:
                return

    spark.udf.register("statement_root", statement_root)
    spark.udtf.register("parse_nodes", ParseNodes)


def skeleton_text(sql):
    return skeleton.fingerprint(sql)


def queries() -> dict:
    return {k: f for k, f in globals().items() if k.startswith("op_")}
