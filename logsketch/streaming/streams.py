"""The log as a stream of events: windows, late rows, repeats, joins, and structures seen for the first time.

Every query drains its source (availableNow) into a table in the shared folder and returns that table, so that a
batch query over the same rows is its oracle. State lives in the checkpoint beside it: a restart goes on from there.
"""

from __future__ import annotations

import time
import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import skeleton as sk
from ..plans.dialect import DUCK, with_log
from ..sources import logsynth
from ..sources.files import read_stream
from ..tables import shared_folder

ORACLES: dict[str, str] = {}


def oracle(sql: str, log: bool = False):
    def wrap(f):
        ORACLES[f.__name__] = with_log(sql) if log else sql
        return f

    return wrap


def events(spark: SparkSession, sf_dir: str, parts: int = 4) -> DataFrame:
    """The events table as a stream of a few files that arrive in time order: each is written by a job of its own."""
    folder = f"{shared_folder(spark)}/logsketch-{uuid.uuid4().hex}/events"
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))  # event time has a zone
    cuts = rows.agg(F.percentile_approx("ts", [k / parts for k in range(1, parts)])).first()[0] or []
    edges = [None, *cuts, None]
    for k, (low, high) in enumerate(zip(edges[:-1], edges[1:], strict=True)):
        some = rows.where(F.col("ts") > F.lit(low)) if low is not None else rows.where(F.col("ts").isNull() | (F.col("ts") <= F.lit(high))) if high is not None else rows
        some = some.where(F.col("ts").isNull() | (F.col("ts") <= F.lit(high))) if high is not None else some
        some.coalesce(1).write.mode("append").parquet(folder)
        time.sleep(0.02)  # a store's clock may count in milliseconds; files are read in the order of their times
    return read_stream(spark, folder, rows.schema, files=1)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream to the end of its source; complete and update results keep each key's last row."""
    spark = stream.sparkSession
    base = f"{shared_folder(spark)}/logsketch-{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{base}/out").start().awaitTermination()
    else:
        writer.foreachBatch(lambda batch, k: batch.write.mode("overwrite").parquet(f"{base}/out")).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


def _windowed(spark, sf_dir, window) -> DataFrame:
    counted = events(spark, sf_dir).groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drain(counted, "complete").select(F.unix_timestamp("w.start").alias("start_s"), "event_type", "n")


@oracle("SELECT cast(floor(epoch(ts) / 86400) * 86400 AS bigint) AS start_s, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def st_tumbling(spark, sf_dir):
    return _windowed(spark, sf_dir, F.window("ts", "1 day"))


@oracle("SELECT cast(floor(epoch(ts) / 43200) * 43200 AS bigint) - o.o AS start_s, event_type, count(*) AS n FROM events, (VALUES (0), (43200)) o(o) GROUP BY 1, 2")
def st_sliding(spark, sf_dir):
    return _windowed(spark, sf_dir, F.window("ts", "1 day", "12 hours"))


@oracle("WITH g AS (SELECT user_id, ts, CASE WHEN epoch(ts) - lag(epoch(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 86400 THEN 0 ELSE 1 END AS s FROM events), z AS (SELECT user_id, sum(s) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, cast(k AS bigint) AS session, count(*) AS n FROM z GROUP BY user_id, k")
def st_session(spark, sf_dir):
    """Gaps of a day end a session; sessions are numbered afterwards."""
    from pyspark.sql import Window

    rows = drain(events(spark, sf_dir).groupBy(F.session_window("ts", "1 day").alias("w"), "user_id").agg(F.count("*").alias("n")), "complete")
    return rows.select("user_id", F.row_number().over(Window.partitionBy("user_id").orderBy("w.start")).cast("long").alias("session"), "n")


@oracle("SELECT cast(floor(epoch(ts) / 21600) * 21600 AS bigint) AS start_s, count(*) AS n FROM events GROUP BY 1 HAVING cast(floor(epoch(ts) / 21600) * 21600 AS bigint) + 21600 <= (SELECT max(epoch(ts)) - 7200 FROM events)")
def st_late_data(spark, sf_dir):
    """Windows closed by a watermark, each appended once; those that it has not reached at the end are not there."""
    counted = events(spark, sf_dir).withWatermark("ts", "2 hours").groupBy(F.window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return drain(counted, "append").select(F.unix_timestamp("w.start").alias("start_s"), "n")


@oracle("SELECT event_id, event_type FROM events")
def st_dedup(spark, sf_dir):
    """Every event sent twice; repeats within the watermark are dropped."""
    twice = events(spark, sf_dir).select("event_id", "event_type", "ts", F.explode(F.array(F.lit(1), F.lit(2))).alias("sent"))
    return drain(twice.withWatermark("ts", "30 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type"))


@oracle("SELECT klass, count(*) AS n FROM log WHERE user_id IN (SELECT c_custkey FROM customer) GROUP BY klass", log=True)
def st_static_join(spark, sf_dir):
    """The streamed log beside a table that stands still."""
    known = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"))
    return drain(logsynth.project(events(spark, sf_dir)).join(known, "user_id", "left_semi").groupBy("klass").agg(F.count("*").alias("n")), "complete")


@oracle("SELECT s.event_id AS signup, e.event_id AS error FROM events s JOIN events e ON s.user_id = e.user_id AND s.event_type = 'signup' AND e.event_type = 'error' AND e.ts > s.ts AND e.ts <= s.ts + interval 6 hours")
def st_stream_join(spark, sf_dir):
    """Errors within six hours of the same user's signup, stream against stream, with bounded state."""
    source = events(spark, sf_dir)
    s = source.where("event_type = 'signup'").select(F.col("event_id").alias("signup"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", "1 day")
    e = source.where("event_type = 'error'").select(F.col("event_id").alias("error"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", "1 day")
    return drain(s.join(e, F.expr("u1 = u2 AND t2 > t1 AND t2 <= t1 + interval 6 hours")).select("signup", "error"))


def _first_seen(key, frames, state: GroupState):
    """A structure's first sight is reported once, while its state lives."""
    n = sum(len(f) for f in frames)
    if state.hasTimedOut:
        state.remove()
        return
    new = not state.exists
    state.update((n + (0 if new else state.get[0]),))
    if new:
        yield pd.DataFrame({"skel_text": [key[0]]})


@oracle(f"SELECT DISTINCT {DUCK.fp('sql')} AS skel_text FROM log WHERE klass = 'SELECT'", log=True)
def st_new_skeletons(spark, sf_dir):
    log = logsynth.project(events(spark, sf_dir)).where("klass = 'SELECT'").select(sk.fingerprint(F.col("sql")).alias("skel_text"))
    return drain(log.groupBy("skel_text").applyInPandasWithState(_first_seen, "skel_text string", "n long", "append", GroupStateTimeout.NoTimeout))


@oracle(f"SELECT {DUCK.fp('sql')} AS skel_text, count(*) AS n_stmt FROM log WHERE klass = 'SELECT' GROUP BY 1", log=True)
def st_foreach_dict(spark, sf_dir):
    """Micro-batches appended under their batch number: a repeated batch replaces itself, so restarts change nothing."""
    base = f"{shared_folder(spark)}/logsketch-{uuid.uuid4().hex}"
    log = logsynth.project(events(spark, sf_dir)).where("klass = 'SELECT'").select(sk.fingerprint(F.col("sql")).alias("skel_text"))

    def upsert(batch: DataFrame, k: int) -> None:
        batch.groupBy("skel_text").agg(F.count("*").alias("n")).write.mode("overwrite").parquet(f"{base}/dict/batch={k}")

    log.writeStream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(upsert).start().awaitTermination()
    return spark.read.schema("skel_text string, n long, batch int").parquet(f"{base}/dict").groupBy("skel_text").agg(F.sum("n").alias("n_stmt"))


def queries() -> dict:
    return {k: f for k, f in globals().items() if k.startswith("st_")}
