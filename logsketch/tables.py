"""Tables in the folder that driver and executors share, and checked size bounds."""

from __future__ import annotations

import atexit
import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

from .session import ship

_written: list[tuple[SparkSession, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or where it is unset and the master is local (tests), an own one."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not folder:
        folder = spark.sparkContext.getCheckpointDir()
    if not folder:
        master = spark.sparkContext.master
        if not (master.startswith("local") and not master.startswith("local-cluster")):
            raise RuntimeError("spark.checkpoint.dir is not set: on a cluster, driver and executors need a folder that they share")
        folder = tempfile.mkdtemp(prefix="logsketch-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _clear() -> None:
    for spark, path in _written:
        try:
            _delete(spark, path)
        except Exception:  # the session has ended; the folder's owner clears it
            return


def table(df: DataFrame, what: str, per_file: int = 0) -> DataFrame:
    """Writes df as Parquet in the shared folder and reads it again: lineage ends here, and a lost executor costs nothing before it.

    per_file: most rows of a file. Spark decodes thousands of rows of one file at once, too many where rows are large."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/logsketch-{uuid.uuid4().hex}/{what}"
    df.write.option("maxRecordsPerFile", per_file).parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def sweep(spark: SparkSession) -> None:
    """Lets Spark's cleaner delete shuffle files that nothing refers to any more, before the next large step needs room."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def release(*dfs: DataFrame) -> None:
    """Deletes tables written by table() that no later step reads."""
    for df in dfs:
        for name in df.inputFiles()[:1]:
            folder = name.rsplit("/", 1)[0]
            for k, (spark, path) in enumerate(_written):
                if folder.endswith(path.removeprefix("file://").removeprefix("file:")):
                    _delete(spark, path)
                    del _written[k]
                    break


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return ship(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def bounded_bytes(df: DataFrame, limit: int) -> bool:
    """Whether the optimizer's size of df (file sizes, not a guess about rows) is at most limit."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) <= limit
