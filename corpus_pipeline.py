"""Documents to packed sequences: language ID, line dedup, near-dedup, decontamination, packing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes it as Parquet in the shared folder and
reads it for the next. All but the last keep the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from logsketch.llm import decontaminate, language, line_dedup, near_dedup, packing
from logsketch.llm.common import read, release, table
from logsketch.llm.sketch import parted
from logsketch.session import ship

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language can be told; rows and columns stay as they are."""
    ship(spark)
    docs = docs.select(*COLUMNS)
    # What is judged depends on these columns only. Rows go by 128 bits of them, so that no text is written before the result.
    judged = [x for c in ("text", "lang", "source") for x in (F.col(c).isNull(), F.col(c))]
    digests = [F.xxhash64(F.lit(k), *judged).alias(f"_d{k}") for k in (1, 2)]
    rows = language.identify(docs.select("text", "lang", "source", *digests), keep_text=False)
    gone = table(rows.where(~F.coalesce("accepted", F.lit(False))).select("_d1", "_d2").distinct(), "rejected")
    stay, some = parted(docs, F.xxhash64(F.lit(1), *judged), gone.select("_d1"))
    some = some.select(*COLUMNS, *digests).join(gone, ["_d1", "_d2"], "left_anti").select(*COLUMNS)
    return stay.unionByName(some)


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that repeat earlier ones are cut; documents of which nothing is left go. n_chars follows the text."""
    ship(spark)
    docs = docs.select(*COLUMNS)
    cut = line_dedup.without_lines(docs, line_dedup.repeated_lines(docs))
    cut = cut.where((F.col("n_removed") == 0) | (F.trim("text") != ""))
    n_chars = F.when(F.col("n_removed") == 0, F.col("n_chars")).otherwise(F.length("text"))
    return cut.withColumn("n_chars", n_chars.cast(docs.schema["n_chars"].dataType)).select(*COLUMNS)


def dedup_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays, that with the smallest doc_id, in one row."""
    ship(spark)
    docs = docs.select(*COLUMNS)
    per = near_dedup.near_duplicates(docs).groupBy("doc_id").agg(F.max("kept").alias("kept"), F.count("*").alias("n"))
    # All but these stay as they are, without being shuffled: documents that go, and those that have several rows.
    open_ = table(per.where("not kept or n > 1").select("doc_id", "kept"), "open")
    stay, some = parted(docs, F.xxhash64(F.col("doc_id").cast("long")), open_.select(F.xxhash64("doc_id")))
    gone = open_.where("not kept").select(F.col("doc_id").alias("_gone"))
    some = some.join(gone, F.col("doc_id") == F.col("_gone"), "left_anti").dropDuplicates(["doc_id", "text"])
    return stay.unionByName(some)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    ship(spark)
    docs = docs.select(*COLUMNS)
    return decontaminate.decontaminate(docs, read(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces and the sequences that they lie in."""
    ship(spark)
    return packing.pack(docs)


STAGES = [("language_id", identify_language), ("line_dedup", dedup_lines), ("minhash_near_dedup", dedup_near), ("benchmark_decontamination", drop_benchmark), ("best_fit_packing", pack)]

#: SQL cannot express the language model, the set joins and the tokenizer; tests/llm holds brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    before = None
    for name, stage in STAGES[:-1]:
        docs = table(stage(spark, docs, sf_dir), name)
        if before is not None:
            release(before)
        before = docs
    return STAGES[-1][1](spark, docs, sf_dir)
