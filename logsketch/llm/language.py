"""Language by Bayesian evidence fusion: what the text says, what is declared, and where it comes from.

Text likelihoods come from byte trigrams counted over all rows under their declared language. Hosts have priors by
grouped aggregation, each level smoothed towards the one above: host, its domain, its address suffix, all rows.
A declared language is evidence with a known rate of error. Rows are rejected only when the text holds no letters, no
language reaches half of the belief, or hardly any of its trigrams is likelier than chance in any language.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textkernel as K
from .common import bounded_bytes, lean, small_batches, table
from .sketch import count_sketch

GRAMS = 1 << 16
ROWS = 20  # declared rows that are enough for a model of a language, however many other rows there are
SHARE = 0.001  # of all declarations: enough as well, where all rows are few
TEMPER = 0.25  # neighbouring trigrams overlap, so their evidence counts for less
WRONG = 0.05  # rate of wrong declarations
PLAUSIBLE = 0.2  # of the trigrams of a text in some language
WEIGHT = 20.0  # rows that a level's prior weighs at the level below
SMOOTH = 0.5
PRIORS_BYTES = 32 << 20
ADDED = ("language", "posterior", "accepted", "text_language")
_fold = K._fold.astype(np.uint32)
_LETTER = np.zeros(256, bool)
_LETTER[0x41:0x5B] = _LETTER[0x61:0x7B] = _LETTER[0x80:] = True


def trigrams(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Cells of all byte trigrams that lie in one row and hold a letter, and the row of each."""
    n = len(data)
    if n < 3:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    x = _fold[data]
    cell = ((x[:-2] * np.uint32(0x9E3779B1)) ^ (x[1:-1] * np.uint32(0x85EBCA77)) ^ (x[2:] * np.uint32(0xC2B2AE3D))) >> np.uint32(16)
    letter = _LETTER[data]
    ok = letter[:-2] | letter[1:-1] | letter[2:]
    border = offsets[1:-1]
    for d in (1, 2):
        at = border - d
        ok[at[(at >= 0) & (at < n - 2)]] = False
    at = np.flatnonzero(ok)
    size = np.diff(np.searchsorted(at, offsets))
    return cell[at].astype(np.int64), np.repeat(np.arange(len(size)), size)


def _keys(languages: list[str]):
    index = {x: k for k, x in enumerate(languages)}

    def keys(batch: pa.RecordBatch) -> Iterator[np.ndarray]:
        said = np.array([index.get(x, -1) for x in batch.column("_said").to_pylist()], np.int64)
        for first, data, offsets in K.blocks(batch.column("_text")):
            cell, row = trigrams(data, offsets)
            lang = said[first + row]
            yield (lang * GRAMS + cell)[lang >= 0].astype(np.uint64)

    return keys


def _likelihoods(shared, n: int):
    def run(batches):
        logs = shared.value
        likely = logs.max(axis=0) > -np.log(GRAMS)
        for batch in batches:
            size, good, letters, out = [], [], [], []
            for _, data, offsets in K.blocks(batch.column("_text")):
                cell, row = trigrams(data, offsets)
                rows = len(offsets) - 1
                size.append(np.bincount(row, minlength=rows))
                good.append(np.bincount(row[likely[cell]], minlength=rows))
                held = np.concatenate([[0], np.cumsum(_LETTER[data])])
                letters.append(held[offsets[1:]] - held[offsets[:-1]])
                out.append(np.stack([np.bincount(row, weights=logs[k][cell], minlength=rows) for k in range(n)], axis=1).astype(np.float64))
            size, good, letters = (np.concatenate(x).astype(np.int64) if x else np.zeros(0, np.int64) for x in (size, good, letters))
            flat = np.concatenate(out).ravel() if out else np.zeros(0)
            ll = pa.ListArray.from_arrays(pa.array(np.arange(len(size) + 1, dtype=np.int32) * n), pa.array(flat))
            kept = [c for c in batch.schema.names if c not in ("_text",)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(size), pa.array(good), pa.array(letters), ll], names=[*kept, "_grams", "_good", "_letters", "_ll"])

    return run


def _levels(host):
    """Host, its last two labels, its last label."""
    labels = F.split(host, r"\.")
    return host, F.when(F.size(labels) > 1, F.concat_ws(".", F.slice(labels, -2, 2))), F.when(F.size(labels) > 1, F.element_at(labels, -1))


def host_priors(rows: DataFrame, languages: list[str]) -> DataFrame:
    """rows (_host, _best: place of the language that the text says) -> _host, _prior: smoothed shares, one for each language."""
    n = len(languages)
    counts = F.array(*(F.sum(F.when(F.col("_best") == k, 1.0).otherwise(0.0)) for k in range(n)))
    host, domain, suffix = _levels(F.col("_host"))
    per = rows.where("_host is not null").groupBy("_host").agg(counts.alias("_c"))
    per = table(per.withColumn("_domain", domain).withColumn("_suffix", suffix), "host-counts")

    def total(level: str) -> DataFrame:
        sums = F.array(*(F.sum(F.col("_c")[k]) for k in range(n)))
        return per.groupBy(F.col(level).alias(f"{level}_key")).agg(sums.alias(f"{level}_c")).where(F.col(f"{level}_key").isNotNull())

    everything = per.agg(F.array(*(F.coalesce(F.sum(F.col("_c")[k]), F.lit(0.0)) for k in range(n)))).first()[0]
    base = (np.array(everything) + 1) / (sum(everything) + n)
    smooth = lambda c, above: F.when(c.isNull(), above).otherwise(F.zip_with(c, above, lambda x, p: (x + WEIGHT * p) / (F.aggregate(c, F.lit(0.0), lambda a, b: a + b) + WEIGHT)))
    out = per.join(total("_domain"), F.col("_domain") == F.col("_domain_key"), "left").join(total("_suffix"), F.col("_suffix") == F.col("_suffix_key"), "left")
    top = F.array(*(F.lit(float(x)) for x in base))
    out = out.withColumn("_p1", smooth(F.col("_suffix_c"), top))
    out = out.withColumn("_p2", smooth(F.col("_domain_c"), F.col("_p1")))
    return out.select("_host", smooth(F.col("_c"), F.col("_p2")).alias("_prior"), F.lit(True).alias("_known"))


def identify(docs: DataFrame, text: str = "text", declared: str | None = "lang", host: str | None = "source", url: str | None = None, languages: list[str] | None = None, keep_text: bool = True) -> DataFrame:
    """docs with language, posterior, accepted, text_language added (keep_text=False drops the text).

    declared: column of declared languages (case and region are ignored), or None. host: column of hosts or sources;
    url: column of addresses whose host is used where `host` is None. A null in any of them is no evidence. Null text
    is empty: no letters, hence rejected, with the prior's language. Repeated rows and ties: equal rows get equal
    results; of equally believed languages the first by name. Without any declared language there is nothing to learn
    from: language is null and nothing is accepted. Every language that ROWS rows declare has a model, or SHARE of the
    declarations where these are fewer; a rarer one is the row's language, accepted with posterior 1 - WRONG, where the
    row would be rejected otherwise and holds letters. Columns of docs keep their names, whatever these are; only those
    with an added name are replaced.
    """
    spark = docs.sparkSession
    docs = docs.drop(*ADDED)
    kept = [c for c in docs.columns if keep_text or c != text]
    said = F.lower(F.split(F.col(declared).cast("string"), "[-_]")[0]) if declared else F.lit(None).cast("string")
    where = F.lower(F.col(host).cast("string")) if host else F.lower(F.regexp_extract(F.col(url).cast("string"), r"://([^/?#]*)", 1)) if url else F.lit(None).cast("string")
    # The columns of docs go along as one, so that no name of theirs can clash.
    own = F.struct(*(F.col(f"`{c}`") for c in kept)) if kept else F.struct(F.lit(None).cast("int").alias("none"))
    rows = docs.select(own.alias("_row"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("_text"), said.alias("_said"), where.alias("_host"))
    if languages is None:
        per = table(rows.where("_said is not null").groupBy("_said").count(), "declared") if declared else None
        total = per.agg(F.sum("count")).first()[0] or 0 if declared else 0
        languages = sorted(r["_said"] for r in per.where(F.col("count") >= min(ROWS, SHARE * total)).select("_said").collect()) if declared else []  # one row for each modelled language
    if not languages:
        return docs.select(*(F.col(f"`{c}`") for c in kept)).withColumn("language", F.lit(None).cast("string")).withColumn("posterior", F.lit(0.0)).withColumn("accepted", F.lit(False)).withColumn("text_language", F.lit(None).cast("string"))
    n = len(languages)
    cells = 1 << (n * GRAMS - 1).bit_length()
    with small_batches(spark):
        counts = count_sketch(rows.select("_text", "_said"), cells, _keys(languages))[: n * GRAMS].reshape(n, GRAMS)
    shared = spark.sparkContext.broadcast(np.log((counts + SMOOTH) / (counts.sum(axis=1, keepdims=True) + SMOOTH * GRAMS)))

    best = F.expr("array_position(_ll, array_max(_ll)) - 1").cast("int")

    schema = T.StructType([f for f in rows.schema if f.name != "_text"] + [T.StructField(x, T.LongType()) for x in ("_grams", "_good", "_letters")] + [T.StructField("_ll", T.ArrayType(T.DoubleType()))])
    # Texts are scored once; all that follows reads the scores from a table.
    with small_batches(spark):
        scored = table(rows.mapInArrow(lean(_likelihoods(shared, n)), schema).withColumn("_best", F.when(F.col("_grams") > 0, best)), "scored")
    shared.destroy()
    priors = table(host_priors(scored.select("_best", "_host"), languages), "hosts")
    if bounded_bytes(priors, PRIORS_BYTES):
        priors = F.broadcast(priors)
    out = scored.withColumnRenamed("_host", "_where").join(priors, F.col("_where") == F.col("_host"), "left")
    names = F.array(*map(F.lit, languages))
    prior = F.coalesce("_prior", F.array(*[F.lit(1.0 / n)] * n))
    declared_known = F.array_contains(names, F.col("_said"))
    log_said = F.transform(names, lambda x: F.when(F.col("_said").isNull() | ~declared_known, 0.0).when(x == F.col("_said"), float(np.log(1 - WRONG))).otherwise(float(np.log(WRONG / max(1, n - 1)))))
    belief = F.zip_with(F.zip_with(F.transform("_ll", lambda x: x * TEMPER), F.transform(prior, lambda p: F.log(p)), lambda a, b: a + b), log_said, lambda a, b: a + b)
    out = out.withColumn("_belief", belief).withColumn("_top", F.array_max("_belief"))
    out = out.withColumn("language", F.element_at(names, F.array_position("_belief", F.col("_top")).cast("int")))
    out = out.withColumn("posterior", F.round(1 / F.aggregate(F.transform("_belief", lambda b: F.exp(b - F.col("_top"))), F.lit(0.0), lambda a, b: a + b), 9))
    accepted = (F.col("_letters") > 0) & (F.col("posterior") >= 0.5) & (F.col("_good") >= PLAUSIBLE * F.col("_grams"))
    # A declared language without a model of its own stands where no other is believed.
    rare = F.col("_said").isNotNull() & ~declared_known & (F.col("_letters") > 0) & ~accepted
    language = F.when(rare, F.col("_said")).otherwise(F.col("language")).alias("language")
    posterior = F.when(rare, F.lit(1 - WRONG)).otherwise(F.col("posterior")).alias("posterior")
    return out.select(*(F.col(f"_row.`{c}`").alias(c) for c in kept), language, posterior, (accepted | rare).alias("accepted"), F.element_at(names, F.col("_best") + 1).alias("text_language"))
