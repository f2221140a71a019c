"""Addresses judged by rules, and where no rule fits, by a tree of path templates per host. DataFrame functions only.

Segments of a path that vary are generalised: by shape (numbers, long mixtures of letters and digits), and where a
host's node has many children that hardly repeat, to a wildcard. Sibling branches whose children and labels are
distributed like those of all their siblings together are one branch. A template is rejected when the share of
labelled addresses in it that are blocked, smoothed towards that of the same template on related hosts, reaches one half.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import bounded_bytes, table

LEVELS = 4  # segments of a path that the tree tells apart; what lies deeper counts as one
MANY, SPREAD = 8, 0.5  # a node with so many children, and so many for each row, varies
SIMILAR = 1.0  # branches are merged within this many root-mean-square deviations of their siblings
WEIGHT = 4.0  # labelled addresses that the prior weighs
BROADCAST_BYTES = 32 << 20
_UP, _LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

# The rules of the production query, (verdict, host, path).
RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)


def host_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z folded) and path of an address; both empty without ://."""
    url = F.coalesce(url.cast("string"), F.lit(""))
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(host) + 1, F.length(rest)), r"^[^?#]*", 0)
    return F.translate(host, _UP, _LOW), path


def by_rule(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits, as written, and its verdict; null where none does."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for what, h, p in sorted(rules, key=lambda r: len(r[1] + r[2])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        name, verdict = F.when(fits, F.lit(h + p)).otherwise(name), F.when(fits, F.lit(what)).otherwise(verdict)
    return name, verdict


def _shape(segment: Column) -> Column:
    """A segment by its shape, where the shape says that it varies."""
    stem, ending = F.regexp_extract(segment, r"^([^.]*)", 1), F.regexp_extract(segment, r"(\.[A-Za-z0-9]{1,5})$", 1)
    kind = F.when(stem.rlike(r"^[0-9]+$"), F.lit("#")).when(stem.rlike(r"^(?=.*[0-9])[0-9a-zA-Z_-]{8,}$"), F.lit("*")).when(F.length(stem) > 40, F.lit("*"))
    return F.when(kind.isNotNull(), F.concat(kind, ending)).otherwise(segment)


def templates(rows: DataFrame) -> DataFrame:
    """rows (.., _host, _path) -> the same with _t, an array of generalised segments for each level."""
    parts = F.filter(F.split(F.regexp_replace("_path", "^/", ""), "/"), lambda s: s != "")
    rows = rows.withColumn("_parts", F.concat(F.transform(F.slice(parts, 1, LEVELS), _shape), F.when(F.size(parts) > LEVELS, F.array(F.lit("**"))).otherwise(F.array().cast("array<string>"))))
    rows = rows.withColumn("_t", F.lit(""))
    for level in range(1, LEVELS + 1):
        here = F.try_element_at("_parts", F.lit(level))
        rows = rows.withColumn("_here", here)
        # Rows are summed by child before children are counted, so that a busy host costs one row for each child and task.
        child = rows.where(F.col("_here").isNotNull() & ~F.col("_here").rlike(r"^[#*]")).groupBy("_host", "_t", "_here").agg(F.count("*").alias("_n"))
        varied = child.groupBy("_host", "_t").agg(F.count("*").alias("_kinds"), F.sum("_n").alias("_rows")).where((F.col("_kinds") >= MANY) & (F.col("_kinds") >= SPREAD * F.col("_rows")))
        varied = table(varied.select(F.col("_host").alias("_vh"), F.col("_t").alias("_vt")), f"varied-{level}")
        varied = F.broadcast(varied) if bounded_bytes(varied, BROADCAST_BYTES) else varied
        rows = rows.join(varied, (F.col("_host") == F.col("_vh")) & (F.col("_t") == F.col("_vt")), "left")
        general = F.when(F.col("_vh").isNotNull() & ~F.col("_here").rlike(r"^[#*]"), F.lit("*")).otherwise(F.col("_here"))
        rows = rows.withColumn("_t", F.when(F.col("_here").isNull(), F.col("_t")).otherwise(F.concat("_t", F.lit("/"), general))).drop("_vh", "_vt")
    return rows.drop("_here", "_parts")


def _merged(rows: DataFrame) -> DataFrame:
    """Template counts by label -> for each (host, template) the branch that it is merged into."""
    stem = F.regexp_extract("_t", r"^(/[^/]*)", 1)
    child = F.substring(F.col("_t"), F.length(stem) + 1, F.length("_t"))
    counts = rows.groupBy("_host", "_t", F.coalesce("_label", F.lit("none")).alias("_label")).agg(F.count("*").alias("_n"))
    counts = table(counts.withColumn("_stem", stem).withColumn("_child", child), "template-counts")
    own = counts.groupBy("_host", "_stem", "_child", "_label").agg(F.sum("_n").alias("_n"))
    # Only branches whose labelled addresses have the same verdicts can be one.
    verdicts = F.array_join(F.array_sort(F.collect_set(F.when(F.col("_label") != "none", F.col("_label")))), "|")
    branch = own.groupBy("_host", "_stem").agg(F.sum("_n").alias("_bn"), verdicts.alias("_kind"))
    own = own.join(branch, ["_host", "_stem"])
    pooled = own.groupBy("_host", "_kind", "_child", "_label").agg(F.sum("_n").alias("_pn"))
    whole = branch.groupBy("_host", "_kind").agg(F.sum("_bn").alias("_hn"), F.count("*").alias("_stems"))
    kinds = pooled.groupBy("_host", "_kind").agg(F.count("*").alias("_kinds"))
    # Total variation = half the sum of differences; outcomes that a branch lacks add their pooled share.
    seen = own.join(pooled, ["_host", "_kind", "_child", "_label"]).join(whole, ["_host", "_kind"]).join(kinds, ["_host", "_kind"])
    share, pool = F.col("_n") / F.col("_bn"), F.col("_pn") / F.col("_hn")
    far = seen.groupBy("_host", "_stem", "_kind").agg((0.5 * (F.sum(F.abs(share - pool)) + 1 - F.sum(pool))).alias("_far"), F.first("_bn").alias("_bn"), F.first("_kinds").alias("_kinds"), F.first("_stems").alias("_stems"))
    like = (F.col("_stems") > 1) & (F.col("_far") <= SIMILAR * 0.5 * F.sqrt(F.col("_kinds") / F.col("_bn"))) & (F.col("_far") < 0.5)
    several = F.when(F.col("_kind") == "", F.lit("/*")).otherwise(F.concat(F.lit("/*{"), "_kind", F.lit("}")))
    far = far.select("_host", "_stem", F.when(like, several).otherwise(F.col("_stem")).alias("_branch"))
    return counts.join(far, ["_host", "_stem"]).select("_host", "_t", "_label", "_n", F.concat("_branch", "_child").alias("_class"))


def _purities(merged: DataFrame, prior: float) -> DataFrame:
    """merged (_host, _t, _class, _label, _n) -> _host, _t, _class, purity.

    The blocked share among a branch's labelled addresses is smoothed towards that of the same template on all hosts of
    the domain, this towards the suffix, towards all hosts, and towards all labelled addresses. Where neither the branch
    nor the template on any host has a labelled address, there is none (null).
    """
    blocked, labelled = F.sum(F.when(F.col("_label") == "block", F.col("_n")).otherwise(0)), F.sum(F.when(F.col("_label") != "none", F.col("_n")).otherwise(0))
    labels = F.split("_host", r"\.")
    counts = merged.groupBy("_host", "_t", "_class").agg(blocked.alias("_b"), labelled.alias("_l"))
    counts = table(counts.withColumn("_domain", F.concat_ws(".", F.slice(F.reverse(labels), 1, 2))).withColumn("_suffix", F.element_at(labels, -1)), "template-labels")
    out = counts.select("_host", "_t", "_class", "_domain", "_suffix")
    levels = (("all", ["_t"]), ("suffix", ["_suffix", "_t"]), ("domain", ["_domain", "_t"]), ("host", ["_host", "_class"]))
    for level, keys in levels:
        out = out.join(counts.groupBy(*keys).agg(F.sum("_b").alias(f"_b_{level}"), F.sum("_l").alias(f"_l_{level}")), keys)
    share = F.when((F.col("_l_all") > 0) | (F.col("_l_host") > 0), F.lit(prior))
    for level, _ in levels:
        share = (F.col(f"_b_{level}") + WEIGHT * share) / (F.col(f"_l_{level}") + WEIGHT)
    return out.select("_host", "_t", "_class", share.alias("purity"))


def judge(pages: DataFrame, url: str = "url", rules=RULES) -> DataFrame:
    """pages with host, path, template, purity, rule, verdict added.

    Null addresses and those without :// have an empty host and path. Rules come first, the longest that fits; else
    the template decides: by its own labelled addresses and, the fewer these are, by those of the same template on other
    hosts of its domain, its suffix, or anywhere. Templates without a labelled address on any host are allowed. Labels are
    the rules' own verdicts.
    Repeated rows count and are judged each time; no rows, no rows; columns of pages are kept, but for those added and names that begin with _.
    """
    columns = [c for c in pages.columns if c not in ("host", "path", "template", "purity", "rule", "verdict") and not c.startswith("_")]
    host, path = host_path(F.col(url))
    rows = pages.select(*columns, host.alias("_host"), path.alias("_path"))
    rule, verdict = by_rule(F.col("_host"), F.col("_path"), rules)
    rows = templates(rows.withColumn("_rule", rule).withColumn("_label", verdict))
    merged = table(_merged(rows.select("_host", "_t", "_label")), "branches")
    total = merged.where("_label <> 'none'").agg(F.sum(F.when(F.col("_label") == "block", F.col("_n")).otherwise(0)), F.sum("_n")).first()
    prior = (total[0] + 1) / (total[1] + 2) if total[1] else 0.0
    known = _purities(merged, prior)
    known = table(known.select(F.col("_host").alias("_kh"), F.col("_t").alias("_kt"), F.col("_class").alias("template"), "purity"), "purities")
    known = F.broadcast(known) if bounded_bytes(known, BROADCAST_BYTES) else known
    out = rows.join(known, (F.col("_host") == F.col("_kh")) & (F.col("_t") == F.col("_kt")), "left")
    by_template = F.when(F.col("purity") >= 0.5, F.lit("block")).otherwise(F.lit("allow"))
    return out.select(*columns, F.col("_host").alias("host"), F.col("_path").alias("path"), "template", "purity", F.col("_rule").alias("rule"), F.coalesce("_label", by_template).alias("verdict"))
