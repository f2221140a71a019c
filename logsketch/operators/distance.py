"""Distances of feature bags: exact squared integers by an inverted index or by blocks, and only the near pairs by leading rare features."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..tables import sweep, table

#: All pairs are asked for only up to so many items; beyond, within() finds the near ones.
MOST = 20_000
BLOCK = 512
MOST_BLOCKS = 24  # of vectors, larger where there are more


def packed(bag: DataFrame) -> DataFrame:
    """bag (tree_id, feature_id, mult) -> tree_id, items: array of (feature_id, mult) in feature order."""
    return bag.groupBy("tree_id").agg(F.array_sort(F.collect_list(F.struct("feature_id", "mult"))).alias("items"))


def norms(bag: DataFrame) -> DataFrame:
    m = F.col("mult").cast("long")
    return bag.groupBy("tree_id").agg(F.sum(m * m).alias("n2"), F.sum(m).alias("n1"), F.count("*").alias("n0"))


def shared(bag: DataFrame) -> DataFrame:
    """Pairs i < j with a common feature: dot product, sum of minima, number of common features."""
    a = bag.select(F.col("tree_id").alias("i"), "feature_id", F.col("mult").cast("long").alias("x"))
    b = bag.select(F.col("tree_id").alias("j"), "feature_id", F.col("mult").cast("long").alias("y"))
    both = a.join(b.hint("shuffle_hash"), "feature_id").where("i < j")
    return both.groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("dot"), F.sum(F.least("x", "y")).alias("low"), F.count("*").alias("common"))


def pairwise(bag: DataFrame, metric: str = "l2", engine: str = "index") -> DataFrame:
    """All pairs i < j: d2 (exact, for l2) and d. metric: l2, l1, jaccard, cosine. At most MOST items."""
    size = norms(bag)
    n = size.count()
    if n > MOST:
        raise ValueError(f"{n} items: all pairs are for at most {MOST}; use within()")
    if engine == "block":
        return _blocks(bag, metric)
    a = size.select(F.col("tree_id").alias("i"), F.col("n2").alias("i2"), F.col("n1").alias("i1"), F.col("n0").alias("i0"))
    b = size.select(F.col("tree_id").alias("j"), F.col("n2").alias("j2"), F.col("n1").alias("j1"), F.col("n0").alias("j0"))
    grid = a.join(F.broadcast(b), F.col("i") < F.col("j"))  # bounded by MOST
    out = grid.join(shared(bag), ["i", "j"], "left").na.fill(0, ["dot", "low", "common"])
    d2 = F.col("i2") + F.col("j2") - 2 * F.col("dot")
    if metric == "l2":
        return out.select("i", "j", d2.alias("d2"), F.sqrt(d2.cast("double")).alias("d"))
    if metric == "l1":
        d = F.col("i1") + F.col("j1") - 2 * F.col("low")
    elif metric == "jaccard":
        d = 1 - F.col("common") / (F.col("i0") + F.col("j0") - F.col("common"))
    elif metric == "cosine":
        d = 1 - F.col("dot") / F.sqrt(F.col("i2").cast("double") * F.col("j2"))
    else:
        raise ValueError(metric)
    return out.select("i", "j", d2.alias("d2"), d.cast("double").alias("d"))


def matrix(items: list[list[tuple[int, int]]], metric: str = "l2") -> np.ndarray:
    """Dense distances of packed bags: exact squares for l2, sums of differences for l1."""
    number: dict = {}
    place = np.repeat(np.arange(len(items)), [len(row) for row in items])
    features = np.array([number.setdefault(f, len(number)) for row in items for f, _ in row], np.int64)
    return bag_matrix(place, features, np.array([m for row in items for _, m in row], np.int64), len(items), metric)


def dense(place: np.ndarray, features: np.ndarray, mult: np.ndarray, n: int, kind: type = np.float64) -> np.ndarray:
    """A row for each of n items, a column for each feature, from (item, feature, multiplicity); features are numbers from 0."""
    x = np.zeros((n, int(features.max(initial=-1)) + 1), kind)
    x[place, features] = mult
    return x


def bag_matrix(place: np.ndarray, features: np.ndarray, mult: np.ndarray, n: int, metric: str = "l2") -> np.ndarray:
    """matrix() from (item, feature, multiplicity), each pair of item and feature once."""
    if metric == "l1":
        x = dense(place, features, mult, n)
        return np.stack([np.abs(x - row).sum(axis=1) for row in x]) if len(x) else np.zeros((0, 0))
    n2 = np.bincount(place, np.square(mult, dtype=np.float64), n)
    # Only features of several items make products; below 2^24 they are exact in half the room.
    often = np.flatnonzero(np.bincount(features) > 1) if len(features) else features
    column = np.full(int(features.max(initial=-1)) + 1, -1)
    column[often] = np.arange(len(often))
    kept = column[features] >= 0
    x = dense(place[kept], column[features[kept]], mult[kept], n, np.float32 if n2.max(initial=0) < 1 << 24 else np.float64)
    d = (x @ x.T).astype(np.float64)
    d *= -2
    d += n2[:, None]
    d += n2[None, :]
    np.fill_diagonal(d, 0)
    return np.rint(np.maximum(d, 0, out=d), out=d)


def _blocks(bag: DataFrame, metric: str) -> DataFrame:
    """Blocks of items meet in pairs, each pair of blocks in a task of its own."""
    rows = packed(bag)
    count = max(1, -(-rows.count() // BLOCK))
    rows = rows.withColumn("block", F.pmod(F.xxhash64("tree_id"), F.lit(count)).cast("int"))
    whole = table(rows.groupBy("block").agg(F.collect_list(F.struct("tree_id", "items")).alias("rows")), "blocks")
    a = whole.select(F.col("block").alias("p"), F.col("rows").alias("left"), F.explode(F.sequence(F.col("block"), F.lit(count - 1))).alias("q"))
    both = a.join(whole.select(F.col("block").alias("q"), F.col("rows").alias("right")), "q")

    def run(batches):
        for batch in batches:
            for p, q, left, right in zip(*(batch.column(c).to_pylist() for c in ("p", "q", "left", "right")), strict=True):
                rows = left if p == q else left + right
                ids = np.array([r["tree_id"] for r in rows], np.int64)
                items = [[(x["feature_id"], x["mult"]) for x in r["items"]] for r in rows]
                d2 = matrix(items)
                d = np.sqrt(d2) if metric == "l2" else matrix(items, metric)
                i, j = np.triu_indices(len(rows), 1)
                if p != q:
                    keep = (i < len(left)) & (j >= len(left))
                    i, j = i[keep], j[keep]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(ids[i], ids[j])), pa.array(np.maximum(ids[i], ids[j])), pa.array(d2[i, j].astype(np.int64)), pa.array(d[i, j])], names=["i", "j", "d2", "d"])

    return both.mapInArrow(run, "i long, j long, d2 long, d double")


def within(bag: DataFrame, tau: float) -> DataFrame:
    """Pairs i < j at l2 distance of at most tau > 0: i, j, d2, d.

    Features go in order of rarity. What either item has before the first feature that a pair has in common counts in
    full, so in both items this feature follows less than tau: only such leading features are joined, and lengths differ by
    no more than tau. Pairs without a common feature are within tau when both are short; they meet by their lengths.
    Below the root of two, where bags are equal or differ by one in one feature, they meet by what they are.
    """
    if tau * tau < 2:
        return _within_one(bag, tau)
    t2, m = tau * tau, F.col("mult").cast("long")
    items = table(bag.groupBy("tree_id").agg(F.map_from_entries(F.collect_list(F.struct("feature_id", m))).alias("m"), F.sum(m * m).alias("n2")), "items")
    rare = bag.groupBy("feature_id").agg(F.count("*").alias("df"))
    before = Window.partitionBy("tree_id").orderBy("df", "feature_id").rowsBetween(Window.unboundedPreceding, -1)
    lead = bag.join(rare, "feature_id").withColumn("before", F.coalesce(F.sum(m * m).over(before), F.lit(0))).where(F.col("before") <= t2)
    lead = table(lead.select("tree_id", "feature_id").join(items.select("tree_id", "n2"), "tree_id"), "leading")
    side = lambda rows, key, k: rows.select(F.col("tree_id").alias(k), F.col("n2").alias(f"{k}2"), key)
    near = side(lead, "feature_id", "i").join(side(lead, "feature_id", "j"), "feature_id").where(F.abs(F.sqrt("i2") - F.sqrt("j2")) <= tau)
    short = items.where(F.col("n2") < t2).select("tree_id", "n2", F.col("n2").alias("at"))
    apart = side(short.withColumn("at", F.explode(F.expr(f"sequence(1L, greatest(1L, {int(t2)}L - n2))"))), "at", "i").join(side(short, "at", "j"), "at").where(F.col("i2") + F.col("j2") <= t2)
    near = near.select("i", "j").unionByName(apart.select("i", "j")).where("i < j").distinct()
    a, b = items.select(F.col("tree_id").alias("i"), F.col("m").alias("x"), F.col("n2").alias("i2")), items.select(F.col("tree_id").alias("j"), F.col("m").alias("y"), F.col("n2").alias("j2"))
    dot = F.aggregate(F.map_entries("x"), F.lit(0).cast("long"), lambda s, e: s + e["value"] * F.coalesce(F.try_element_at("y", e["key"]), F.lit(0).cast("long")))
    both = near.join(a, "i").join(b, "j").select("i", "j", (F.col("i2") + F.col("j2") - 2 * dot).alias("d2"))
    return both.where(F.col("d2") <= t2).select("i", "j", "d2", F.sqrt(F.col("d2").cast("double")).alias("d"))


def _bag_key(items: Column) -> Column:
    """128 bits of a packed bag: lengths keep features of any text apart."""
    f = lambda x: x["feature_id"].cast("string")
    return F.unhex(F.md5(F.array_join(F.transform(items, lambda x: F.concat_ws(":", F.length(f(x)).cast("string"), f(x), x["mult"].cast("string"))), ",")))


def _within_one(bag: DataFrame, tau: float) -> DataFrame:
    """Pairs of equal bags, and of bags of which one is the other with one more of one feature. Multiplicities are from 1 on.

    Equal bags are put together, each with the list of its items, and only distinct ones look for neighbours: each offers
    itself less one of each of its features. Bags go by their keys, and pairs are made from two lists where they are
    read: no pair and no bag is shuffled with each item."""
    sweep(bag.sparkSession)
    items = packed(bag.select("tree_id", "feature_id", F.col("mult").cast("long").alias("mult")))
    groups = table(items.groupBy(_bag_key(F.col("items")).alias("kind")).agg(F.first("items").alias("items"), F.sort_array(F.collect_list("tree_id")).alias("ids")), "groups")
    sweep(bag.sparkSession)
    first = groups.where(F.size("ids") > 1).select("ids", F.posexplode("ids").alias("_p", "i"))
    alike = first.select("i", F.explode(F.slice("ids", F.col("_p") + 2, F.size("ids"))).alias("j"), F.lit(0).cast("long").alias("d2"))
    if tau >= 1:
        one_less = F.expr("filter(transform(items, x -> struct(x.feature_id AS feature_id, x.mult - CASE WHEN x.feature_id <=> one.feature_id THEN 1L ELSE 0L END AS mult)), x -> x.mult > 0)")
        less = groups.select("kind", "items", F.explode("items").alias("one")).select("kind", one_less.alias("rest")).select("kind", _bag_key(F.col("rest")).alias("rest"))
        next_ = table(less.join(groups.select(F.col("kind").alias("rest")), "rest"), "neighbours")
        sweep(bag.sparkSession)
        lists = next_.join(groups.select("kind", F.col("ids").alias("us")), "kind").select("rest", "us").join(groups.select(F.col("kind").alias("rest"), F.col("ids").alias("ks")), "rest")
        more = lists.select("ks", F.explode("us").alias("u")).select("u", F.explode("ks").alias("k"))
        alike = alike.unionByName(more.select(F.least("u", "k").alias("i"), F.greatest("u", "k").alias("j"), F.lit(1).cast("long").alias("d2")))
    return alike.select("i", "j", "d2", F.sqrt(F.col("d2").cast("double")).alias("d"))


def rounded(d: np.ndarray, digits: int) -> np.ndarray:
    """Distances to so many digits, halves upwards; what is too large for digits stays."""
    with np.errstate(over="ignore", invalid="ignore"):
        r = d * 10.0**digits
        low = np.floor(r)
        low += (r - low) >= 0.5
        low /= 10.0**digits
    return low if np.isfinite(low).all() else np.where(np.isfinite(low), low, d)


def vector_pairs(vectors: DataFrame, tau: float | None = None, digits: int | None = None) -> DataFrame:
    """vectors (id, v: array<double>) -> i < j, d: Euclidean distances of all pairs, or of those within tau, to so many digits if given.

    Vectors lie in blocks that meet in pairs, any number of them. Squares add up in the order of the components; a vector
    that is null or holds nulls, and vectors of different length, have no distance."""
    rows = vectors.where("id is not null")
    count = max(1, min(MOST_BLOCKS, -(-rows.count() // BLOCK)))
    rows = rows.select(F.pmod(F.xxhash64("id"), F.lit(count)).cast("int").alias("block"), "id", F.when(~F.exists("v", lambda x: x.isNull()), F.col("v")).alias("v"))
    whole = table(rows.groupBy("block").agg(F.collect_list(F.struct("id", "v")).alias("rows")), "vectors", 1)
    tasks = count * (count + 1) // 2
    a = whole.select(F.col("block").alias("p"), F.col("rows").alias("left"), F.explode(F.sequence(F.col("block"), F.lit(count - 1))).alias("q"))
    both = a.join(whole.select(F.col("block").alias("q"), F.col("rows").alias("right")), "q").repartition(tasks, "p", "q")

    def block(rows: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids, lengths (-1 for a null), and vectors, a component to a row."""
        rows = rows.flatten()
        v = rows.field("v").to_pylist()
        size = np.array([-1 if x is None else len(x) for x in v], np.int64)
        x = np.zeros((max(size.max(initial=0), 0), len(v)))
        for k, n in enumerate(size.tolist()):
            if n > 0:
                x[:n, k] = v[k]
        return rows.field("id").to_numpy(zero_copy_only=False), size, x

    def run(batches):
        for batch in batches:
            for n in range(batch.num_rows):
                one = batch.slice(n, 1)
                (ids, size, x), (other, width, y) = block(one.column("left")), block(one.column("right"))
                step = max(1, (1 << 15) // max(1, len(other)))
                for s in range(0, len(ids), step):
                    part = slice(s, s + step)
                    d = np.zeros((len(ids[part]), len(other)))
                    gap = np.empty_like(d)
                    for a, b in zip(x[:, part], y, strict=False):
                        np.subtract(a[:, None], b[None, :], out=gap)
                        gap *= gap
                        d += gap
                    np.sqrt(d, out=d)
                    known = (size[part, None] == width[None, :]) & (size[part, None] >= 0)
                    keep = ids[part, None] < other[None, :] if one.column("p")[0] == one.column("q")[0] else ids[part, None] != other[None, :]
                    if tau is not None:
                        keep &= known & (d <= tau)
                    shape = d.shape
                    left, right = np.broadcast_to(ids[part, None], shape)[keep], np.broadcast_to(other[None, :], shape)[keep]
                    d, lack = d[keep], ~known[keep]
                    if digits is not None:
                        d = rounded(d, digits)
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(left, right)), pa.array(np.maximum(left, right)), pa.array(d, mask=lack)], names=["i", "j", "d"])

    return both.mapInArrow(run, "i long, j long, d double")


def approx_within(bag: DataFrame, tau: float, tables: int = 6, seed: int = 7) -> DataFrame:
    """The same by random projections (MLlib): some pairs may be missed."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH

    vectors = sparse_vectors(bag)
    lsh = BucketedRandomProjectionLSH(inputCol="features", outputCol="h", bucketLength=max(tau, 1e-6) * 2, numHashTables=tables, seed=seed).fit(vectors)
    got = lsh.approxSimilarityJoin(vectors, vectors, tau + 1e-9, "d")
    return got.select(F.col("datasetA.tree_id").alias("i"), F.col("datasetB.tree_id").alias("j"), "d").where("i < j")


def sparse_vectors(bag: DataFrame) -> DataFrame:
    """tree_id, features: MLlib vectors over dense feature numbers."""
    from pyspark.ml.linalg import SparseVector, VectorUDT

    ids = table(bag.select("feature_id").distinct(), "features")
    size = int(ids.agg(F.max("feature_id")).first()[0] or 0) + 1
    make = F.udf(lambda rows: SparseVector(size, {int(r["feature_id"]): float(r["mult"]) for r in rows}), VectorUDT())
    return packed(bag).select("tree_id", make("items").alias("features"))


def to_clusters(bag: DataFrame, assign: DataFrame, how: str = "nearest") -> DataFrame:
    """Each item's distance to each cluster: nearest or farthest member, or centroid. -> tree_id, cluster_id, d."""
    if how == "centroid":
        sizes = assign.groupBy("cluster_id").agg(F.count("*").alias("n"))
        centre = bag.join(assign.withColumnRenamed("item", "tree_id"), "tree_id").groupBy("cluster_id", "feature_id").agg(F.sum("mult").alias("s")).join(sizes, "cluster_id").select("cluster_id", "feature_id", (F.col("s") / F.col("n")).alias("c"))
        c2 = centre.groupBy("cluster_id").agg(F.sum(F.col("c") * F.col("c")).alias("c2"))
        dot = bag.join(centre, "feature_id").groupBy("tree_id", "cluster_id").agg(F.sum(F.col("mult") * F.col("c")).alias("dot"))
        grid = norms(bag).join(F.broadcast(c2), F.lit(True))  # clusters are few
        return grid.join(dot, ["tree_id", "cluster_id"], "left").select("tree_id", "cluster_id", F.sqrt(F.greatest(F.col("n2") + F.col("c2") - 2 * F.coalesce("dot", F.lit(0.0)), F.lit(0.0))).alias("d"))
    pairs = pairwise(bag)
    both = pairs.select(F.col("i").alias("tree_id"), F.col("j").alias("item"), "d").unionByName(pairs.select(F.col("j").alias("tree_id"), F.col("i").alias("item"), "d"))
    pick = F.min("d") if how == "nearest" else F.max("d")
    return both.join(assign, "item").groupBy("tree_id", "cluster_id").agg(pick.alias("d"))
