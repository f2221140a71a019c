"""Near-duplicate documents by a chosen-path set similarity join.

Documents become sets of word shingles. Exact copies of a set meet in one group-by and go on as one representative.
Every representative draws minwise tokens; a tree's root sends it down the paths named by some of these tokens, and a
node that is still large sends its members further down by other tokens, in coordinates that the node chooses for all
its members: its name picks them among those in which the members agree least with the smallest member, so that a passage
that all have in common does not keep them together. Independent trees raise the recall: a pair of similarity s misses `trees` roots with
probability (1-s)**trees. All links are confirmed on whole sets.

Small nodes compare all members by sketches, but first put forward only a spanning forest of the likely links, so that
a group of copies costs as many confirmations as it has members. Only where one of these fails do the pairs across
the components that are left follow.

A large node in which many members read like its pivot (its smallest member) would send them all down every branch and
never fall apart. Its crowd, those that share CROWD minwise tokens with the pivot, stays: it is cut into blocks that hold
the pivot, and afterwards members outside the pivot's component meet every block. All that are not of the crowd go on as
a node of their own; those of them that share FAR tokens with the pivot could be linked with the crowd and stay with it
as well. Two members, one of the crowd and one below FAR, share at most FAR - 1 + COORDS - CROWD = 29 of 64 tokens; at a
similarity of 0.8, 51 are expected, and 29 or fewer have a chance of 1e-9. What is still large after the last branch is
cut into blocks in the same way, whole. A pivot is mostly that of the same crowd in several trees; these crowds are joined
into one, which keeps all pairs that any of them holds.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .common import bounded_bytes, lean, release, small_batches, table
from .components import components
from .sketch import marks, parted

WORDS, NUMERATOR = 5, 80
COORDS = 64
#: Bits of the odd sketch: bit k tells whether an odd number of the set's tokens fall there. Two sketches differ in at
#: most as many bits as their sets do in tokens, so no pair at the threshold is ever refused.
ODD = 1024
TREES, DEPTH, BRANCHES, NODE = 8, 3, 3, 256
APART = 24  # coordinates among which a node chooses those that it branches by
CROWD, FAR = 44, 10  # of COORDS minwise tokens shared with the pivot
SEEN = 1 << 22
MOST = 0.5  # of those that share FAR tokens with the pivot: so large a crowd stays together
PIVOTS_BYTES = 32 << 20
_rng = np.random.default_rng(7)
_mul = _rng.integers(1 << 62, size=COORDS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_xor = _rng.integers(1 << 63, size=COORDS, dtype=np.uint64)


def shingle_sets(column: pa.Array, n: int) -> Iterator[np.ndarray]:
    """Per row the sorted distinct shingle hashes; fewer words than n: the whole sequence as one; no word: empty."""
    for _, data, offsets in K.blocks(column):
        _, _, h, first = K.words(data, offsets)
        g = K.shingles(h, n)
        for a, b in zip(first[:-1], first[1:], strict=True):
            yield np.unique(g[a : b - n + 1]) if b - a >= n else np.array([K.whole(h[a:b])], np.uint64) if b > a else np.zeros(0, np.uint64)


def minwise(s: np.ndarray) -> np.ndarray:
    """The set's minwise tokens, one per coordinate."""
    out = np.full(COORDS, np.uint64((1 << 64) - 1))
    for k in range(0, len(s), 1024):
        np.minimum(out, ((s[k : k + 1024, None] ^ _xor) * _mul).min(axis=0), out=out)
    return (out >> np.uint64(32)).astype(np.uint32).view(np.int32)


def odd_sketch(s: np.ndarray) -> bytes:
    bits = np.bincount((s >> np.uint64(20)).astype(np.int64) & (ODD - 1), minlength=ODD) & 1
    return np.packbits(bits.astype(np.uint8)).tobytes()


def _digests(s: np.ndarray) -> tuple[int, int]:
    return int(s.sum(dtype=np.uint64).astype(np.int64)), int(K.mix(s ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64).astype(np.int64))


def _features(n: int):
    def run(batches):
        for batch in batches:
            rows = [(len(s), *_digests(s), minwise(s).tobytes() if len(s) else None, odd_sketch(s) if len(s) else None) for s in shingle_sets(batch.column("text"), n)]
            columns = zip(*rows, strict=True) if rows else [[]] * 5
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(list(c), k) for c, k in zip(columns, kinds, strict=True))], names=["doc_id", "n_shingles", "d1", "d2", "sig", "odd"])

    return run


def _id_keys(batch: pa.RecordBatch) -> Iterator[np.ndarray]:
    yield K.mix(batch.column("doc_id").to_numpy().view(np.uint64))


def _sets(n: int, seen):
    """Token sets of the documents that the fixed-size table marks; a few others slip in and are joined away."""

    def run(batches):
        for batch in batches:
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
            some = seen.value[(K.mix(ids.astype(np.int64).view(np.uint64)) & np.uint64(SEEN - 1)).astype(np.int64)]
            batch = batch.filter(pa.array(some))
            whole = list(shingle_sets(batch.column("text"), n))
            both = [_digests(s) for s in whole]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array([d[0] for d in both], pa.int64()), pa.array([d[1] for d in both], pa.int64()), pa.array([len(s) for s in whole], pa.int64()), pa.array([s.tobytes() for s in whole], pa.binary())],
                names=["doc_id", "d1", "d2", "n_shingles", "tokens"],
            )

    return run


def _roots(trees: int):
    """A row for each root branch of each tree."""
    chosen = np.random.default_rng(11).permutation(COORDS)[:trees].astype(np.int64)

    def run(batches):
        for batch in batches:
            sig = np.frombuffer(b"".join(batch.column("sig").to_pylist()), np.int32).reshape(-1, COORDS)
            keys = K.mix((sig[:, chosen].astype(np.int64).view(np.uint64) << np.uint64(8)) + np.arange(trees, dtype=np.uint64)).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(batch.column("rep").to_numpy(), trees)), pa.array(keys.ravel())], names=["rep", "node"])

    return run


def _branch(batches):
    """The node names the coordinates; a member's tokens there name the children."""
    for batch in batches:
        if not batch.num_rows:
            continue
        node = batch.column("node").to_numpy().view(np.uint64)
        sig = np.frombuffer(b"".join(batch.column("sig").to_pylist()), np.int32).reshape(-1, COORDS)
        coords = batch.column("coords").flatten().to_numpy().astype(np.int64).reshape(len(sig), -1)
        keys = []
        for j in range(coords.shape[1]):
            seed = K.mix(node + coords[:, j].astype(np.uint64) + np.uint64(1))
            token = sig[np.arange(len(sig)), coords[:, j]].astype(np.int64).view(np.uint64)
            keys.append(K.mix(seed ^ (token << np.uint64(1))).view(np.int64))
        yield pa.RecordBatch.from_arrays([pa.array(np.tile(batch.column("rep").to_numpy(), len(keys))), pa.array(np.concatenate(keys))], names=["rep", "node"])


def _alike(batches):
    """In which coordinates a member's signature is the pivot's: as bits, and how many."""
    for batch in batches:
        if batch.num_rows:
            own, pivot = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.int32).reshape(-1, COORDS) for c in ("sig", "pivot_sig"))
            same = own == pivot
            bits = np.packbits(same, axis=1, bitorder="little").view(np.int64).ravel()
            yield pa.RecordBatch.from_arrays([batch.column("rep"), batch.column("pivot"), pa.array(same.sum(axis=1).astype(np.int32)), pa.array(bits)], names=["rep", "pivot", "shared", "same"])


def _confirm(numerator: int):
    """Rows (a, b, tokens_a, tokens_b) -> the pairs with 100 * intersection >= numerator * union."""

    def run(batches):
        for batch in batches:
            keep = np.zeros(batch.num_rows, bool)
            one, two = batch.column("tokens_a"), batch.column("tokens_b")
            for k in range(batch.num_rows):
                x, y = np.frombuffer(one[k].as_buffer(), np.uint64), np.frombuffer(two[k].as_buffer(), np.uint64)
                if 100 * min(len(x), len(y)) >= numerator * max(len(x), len(y)):
                    if len(x) > len(y):
                        x, y = y, x
                    at = np.searchsorted(y, x)
                    at[at == len(y)] = 0
                    both = int((y[at] == x).sum())
                    keep[k] = 100 * both >= numerator * (len(x) + len(y) - both)
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(keep))

    return run


def _groups(batches, columns: tuple[str, ...]) -> Iterator[list[np.ndarray]]:
    """The groups of equal (node, block) in a sorted partition; a group may run over several batches."""
    held: list[list] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        now = [np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint64).reshape(-1, ODD // 64) if c == "odd" else batch.column(c).to_numpy(zero_copy_only=False) for c in columns]
        if held:
            now = [np.concatenate(x) for x in zip(held, now, strict=True)]
        cut = np.flatnonzero((np.diff(now[0]) != 0) | (np.diff(now[1]) != 0)) + 1
        for a, b in zip(np.append(0, cut[:-1]), cut, strict=True) if len(cut) else ():
            yield [c[a:b] for c in now]
        held = [c[cut[-1] if len(cut) else 0 :] for c in now]
    if held:
        yield held


def _near(size: np.ndarray, odd: np.ndarray, k: int, at: np.ndarray, numerator: int) -> tuple[np.ndarray, np.ndarray]:
    """Of the rows `at`, those that may reach the threshold with row k, and in how many bits they differ."""
    n, m = int(size[k]), size[at]
    ok = 100 * np.minimum(n, m) >= numerator * np.maximum(n, m)
    at = at[ok]
    differ = np.bitwise_count(odd[at] ^ odd[k]).sum(axis=1, dtype=np.int64)
    total = n + size[at]
    most = total - 2 * (-((-numerator * total) // (100 + numerator)))
    return at[differ <= most], differ[differ <= most]


def _forest(numerator: int):
    """A spanning forest of each group's likely links, the likeliest first."""

    def run(batches):
        a, b, nodes = [], [], []
        for node, _, rep, size, odd in _groups(batches, ("node", "block", "rep", "n_shingles", "odd")):
            top = list(range(len(rep)))
            links = []
            for k in range(len(rep) - 1):
                at, differ = _near(size, odd, k, np.arange(k + 1, len(rep)), numerator)
                links.append(np.stack([differ, np.full(len(at), k), at]))
            links = np.concatenate(links, axis=1) if links else np.zeros((3, 0), np.int64)
            for k in np.argsort(links[0], kind="stable"):
                x, y = int(links[1, k]), int(links[2, k])
                while top[x] != x:
                    top[x] = x = top[top[x]]
                while top[y] != y:
                    top[y] = y = top[top[y]]
                if x != y:
                    top[max(x, y)] = min(x, y)
                    i, j = rep[links[1, k]], rep[links[2, k]]
                    a.append(max(i, j)), b.append(min(i, j)), nodes.append(node[0])
            if len(a) > 50_000:
                yield _pairs(a, b, nodes)
                a, b, nodes = [], [], []
        yield _pairs(a, b, nodes)

    return run


def _pairs(a, b, nodes):
    return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(nodes, pa.int64())], names=["a", "b", "node"])


def _across(numerator: int):
    """All likely links between different components of a group; rows without probe meet only those with it."""

    def run(batches):
        for node, _, rep, size, odd, part, probe in _groups(batches, ("node", "block", "rep", "n_shingles", "odd", "component", "probe")):
            a, b = [], []
            probe = probe.astype(bool)
            for k in np.flatnonzero(probe):
                at, _ = _near(size, odd, k, np.flatnonzero((part != part[k]) & (~probe | (rep > rep[k]))), numerator)
                a += np.maximum(rep[at], rep[k]).tolist()
                b += np.minimum(rep[at], rep[k]).tolist()
            if a:
                yield _pairs(a, b, [node[0]] * len(a))

    return run


def near_duplicates(docs: DataFrame, words: int = WORDS, numerator: int = NUMERATOR, trees: int = TREES) -> DataFrame:
    """docs (doc_id, text) -> doc_id, n_shingles, component_id (smallest doc_id reachable), kept.

    Words are runs outside space and \\t-\\r, A-Z folded; links need 100 * intersection >= numerator * union.
    Null or wordless text: empty set, linked with nothing. Repeated rows come back as often as given; a null doc_id
    is linked with nothing and stays, with a null component. Other columns are not read. No rows: no rows.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    with small_batches(docs.sparkSession):
        features = table(docs.mapInArrow(lean(_features(words)), "doc_id long, n_shingles long, d1 long, d2 long, sig binary, odd binary"), "features")
    some = features.where("doc_id is not null and n_shingles > 0")
    groups = table(some.groupBy("d1", "d2", "n_shingles").agg(F.min("doc_id").alias("rep")), "groups")
    # A representative goes by a name made of its id and its set, as rows that share an id may differ in text.
    own = some.join(groups.withColumnRenamed("rep", "doc_id"), ["doc_id", "d1", "d2", "n_shingles"]).dropDuplicates(["doc_id", "d1", "d2", "n_shingles"])
    reps = table(own.select(F.xxhash64("doc_id", "d1", "d2", "n_shingles").alias("rep"), "doc_id", "n_shingles", "sig", "odd"), "representatives")

    def needed(of: DataFrame, rows: DataFrame) -> DataFrame:
        """Those of the representatives that rows name, and a few others: the rest need not be shuffled for a join."""
        return parted(of, F.xxhash64("rep"), rows.select(F.xxhash64("rep")))[1]

    signatures = reps.select("rep", "sig")
    frontier, small, large = signatures.mapInArrow(lean(_roots(trees)), "rep long, node long"), None, None
    for depth in range(DEPTH + 1):
        frontier = table(frontier.distinct() if depth else frontier, f"paths-{depth}")
        size = frontier.groupBy("node").agg(F.count("*").alias("n"), F.min("rep").alias("pivot"), F.sum(F.xxhash64("rep").cast("decimal(38,0)")).alias("same")).where("n > 1")
        # Nodes with the same members are one.
        size = size.groupBy("same", "n", "pivot").agg(F.min("node").alias("node"))
        sized = table(frontier.join(size.select("node", "n", "pivot"), "node"), f"nodes-{depth}")
        release(frontier)
        fits = sized.where(F.col("n") <= NODE)
        small = fits if small is None else small.unionByName(fits)
        rest = sized.where(F.col("n") > NODE)
        if depth == DEPTH or not rest.limit(1).count():
            large = rest.select("rep", "node", "pivot") if large is None else large.unionByName(rest.select("rep", "node", "pivot"))
            break
        # How many tokens each member of a large node shares with the pivot: looked up once for a pivot of several nodes.
        near = table(rest.select("rep", "pivot").distinct(), f"near-{depth}")
        before, signatures = signatures, table(needed(signatures, near), f"signatures-{depth}")
        pivots = near.select("pivot").distinct().join(signatures, F.col("pivot") == F.col("rep")).select("pivot", F.col("sig").alias("pivot_sig"))
        pivots = table(pivots, f"pivots-{depth}")
        pivots = F.broadcast(pivots) if bounded_bytes(pivots, PIVOTS_BYTES) else pivots
        compared = table(near.join(signatures, "rep").join(pivots, "pivot").mapInArrow(lean(_alike), "rep long, pivot long, shared int, same long"), f"compared-{depth}")
        alike = table(rest.join(compared, ["rep", "pivot"]).select("rep", "node", "pivot", "shared", "same"), f"alike-{depth}")
        release(near, compared, *([before] if depth else []))
        agree = F.array(*(F.sum(F.shiftright("same", k).bitwiseAND(F.lit(1))) for k in range(COORDS)))
        crowd = alike.groupBy("node").agg(F.sum(F.when(F.col("shared") >= CROWD, 1).otherwise(0)).alias("crowd"), F.sum(F.when(F.col("shared") >= FAR, 1).otherwise(0)).alias("stay"), agree.alias("agree"))
        # Of the coordinates in which the node's members agree least with the pivot, its name picks some.
        apart = F.slice(F.array_sort(F.transform("agree", lambda x, k: F.struct(x.alias("x"), k.alias("k")))), 1, APART)
        picked = F.slice(F.array_sort(F.transform(apart, lambda s: F.struct(F.xxhash64("node", s["k"]).alias("h"), s["k"].alias("k")))), 1, BRANCHES)
        crowd = table(crowd.select("node", "crowd", "stay", F.transform(picked, lambda s: s["k"]).alias("coords")), f"crowds-{depth}")
        alike = alike.join(crowd, "node").withColumn("crowded", (F.col("crowd") >= NODE / 4) & (F.col("crowd") >= MOST * F.col("stay")))
        # Crowds of one pivot, met in several trees, are one: their union.
        stays = alike.where(F.col("crowded") & (F.col("shared") >= FAR)).select("rep", F.xxhash64("pivot").alias("node"), "pivot")
        large = stays if large is None else large.unionByName(stays)
        others = alike.where(F.col("crowded") & (F.col("shared") < CROWD)).select("rep", F.xxhash64("node").alias("node"))
        frontier = alike.where(~F.col("crowded")).select("rep", "node", "coords").join(signatures, "rep").select("rep", "node", "coords", "sig").mapInArrow(lean(_branch), "rep long, node long").unionByName(others)
    if depth:
        release(signatures)
    large = table(large.distinct(), "large-members")
    large = table(large.join(large.groupBy("node").agg(F.count("*").alias("n")), "node"), "large")
    blocks = F.ceil(F.col("n") / NODE).cast("int")
    own_block = F.pmod(F.xxhash64("rep"), blocks).cast("int")
    sketches = reps.select("rep", "n_shingles", "odd")

    def gathered(rows: DataFrame) -> DataFrame:
        return rows.join(needed(sketches, rows), "rep").repartition("node", "block").sortWithinPartitions("node", "block")

    in_blocks = large.withColumn("block", F.explode(F.when(F.col("rep") == F.col("pivot"), F.sequence(F.lit(0), blocks - 1)).otherwise(F.array(own_block))))
    first = small.withColumn("block", F.lit(0)).select("rep", "node", "block").unionByName(in_blocks.select("rep", "node", "block"))
    tried = table(gathered(first).select("node", "block", "rep", "n_shingles", "odd").mapInArrow(lean(_forest(numerator)), "a long, b long, node long"), "forest")

    def confirmed(pairs: DataFrame, what: str) -> DataFrame:
        ends = pairs.select(F.col("a").alias("rep")).unionByName(pairs.select(F.col("b").alias("rep"))).distinct()
        ids = table(reps.join(ends, "rep", "left_semi").select("rep", "doc_id"), f"ends-{what}")
        seen = docs.sparkSession.sparkContext.broadcast(marks(ids, SEEN, _id_keys))
        sets = docs.where("doc_id is not null").mapInArrow(lean(_sets(words, seen)), "doc_id long, d1 long, d2 long, n_shingles long, tokens binary")
        sets = sets.select(F.xxhash64("doc_id", "d1", "d2", "n_shingles").alias("rep"), "tokens")
        with small_batches(docs.sparkSession):
            sets = table(sets.join(ids.select("rep"), "rep", "left_semi"), f"sets-{what}").dropDuplicates(["rep"])
        seen.destroy()
        one, two = sets.select(F.col("rep").alias("a"), F.col("tokens").alias("tokens_a")), sets.select(F.col("rep").alias("b"), F.col("tokens").alias("tokens_b"))
        return table(pairs.join(one, "a").join(two, "b").select("a", "b", "tokens_a", "tokens_b").mapInArrow(lean(_confirm(numerator)), "a long, b long"), f"links-{what}")

    links = confirmed(table(tried.select("a", "b").distinct(), "pairs-1"), "1")
    parts = components(links)
    # Nodes of which a likely link failed may hold others; large nodes, members outside the main component.
    failed = tried.join(links, ["a", "b"], "left_anti").select("node").distinct()
    part_of = lambda x, key: x.join(parts.select(F.col("node").alias("_n"), F.col("component").alias(f"{key}_part")), F.col(key) == F.col("_n"), "left").withColumn(f"{key}_part", F.coalesce(f"{key}_part", key)).drop("_n")
    again = part_of(small.join(failed, "node", "left_semi"), "rep").select("rep", "node", F.lit(0).alias("block"), F.col("rep_part").alias("component"), F.lit(True).alias("probe"))
    outside = part_of(part_of(large, "rep"), "pivot").withColumn("probe", F.col("rep_part") != F.col("pivot_part"))
    outside = outside.join(outside.where("probe").select("node").distinct(), "node", "left_semi")
    outside = outside.withColumn("block", F.explode(F.when(F.col("probe"), F.sequence(F.lit(0), blocks - 1)).otherwise(F.array(own_block))))
    again = again.unionByName(outside.select("rep", "node", "block", F.col("rep_part").alias("component"), "probe"))
    rest = gathered(again).select("node", "block", "rep", "n_shingles", "odd", "component", "probe").mapInArrow(lean(_across(numerator)), "a long, b long, node long")
    rest = table(rest.select("a", "b").distinct().join(tried.select("a", "b"), ["a", "b"], "left_anti"), "pairs-2")
    if rest.limit(1).count():
        more = confirmed(rest, "2")
        if more.limit(1).count():
            parts = components(links.unionByName(more))

    # Back to documents: names -> the component's smallest doc_id -> every row of the group.
    labelled = reps.select("rep", "doc_id").join(parts, F.col("rep") == F.col("node"), "left").select("rep", "doc_id", F.coalesce("component", "rep").alias("component"))
    least = labelled.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    named = labelled.join(least, "component").select(F.col("rep").alias("name"), "component_id")
    of_group = groups.withColumn("name", F.xxhash64("rep", "d1", "d2", "n_shingles")).join(named, "name").select(F.col("d1").alias("e1"), F.col("d2").alias("e2"), F.col("n_shingles").alias("e3"), "component_id")
    rows = features.select("doc_id", "n_shingles", "d1", "d2")
    out = rows.join(of_group, (F.col("d1") == F.col("e1")) & (F.col("d2") == F.col("e2")) & (F.col("n_shingles") == F.col("e3")) & F.col("doc_id").isNotNull(), "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
