"""What a cluster's statements share: characteristic features, fewer and larger features, text, and a coloured tree."""

from __future__ import annotations

import re
from collections import Counter
from functools import lru_cache

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import cnf, grammar
from ..functions.grammar import Tree
from .rules import DEFAULT, Suite, features


def characteristic(bag: DataFrame, assign: DataFrame, share: float = 1.0) -> DataFrame:
    """Features that at least `share` of a cluster's statements have: cluster, feature_key, n, share."""
    rows = bag.join(assign.select(F.col("item").alias("tree_id"), F.col("cluster_id").alias("cluster")), "tree_id")
    size = assign.groupBy(F.col("cluster_id").alias("cluster")).agg(F.count("*").alias("_size"))
    out = rows.groupBy("cluster", "feature_key").agg(F.count("*").alias("n")).join(size, "cluster")
    return out.withColumn("share", F.round(F.col("n") / F.col("_size"), 6)).where(F.col("n") >= F.lit(share) * F.col("_size") - 1e-9).drop("_size")


def rfc(merges: pd.DataFrame, bag: pd.DataFrame, share: float = 1.0, max_depth: int = 4) -> list[dict]:
    """The hierarchy from the top: per cluster what it shares beyond its parent. bag: tree_id, feature_key.

    node: the least member, level: depth, n_queries, features added."""
    have = {t: set(g) for t, g in bag.groupby("tree_id")["feature_key"]}
    members: dict[int, list[int]] = {int(t): [int(t)] for t in have}
    history = []
    for a, b, h in merges.sort_values("step", kind="stable")[["left", "right", "height"]].itertuples(index=False):
        history.append((int(a), int(b), float(h), list(members[int(a)]), list(members[int(b)])))
        members[int(a)] += members.pop(int(b))

    def common(ids: list[int]) -> set[str]:
        counts = Counter(f for i in ids for f in have[i])
        return {f for f, n in counts.items() if n >= share * len(ids) - 1e-9}

    made = {}  # members -> the merge that made them
    for a, b, h, x, y in history:
        made[tuple(sorted(x + y))] = (h, sorted(x), sorted(y))
    out: list[dict] = []
    stack = [(sorted(m), None, 0, set()) for m in members.values()]
    while stack:
        ids, parent, level, known = stack.pop()
        mine = common(ids)
        out.append({"node": ids[0], "parent": parent, "level": level, "n_queries": len(ids), "features": sorted(mine - known)})
        if level < max_depth and tuple(ids) in made:
            _, x, y = made[tuple(ids)]
            stack += [(x, ids[0], level + 1, known | mine), (y, ids[0], level + 1, known | mine)]
    return out


# -- features as trees


def feature_tree(canonical: str) -> Tree:
    """A feature's partial tree from its canonical text; ids of features thus lead back to structure."""
    tokens = re.findall(r"[()]|[^\s()]+", canonical)
    at = 0

    def walk() -> Tree:
        nonlocal at
        atom = tokens[at]
        at += 1
        kids = []
        if at < len(tokens) and tokens[at] == "(":
            at += 1
            while tokens[at] != ")":
                kids.append(walk())
            at += 1
        return Tree(atom, tuple(kids))

    return walk() if tokens else Tree("")


@lru_cache(maxsize=100_000)
def embeds(part: Tree, whole: Tree) -> bool:
    """Whether part lies at whole's root: same symbol, and its children among whole's in order. ? fits any leaf."""
    if part.atom != whole.atom and not (part.atom == "?" and not whole.kids):
        return False
    k = 0
    for child in part.kids:
        while k < len(whole.kids) and not embeds(child, whole.kids[k]):
            k += 1
        if k == len(whole.kids):
            return False
        k += 1
    return True


def occurrences(part: Tree, whole: Tree) -> int:
    """How often part lies in whole."""
    return int(embeds(part, whole)) + sum(occurrences(part, k) for k in whole.kids)


def containment(items: dict[str, int]) -> list[tuple[str, str, int]]:
    """(contained, container, times) among features given by canonical text."""
    trees = {c: feature_tree(c) for c in items}
    size = {c: len(list(grammar.rows(t))) for c, t in trees.items()}
    return [(a, b, m) for b in trees for a in trees if a != b and size[a] < size[b] and (m := occurrences(trees[a], trees[b]))]


def shrink(items: dict[str, int], strict: bool = True) -> dict[str, int]:
    """Without features of which their containers already tell: multiplicity less than what these imply (or equal, if not strict)."""
    implied: Counter = Counter()
    for a, b, m in containment(items):
        implied[a] += items[b] * m
    return {f: n for f, n in items.items() if not (n < implied[f] or not strict and f in implied and n == implied[f])}


def shrink_df(items: DataFrame, contains: DataFrame) -> DataFrame:
    """items (feature, mult), contains (part, container, times) -> feature, mult, kept_strict, kept_nonstrict."""
    sums = contains.join(items.select(F.col("feature").alias("container"), F.col("mult").alias("_m")), "container").groupBy(F.col("part").alias("feature")).agg(F.sum(F.col("_m") * F.col("times")).alias("_implied"))
    out = items.join(sums, "feature", "left")
    return out.select("feature", "mult", (F.col("_implied").isNull() | (F.col("mult") >= F.col("_implied"))).alias("kept_strict"), (F.col("_implied").isNull() | (F.col("mult") > F.col("_implied"))).alias("kept_nonstrict"))


def is_minimal(items: dict[str, int]) -> bool:
    """Whether merging can add nothing: one feature, or one that contains all others."""
    if len(items) <= 1:
        return True
    pairs = containment(items)
    return any(sum(1 for a, c, _ in pairs if c == b) == len(items) - 1 for b in items)


def merge(items: dict[str, int], queries: list[Tree], count: int, rounds: int = 64) -> dict[str, int]:
    """Pairs of features put together where a query shows how; an assembly stays only if `count` queries hold it.

    Two features join when, in the first query, one's root lies directly over or inside the other's occurrence."""
    items = dict(items)
    if not queries:
        return items
    for _ in range(rounds):
        found = None
        names = sorted(items, key=lambda c: (-len(c), c))
        for a in names:
            for b in names:
                if a == b:
                    continue
                joined = _assemble(feature_tree(a), feature_tree(b), queries[0])
                if joined is None:
                    continue
                text = cnf.text(joined)
                if text not in items and verify_merge(joined, queries, count):
                    found = (a, b, text)
                    break
            if found:
                break
        if not found:
            return items
        a, b, text = found
        n = min(items.pop(a), items.pop(b))
        items[text] = n
    return items


def _assemble(a: Tree, b: Tree, query: Tree) -> Tree | None:
    """The tree of a with b hung where the query has b's root: under one of a's nodes that the query extends."""

    def under(part: Tree, whole: Tree) -> Tree | None:
        if part.atom != whole.atom:
            return None
        k, kids = 0, []
        done = None
        for child in whole.kids:
            if k < len(part.kids) and embeds(part.kids[k], child):
                deeper = under(part.kids[k], child) if done is None else None
                kids.append(deeper or part.kids[k])
                done = done or deeper
                k += 1
            elif done is None and embeds(b, child):
                kids.append(b)
                done = b
        return Tree(part.atom, tuple(kids)) if done is not None and k == len(part.kids) else None

    for node in _nodes(query):
        if embeds(a, node) and (got := under(a, node)) is not None:
            return got
    return None


def _nodes(t: Tree) -> list[Tree]:
    return [t, *(x for k in t.kids for x in _nodes(k))]


def verify_merge(assembly: Tree, queries: list[Tree], count: int) -> bool:
    """Whether as many queries hold the assembly as the prefix tree's node counts."""
    return sum(1 for q in queries if occurrences(assembly, q)) == count


def seal(tree: Tree, suite: Suite = DEFAULT, kind: str = "generic", max_rounds: int = 3, max_features: int = 2000) -> tuple[set[str], bool]:
    """Canonical features of a tree after closure, and whether it is whole (False: a bound was met).

    generic: each node's whole subtree. tailored: pairs of features that touch in the tree, assembled, until nothing is new."""
    have = {c for _, _, _, _, c in features(tree, suite)}
    if kind == "generic":
        return have | {cnf.text(x) for x in _nodes(grammar.skeleton(tree))}, True
    plain = grammar.skeleton(tree)
    for _ in range(max_rounds):
        new = set()
        names = sorted(c for c in have if not c.startswith(("CLAUSE", "CNF")))
        for a in names:
            for b in names:
                if a != b and (got := _assemble(feature_tree(a), feature_tree(b), plain)) is not None:
                    text = cnf.text(got)
                    if text not in have:
                        new.add(text)
            if len(have) + len(new) > max_features:
                return have | new, False
        if not new:
            return have, True
        have |= new
    return have, False


def rebuild(subtrees: set[str], root: str) -> Tree | None:
    """The tree whose root's whole subtree is among the features: what a generic seal promises."""
    whole = [c for c in subtrees if c.split("(", 1)[0] == root]
    return feature_tree(max(whole, key=len)) if whole else None


# -- rendering


def readable(canonical: str) -> str:
    """A feature in words."""
    t = feature_tree(canonical)
    if t.atom == "CLAUSE":
        return "condition " + " or ".join(map(_plain, t.kids))
    if t.atom == "CNF":
        return "all of: " + "; ".join(readable(cnf.text(k)) for k in t.kids)
    names = {"COLS": "outputs", "FROM": "reads", "WHERE": "filters by", "GROUP_BY": "groups by", "ORDER_BY": "orders by", "LIMIT": "limits to", "TABLE": "table", "COL_ID": "column"}
    if t.atom in names:
        return f"{names[t.atom]} " + ", ".join(map(_plain, t.kids)) if t.kids else names[t.atom]
    return _plain(t)


def _plain(t: Tree) -> str:
    if not t.kids:
        return t.atom
    if len(t.kids) == 2 and not t.atom[0].isalpha():
        return f"{_plain(t.kids[0])} {t.atom} {_plain(t.kids[1])}"
    if t.atom in ("COL_ID", "TABLE") and len(t.kids) == 1:
        return t.kids[0].atom
    return f"{t.atom.lower().replace('_', ' ')}({', '.join(map(_plain, t.kids))})"


def text_summary(items: dict[str, int], n_queries: int, lines: int = 20) -> list[str]:
    """A cluster in words: the largest features after shrinking."""
    left = shrink(items)
    order = sorted(left, key=lambda c: (-len(c), c))[:lines]
    return [f"{n_queries} statement structures share:"] + [f"- {readable(c)}" + (f" (x{left[c]})" if left[c] > 1 else "") for c in order]


def common_nodes(tree: Tree, common: set[str], suite: Suite = DEFAULT) -> list[tuple[int, int | None, str, bool]]:
    """(node_id, parent_id, atom, common): nodes that own a feature which the whole cluster has, deeper than a mere symbol."""
    plain = grammar.flatten(grammar.skeleton(tree)) if suite.flatten else grammar.skeleton(tree)
    owners = {n for n, k, rule, level, c in features(tree, suite) if k in common}
    return [(r[0], r[1], r[3], r[0] in owners) for r in grammar.rows(plain)]


def unusual_nodes(tree: Tree, usual: set[str], suite: Suite = DEFAULT) -> list[tuple[int, str]]:
    """Nodes none of whose features is usual in the group."""
    owned: dict[int, set[str]] = {}
    for n, k, *_ in features(tree, suite):
        owned.setdefault(n, set()).add(k)
    atoms = {r[0]: r[3] for r in grammar.rows(grammar.flatten(grammar.skeleton(tree)) if suite.flatten else grammar.skeleton(tree))}
    return [(n, atoms[n]) for n in sorted(owned) if not owned[n] & usual]


def render_dot(nodes: list[tuple[int, int | None, str, bool]], legend: dict[str, tuple[int, int]] | None = None) -> str:
    """DOT text: common nodes filled; legend: feature -> (total, in this query)."""
    quote = lambda s: '"' + s.replace("\\", "\\\\").replace('"', '\\"') + '"'
    out = ["digraph statement {"]
    for n, parent, atom, common in nodes:
        out.append(f"  n{n} [label={quote(atom)}{', style=filled, fillcolor=lightblue' if common else ''}];")
        if parent is not None:
            out.append(f"  n{parent} -> n{n};")
    if legend:
        rows = "\\n".join(f"{readable(c)}: {a} in the group, {b} here" for c, (a, b) in sorted(legend.items()))
        out.append(f"  legend [shape=note, label={quote(rows)}];".replace("\\\\n", "\\n"))
    return "\n".join([*out, "}"])
