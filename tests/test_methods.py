"""Worked examples, invariants, and engines against each other."""

from __future__ import annotations

import itertools
import random

import numpy as np
import pandas as pd
import pytest

from logsketch.functions import cnf, digest, grammar, skeleton
from logsketch.operators import compare, datalog, distance, fptree, linkage, relabel, rules, summary
from logsketch.operators.components import components

BASE_KEPT = rules.Suite(skeleton_ops=(), cnf=False, flatten=False, constants="keep")


def bag(sql, suite):
    out = {}
    for _, key, *_ in rules.features(grammar.parse(sql), suite):
        out[key] = out.get(key, 0) + 1
    return out


def d2(a, b):
    return sum((a.get(k, 0) - b.get(k, 0)) ** 2 for k in a.keys() | b.keys())


def condition(text):
    return grammar.parse(f"SELECT a FROM t WHERE {text}").kids[2].kids[0]


def holds(t, values):
    if t.atom == "AND":
        return all(holds(k, values) for k in t.kids)
    if t.atom == "OR":
        return any(holds(k, values) for k in t.kids)
    if t.atom == "NOT":
        return not holds(t.kids[0], values)
    return values[cnf.text(t)]


def test_small_query_features():
    q = "SELECT r_name FROM region WHERE r_regionkey < 3"
    found = rules.features(grammar.parse(q), BASE_KEPT)
    assert [sum(f[3] == level for f in found) for level in range(4)] == [11, 7, 4, 1]
    assert len(rules.features(grammar.parse(q), rules.Suite(cnf=False, constants="keep"))) == 24
    assert d2(bag(q, BASE_KEPT), bag(q.replace("3", "4"), BASE_KEPT)) == 8
    assert d2(bag(q, BASE_KEPT), bag(q.replace("r_regionkey <", "r_name <"), BASE_KEPT)) == 8
    assert d2(bag(q, rules.BASE), bag(q.replace("3", "4"), rules.BASE)) == 0


def test_and_growth_shares_clauses():
    two, three = (bag(f"SELECT a FROM t WHERE {c}", rules.Suite(levels=False, skeleton_ops=())) for c in ("a = b AND c = d", "a = b AND c = d AND e = f"))
    assert len(two.keys() & three.keys()) == 2 and d2(two, three) == 3


@pytest.mark.parametrize("text", ["(a = 1 AND b = 2) OR c = 3", "NOT (a = 1 AND (b = 2 OR c = 3))", "(a = 1 AND b = 2) OR (c = 3 AND d = 4) OR e = 5", "NOT (NOT a = 1 OR b = 2) AND NOT c = 3"])
def test_normal_forms_by_truth_table(text):
    t = condition(text)
    names = sorted({cnf.text(x) for x in cnf.literals(t)})
    for bits in itertools.product([False, True], repeat=len(names)):
        v = dict(zip(names, bits, strict=True))
        for absorb in (False, True):
            assert holds(t, v) == all(any(v[x] == p for x, p in c) for c in cnf.to_cnf(t, absorb=absorb))
            assert holds(t, v) == any(all(v[x] == p for x, p in c) for c in cnf.to_dnf(t, absorb=absorb))


def test_cnf_bound_raises_the_flag():
    text = " OR ".join(f"(a{k} = 1 AND b{k} = 2)" for k in range(12))
    with pytest.raises(cnf.TooMany):
        cnf.to_cnf(condition(text))
    assert any(r == "cnf-too-large" for _, _, r, _, _ in rules.features(grammar.parse(f"SELECT a FROM t WHERE {text}")))


def test_or_and_piggyback_differ():
    assert cnf.formula_key(cnf.to_cnf(condition("(a = 1 AND b = 2) OR c = 3"))) != cnf.formula_key(cnf.to_cnf(condition("a = 1 AND b = 2 AND c = 3")))


def test_equality_skeleton_sides():
    made = lambda c, mirror: [f for f in rules.features(grammar.parse(f"SELECT a FROM t WHERE {c}"), rules.Suite(levels=False, cnf=False, skeleton_ops=("=",), mirror=mirror))]
    assert [len(made(c, False)) for c in ("a = 1", "1 = a", "a = b", "1 = 2")] == [1, 0, 0, 0]
    assert len(made("1 = a", True)) == 1 and made("1 = a", True)[0][1] == made("a = 1", True)[0][1]


@pytest.mark.parametrize("text", ["", "  ", "-- only", "select 'open", "<html><p>x</p></html>", "word " * 20000, "SELECT " + "(" * 400, "SELECT a FROM", None])
def test_bad_text_is_rejected(text):
    with pytest.raises(grammar.Rejected):
        grammar.parse(text)


def test_digest_identities():
    a, b, c = ["a", "b", "a", "c"], ["a", "a", "b", "c"], ["a", "b", "c"]
    assert digest.key("L", a) != digest.key("L", b)
    assert digest.key("B", a) == digest.key("B", b) != digest.key("B", c)
    assert digest.key("S", a) == digest.key("S", c)


def _nodes(spark, texts):
    rows = [(t, *r) for t, q in enumerate(texts) for r in grammar.rows(grammar.parse(q))]
    return spark.createDataFrame(rows, grammar.NODES)


TEXTS = ["SELECT a, b FROM t WHERE a <> 5", "SELECT a FROM t WHERE a = 1 AND b IN (1, 2) ORDER BY a DESC", "SELECT count(*) FROM t INNER JOIN u ON x = y GROUP BY z"]


@pytest.mark.parametrize("leaf", ["carry", "strict"])
def test_joins_and_walk_give_the_same_labels(spark, leaf):
    got = {(r.tree_id, r.node_id, r.label) for r in relabel.relabel(_nodes(spark, TEXTS), leaf=leaf).collect()}
    want = {(t, n, k) for t, q in enumerate(TEXTS) for n, k, *_ in rules.features(grammar.parse(q), rules.Suite(skeleton_ops=(), cnf=False, flatten=False, constants="keep", leaf=leaf))}
    assert got == want


def test_rules_and_joins_give_the_same_labels(spark):
    nodes = _nodes(spark, TEXTS[:1])
    facts = datalog.fixpoint(datalog.descendant_rules(), datalog.FactBase.from_nodes(nodes))
    got = {(r[0], r[1]) for r in facts["Own"].distinct().collect()}
    want = {(f"{r.tree_id}:{r.node_id}", r.label) for r in relabel.relabel(nodes, leaf="strict").collect()}
    assert got == want


def test_skeleton_rule_by_joins(spark):
    facts = datalog.FactBase.from_nodes(_nodes(spark, TEXTS[1:2]))
    got = {r[1] for r in datalog.evaluate(datalog.equality_skeleton(), facts).collect()}
    assert got == {digest.key("L", ["=", "a", "?"])}


def test_tree_shape_and_level_subtree(spark):
    nodes = _nodes(spark, TEXTS)
    shaped = relabel.with_tree_shape(nodes.drop("height"))
    assert {(r.tree_id, r.node_id, r.height) for r in shaped.collect()} == {(r.tree_id, r.node_id, r.height) for r in nodes.collect()}
    cols = relabel.level_subtree(shaped, 2).where("tree_id = 0 and root = 1")
    assert sorted(r.atom for r in cols.collect()) == ["COLS", "COL_ID", "COL_ID", "a", "b"]


def test_feature_dict_grows_without_renumbering(spark):
    one = spark.createDataFrame([("b", "b"), ("a", "a")], "feature_key string, canonical string")
    two = spark.createDataFrame([("c", "c"), ("a", "a")], "feature_key string, canonical string")
    first = digest.FeatureDict().extend(one)
    second = first.extend(two)
    second.assert_unique()
    ids = {r.feature_key: r.feature_id for r in second.rows.collect()}
    assert ids == {"a": 0, "b": 1, "c": 2}


def _brute(d, link):
    groups, out = {i: [i] for i in range(len(d))}, []
    how = {"complete": max, "single": min, "average": lambda v: sum(v) / len(v)}[link]
    while len(groups) > 1:
        h, a, b = min((how([d[x][y] for x in groups[a] for y in groups[b]]), a, b) for a, b in itertools.combinations(sorted(groups), 2))
        groups[a] += groups.pop(b)
        out.append((a, b, h, len(groups[a])))
    return out


@pytest.mark.parametrize("link", ["complete", "single", "average"])
def test_linkage_equals_brute_force_under_ties(link):
    r = np.random.default_rng(0)
    for _ in range(60):
        x = r.integers(0, 5, (int(r.integers(2, 11)), 2))
        d = ((x[:, None] - x[None]) ** 2).sum(-1).astype(float)
        got = linkage.agglomerate(d, link)
        if link == "average":
            assert np.allclose([g[2] for g in got], [b[2] for b in _brute(d, link)])
        else:
            assert got == _brute(d, link)
            assert all(a[2] <= b[2] for a, b in itertools.pairwise(got))


def test_cut_orders_and_entanglement():
    assert linkage.agglomerate(np.abs(np.subtract.outer(range(4), range(4))) ** 2, "complete")[:2] == [(0, 1, 1.0, 2), (2, 3, 1.0, 2)]
    m = pd.DataFrame([(0, 0, 1, 1.0, 2), (1, 2, 3, 1.0, 2), (2, 0, 2, 3.0, 4)], columns=["step", "left", "right", "height", "size"])
    assert linkage.cut(m, range(4), k=2) == {0: 0, 1: 0, 2: 2, 3: 2} and linkage.cut(m, range(4), h=0.5) == {k: k for k in range(4)}
    assert sorted(linkage.leaf_order(m, range(4))) == [0, 1, 2, 3]
    assert compare.entanglement([1, 2, 3, 4], [2, 1, 3, 4]) == pytest.approx(0.1) and compare.entanglement([1, 2, 3, 4], [4, 3, 2, 1]) == 1
    assert compare.crossings([1, 2, 3, 4], [2, 1, 3, 4]) == 1 and compare.crossings([1, 2, 3, 4], [4, 3, 2, 1]) == 6
    tree = linkage.tree_of(m, range(4))
    assert compare.crossings(compare.untangle(tree, [3, 2, 1, 0]), [3, 2, 1, 0]) == 0


def _random_bag(spark, n=25, seed=1):
    r = random.Random(seed)
    return [(i, f, r.randint(1, 3)) for i in range(n) for f in r.sample(range(12), r.randint(1, 6))]


def test_distances_agree(spark):
    rows = _random_bag(spark)
    b = spark.createDataFrame(rows, "tree_id long, feature_id long, mult int")
    have = {}
    for i, f, m in rows:
        have.setdefault(i, {})[f] = m
    want = {(i, j): d2(have[i], have[j]) for i, j in itertools.combinations(sorted(have), 2)}
    for engine in ("index", "block"):
        assert {(r.i, r.j): r.d2 for r in distance.pairwise(b, engine=engine).collect()} == want
    for tau in (1.0, 1.5, 3.0):
        assert {(r.i, r.j): r.d2 for r in distance.within(b, tau).collect()} == {k: v for k, v in want.items() if v <= tau * tau}
    l1 = {(i, j): sum(abs(have[i].get(f, 0) - have[j].get(f, 0)) for f in have[i].keys() | have[j].keys()) for i, j in want}
    assert {(r.i, r.j): r.d for r in distance.pairwise(b, "l1").collect()} == l1
    # Components of near pairs first give the same clusters as all at once.
    whole = linkage.cut(linkage.hierarchical(b), have, h=3.0)
    split = linkage.cut(linkage.hierarchical(b, cut=3.0), have, h=3.0)
    assert whole == split


def test_near_pairs_without_a_common_feature(spark):
    rows = [(0, 0, 1), (1, 1, 1), (2, 2, 2), (3, 0, 1), (3, 1, 1), (4, 5, 9)]
    got = distance.within(spark.createDataFrame(rows, "tree_id long, feature_id long, mult int"), 1.5)
    assert {(r.i, r.j, r.d2) for r in got.collect()} == {(0, 1, 2), (0, 3, 1), (1, 3, 1)}


def test_quotes_in_statements(spark):
    rows = spark.createDataFrame([("SELECT a FROM t WHERE b = 'x union y'",), ("SELECT a FROM t WHERE b = 'it''s'",), ("SELECT a FROM t UNION SELECT a FROM u",)], "sql string")
    got = rows.select(skeleton.statement_class(rows.sql), skeleton.fingerprint(rows.sql)).collect()
    assert [tuple(r) for r in got[:2]] == [("SELECT", "SELECT a FROM t WHERE b = ?")] * 2 and got[2][0] == "UNION"


def test_components(spark):
    edges = spark.createDataFrame([(1, 2), (2, 3), (9, 8), (3, 3), (5, None)], "a long, b long")
    assert {r.node: r.component for r in components(edges).collect()} == {1: 1, 2: 1, 3: 1, 8: 8, 9: 8}
    chain = spark.createDataFrame([(k, k + 1) for k in range(40)], "a long, b long")
    assert {r.component for r in components(chain).collect()} == {0}


def test_prefix_tree_orders(spark):
    sets = [("y",)] * 3 + [("y", "a", "b"), ("a", "b", "c"), ("a", "b", "d")]
    rows = spark.createDataFrame([(0, k, x) for k, s in enumerate(sets) for x in s], "cluster long, set_id long, item string")
    for by, n in (("frequency", 7), ("popularity", 6)):
        tree = fptree.fp_tree(fptree.order_items(rows, by))
        assert tree.count() == n
        assert fptree.compression(tree, rows).first()["items"] == 12
        assert tree.where("depth = 1").agg({"count": "sum"}).first()[0] == 6
        e = fptree.Explorer(tree)
        top = e.unfold()
        assert e.path(e.unfold(top[0]["node_key"])[0]["node_key"])[0] == top[0]["item"]


def test_shrink_merge_and_seal():
    items = {"a": 1, "b(a)": 2, "c": 2, "d(c)": 2}
    assert set(summary.shrink(items)) == {"b(a)", "c", "d(c)"} and set(summary.shrink(items, strict=False)) == {"b(a)", "d(c)"}
    t = grammar.skeleton(grammar.parse(TEXTS[1]))
    have, whole = summary.seal(grammar.parse(TEXTS[1]))
    assert whole and cnf.text(summary.rebuild(have, "SELECT")) == cnf.text(t)
    assert summary.occurrences(summary.feature_tree("COL_ID(a)"), t) == 1
    merged = summary.merge({"WHERE(AND)": 1, "=(a ?)": 1}, [t], 1)
    assert all(summary.verify_merge(summary.feature_tree(c), [t], 1) for c in merged)


def test_readable_and_dot():
    assert summary.readable("=(a ?)") == "a = ?"
    assert summary.render_dot([(0, None, "SELECT", True), (1, 0, 'x"y', False)]).count("->") == 1


def test_flatten_makes_order_irrelevant():
    a, b = (bag(f"SELECT a FROM t WHERE {c}", rules.DEFAULT) for c in ("(a = 1 AND b = 2) AND c = 3", "c = 3 AND (b = 2 AND a = 1)"))
    assert a == b
