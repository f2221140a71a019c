"""Conjunctive rules over DataFrames: bodies are equi-joins on shared variables, recursion is a semi-naive loop."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import digest
from ..tables import table

ANY = "_"


@dataclass(frozen=True)
class Atom:
    """A predicate over variables; "_" stands for anything. Negated atoms only filter."""

    name: str
    args: tuple[str, ...]
    negated: bool = False


@dataclass(frozen=True)
class Collect:
    """Gathers a variable for all valuations of the others in the head, and digests it."""

    kind: str  # list, bag or set
    variable: str
    alias: str


@dataclass
class Rule:
    """head :- body, where; `make` computes head variables from body variables; lower priority runs first."""

    head: Atom
    body: list[Atom]
    where: Callable[[], Column] | None = None
    make: dict[str, Callable[[], Column]] = field(default_factory=dict)
    collect: Collect | None = None
    by: tuple[str, ...] = ()
    priority: int = 0
    name: str = ""


class FactBase(dict):
    """One DataFrame per predicate, its columns in the predicate's order."""

    @classmethod
    def from_nodes(cls, nodes: DataFrame) -> FactBase:
        """Node(N), Atom(N, f), Child(Nc, Np, n), Own(N, f), Const(f). A node's name is the pair of its tree and number."""
        name = lambda c: F.concat_ws(":", "tree_id", c)
        base = nodes.select(name("node_id").alias("n"), F.when(F.col("parent_id").isNotNull(), name("parent_id")).alias("p"), "child_idx", "atom", "is_const", "height")
        return cls(
            Node=base.select("n"), Atom=base.select("n", "atom"), Child=base.where("p is not null").select("n", "p", F.col("child_idx").cast("string").alias("i")),
            Own=base.select("n", "atom"), Const=base.where("is_const").select("atom").distinct(), Height=base.select("n", F.col("height").cast("string").alias("h")),
        )


def _bound(facts: DataFrame, args: tuple[str, ...]) -> DataFrame:
    """A predicate's rows with variables as columns; quoted arguments are constants."""
    cols = facts.columns
    out, seen = facts.toDF(*[f"_{k}" for k in range(len(cols))]), {}
    for k, a in enumerate(args):
        if a.startswith("'"):
            out = out.where(F.col(f"_{k}") == a.strip("'"))
        elif a != ANY:
            if a in seen:
                out = out.where(F.col(f"_{k}") == F.col(f"_{seen[a]}"))
            else:
                seen[a] = k
    return out.select(*(F.col(f"_{k}").alias(a) for a, k in seen.items())).distinct() if ANY in args or len(seen) < len(args) else out.select(*(F.col(f"_{k}").alias(a) for a, k in seen.items()))


def evaluate(rule: Rule, facts: FactBase, delta: dict[str, DataFrame] | None = None) -> DataFrame:
    """The head's rows. With delta, at least one body atom must come from it (semi-naive)."""
    positive = [a for a in rule.body if not a.negated]
    if delta is None:
        choices = [[facts[a.name] for a in positive]]
    else:
        choices = [[delta[a.name] if j == k else facts[a.name] for j, a in enumerate(positive)] for k, x in enumerate(positive) if x.name in delta]
    out = None
    for sources in choices:
        rows = None
        for a, source in zip(positive, sources, strict=True):
            more = _bound(source, a.args)
            shared = [c for c in more.columns if rows is not None and c in rows.columns]
            if rows is not None and not shared:
                raise ValueError(f"{rule.name}: the body's atoms share no variable")
            rows = more if rows is None else rows.join(more, shared)
        for a in rule.body:
            if a.negated:
                no = _bound(facts[a.name], a.args)
                rows = rows.join(no, [c for c in no.columns if c in rows.columns], "left_anti")
        if rule.where:
            rows = rows.where(rule.where())
        if rule.collect:
            c = rule.collect
            gathered = F.collect_list(c.variable) if c.kind != "set" else F.collect_set(c.variable)
            fold = {"list": digest.list_digest, "bag": digest.bag_digest, "set": digest.set_digest}[c.kind]
            rows = rows.groupBy(*rule.by).agg(fold(gathered).alias(c.alias))
        for name, expression in rule.make.items():
            rows = rows.withColumn(name, expression())
        heads = rows.select(*(F.lit(a.strip("'")).alias(f"_{k}") if a.startswith("'") else F.col(a).alias(f"_{k}") for k, a in enumerate(rule.head.args))).distinct()
        out = heads if out is None else out.unionByName(heads).distinct()
    return out


def fixpoint(rules: list[Rule], facts: FactBase, max_iter: int = 64) -> FactBase:
    """Adds what the rules derive until nothing is new; each round's news are written before the next.

    Rules with a collection are evaluated on all facts in every round (their groups must be whole)."""
    facts = FactBase(facts)
    delta: dict[str, DataFrame] | None = None
    for step in range(max_iter):
        news: dict[str, DataFrame] = {}
        for rule in sorted(rules, key=lambda r: r.priority):
            if any(not a.negated and a.name not in facts for a in rule.body):
                continue
            if delta is not None and not any(a.name in delta for a in rule.body):
                continue
            got = evaluate(rule, facts, None if delta is None or rule.collect else delta)
            if rule.head.name in facts:
                known = facts[rule.head.name].toDF(*got.columns)
                got = got.join(known, got.columns, "left_anti")
            news[rule.head.name] = got if rule.head.name not in news else news[rule.head.name].unionByName(got).distinct()
        news = {k: table(v, f"{k}-{step}") for k, v in news.items()}
        news = {k: v for k, v in news.items() if v.limit(1).count()}
        if not news:
            return facts
        for k, v in news.items():
            facts[k] = v if k not in facts else facts[k].unionByName(v.toDF(*facts[k].columns))
        delta = news
    raise RuntimeError("no fixpoint within max_iter rounds")


def descendant_rules() -> list[Rule]:
    """The base relabelling as rules with the strict leaf policy; a level's bag needs a multiset, so children go by name."""
    first = Rule(Atom("IterF", ("n", "f", "'0'")), [Atom("Atom", ("n", "f"))], name="level 0")
    step = Rule(
        Atom("IterF", ("p", "f", "m")),
        [Atom("IterF", ("c", "fc", "k")), Atom("Child", ("c", "p", ANY)), Atom("Atom", ("p", "fp")), Atom("Height", ("p", "h"))],
        where=lambda: F.col("k").cast("int") + 1 < F.col("h").cast("int"),
        collect=Collect("bag", "fc", "bag"),
        by=("p", "fp", "k"),
        make={"f": lambda: digest.list_digest(F.array("fp", "bag")), "m": lambda: (F.col("k").cast("int") + 1).cast("string")},
        priority=1,
        name="level n",
    )
    own = Rule(Atom("Own", ("n", "f")), [Atom("IterF", ("n", "f", ANY))], priority=2, name="own")
    return [first, step, own]


def equality_skeleton(op: str = "=") -> Rule:
    """A comparison with a constant on its right and none on its left, by operator and left atom."""
    return Rule(
        Atom("Own", ("p", "f")),
        [Atom("Atom", ("p", f"'{op}'")), Atom("Child", ("r", "p", "'2'")), Atom("Atom", ("r", "fr")), Atom("Const", ("fr",)), Atom("Child", ("l", "p", "'1'")), Atom("Atom", ("l", "fl")), Atom("Const", ("fl",), negated=True)],
        make={"f": lambda: digest.list_digest(F.array(F.lit(op), F.col("fl"), F.lit("?")))},
        name=f"skeleton {op}",
    )
