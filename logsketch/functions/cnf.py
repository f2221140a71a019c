"""Boolean formulas of syntax trees as clause sets: conjunctive form, disjunctive form, and back to text.

A literal is a node without connectives below; it is named by its subtree's content, so that equal literals of
different statements are one. A negated formula is the dual: its disjunctive form with every literal turned.
"""

from __future__ import annotations

from itertools import product

from .digest import key
from .grammar import CONNECTIVES, Tree

MAX_CLAUSES = 256
Clause = frozenset  # of (literal text, positive)


class TooMany(ValueError):
    """The clause set would pass max_clauses."""


def text(t: Tree) -> str:
    """A tree as one string, apart from any other tree's."""
    return t.atom if not t.kids else f"{t.atom}({' '.join(map(text, t.kids))})"


def is_formula(t: Tree) -> bool:
    return t.atom in CONNECTIVES and bool(t.kids)


def _clauses(t: Tree, positive: bool, conjunctive: bool, limit: int) -> set[Clause]:
    if t.atom == "NOT" and t.kids:
        return _clauses(t.kids[0], not positive, conjunctive, limit)
    if t.atom in ("AND", "OR") and t.kids:
        parts = [_clauses(k, positive, conjunctive, limit) for k in t.kids]
        # Under negation AND and OR change places; a connective gathers in its own form and distributes in the other.
        gathers = ((t.atom == "AND") == positive) == conjunctive
        if gathers:
            out = set().union(*parts)
        else:
            out = {Clause()}
            for p in parts:
                if len(out) * len(p) > 64 * limit:
                    raise TooMany(len(out) * len(p))
                out = {a | b for a, b in product(out, p)}
        if len(out) > limit:
            raise TooMany(len(out))
        return out
    return {Clause({(text(t), positive)})}


def to_cnf(t: Tree, max_clauses: int = MAX_CLAUSES, absorb: bool = False) -> set[Clause]:
    """Clauses (any literal holds) of which all hold."""
    out = _clauses(t, True, True, max_clauses)
    return simplify(out) if absorb else out


def to_dnf(t: Tree, max_clauses: int = MAX_CLAUSES, absorb: bool = False) -> set[Clause]:
    """Clauses (all literals hold) of which any holds."""
    out = _clauses(t, True, False, max_clauses)
    return simplify(out) if absorb else out


def simplify(clauses: set[Clause]) -> set[Clause]:
    """Without clauses that hold both a literal and its negation, and without supersets of others."""
    some = {c for c in clauses if not any((x, not p) in c for x, p in c)}
    return {c for c in some if not any(d < c for d in some)}


def literals(t: Tree) -> list[Tree]:
    """The literals of a formula, left to right."""
    if t.atom in CONNECTIVES and t.kids:
        return [x for k in t.kids for x in literals(k)]
    return [t]


def clause_key(c: Clause) -> str:
    """A clause's identifier: the set digest of its literals' texts."""
    return key("S", [x if p else f"NOT {x}" for x, p in c])


def formula_key(clauses: set[Clause]) -> str:
    return key("S", map(clause_key, clauses))


def to_sql(clauses: set[Clause], render) -> str:
    """A conjunctive form as a predicate; render(literal text) gives a literal's SQL."""
    one = lambda c: "(" + " OR ".join(render(x) if p else f"NOT ({render(x)})" for x, p in sorted(c)) + ")"
    return " AND ".join(sorted(map(one, clauses))) or "TRUE"
