"""Statistics of predicates and the cost model for trees and join orders."""

from __future__ import annotations

from dataclasses import dataclass, field
from math import prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.plans.trees import JoinTree, hypertree_width, search
from treefix.rules import Atom, Const, Rule, Var


@dataclass
class PredStats:
    rows: float = 1.0
    distinct: list[float] = field(default_factory=list)


def collect(df: DataFrame) -> PredStats:
    """Rows and distinct values of each column, in one pass."""
    named = [F.approx_count_distinct(c).alias(f"d{n}") for n, c in enumerate(df.columns)]
    row = df.agg(F.count(F.lit(1)).alias("rows"), *named).first()
    return PredStats(float(row["rows"]), [float(max(1, row[f"d{n}"])) for n in range(len(df.columns))])


class Stats(dict):
    """``PredStats`` by predicate; unknown ones count as one row."""

    def of(self, atom: Atom) -> tuple[float, dict[str, float]]:
        """Estimated rows of an atom's scan and distinct values by variable."""
        s = self.get(atom.pred) or PredStats(1.0, [1.0] * len(atom.terms))
        rows, seen = max(s.rows, 1.0), {}
        for t, d in zip(atom.terms, s.distinct or [1.0] * len(atom.terms)):
            if isinstance(t, Const) or t.name in seen:
                rows /= max(d, 1.0)
            elif isinstance(t, Var):
                seen[t.name] = d
        rows = max(rows, 1.0)
        return rows, {v: min(d, rows) for v, d in seen.items()}

    def join_rows(self, atoms: list[Atom]) -> float:
        """The product of rows, divided for each shared variable by all but its smallest distinct count."""
        known = [self.of(a) for a in atoms]
        rows = prod(r for r, _ in known)
        for v in {v for _, d in known for v in d}:
            counts = sorted(d[v] for _, d in known if v in d)
            rows /= prod(counts[1:])
        return max(rows, 1.0)

    def extend(self, rules: list[Rule]) -> None:
        """Derived predicates: at least the estimated heads of their rules, at most all values of the columns."""
        for r in rules:
            distinct = {}
            for a in r.body:
                for v, d in self.of(a)[1].items():
                    distinct[v] = min(d, distinct.get(v, d))
            heads = [distinct.get(t.name, 1.0) if isinstance(t, Var) else 1.0 for t in r.head.terms]
            rows = min(self.join_rows(list(r.body)), prod(heads))
            old = self.get(r.head.pred) or PredStats(1.0, [1.0] * len(heads))
            merged = [max(a, min(b, rows)) for a, b in zip(old.distinct or heads, heads)]
            self[r.head.pred] = PredStats(max(old.rows, rows), merged)


#: Columns with fewer distinct values a row, as estimated, aren't asked whether they are keys.
LIKELY = 0.8


def determined(known: set[str], atoms: list[tuple[Atom, set[str]]], keys: dict[str, frozenset[int]]) -> set[str]:
    """The known variables and all that have one value for each of theirs: an atom's key fixes its other variables. With each atom come the
    variables that the rows in question still hold of it."""
    known = set(known)
    while more := {v for a, held in atoms for n, t in enumerate(a.terms) if n in keys.get(a.pred, ()) and isinstance(t, Var) and t.name in known & held for v in held} - known:
        known |= more
    return known


def useful_keys(rule: Rule, frames: dict[str, DataFrame], stats: Stats) -> dict[str, frozenset[int]]:
    """Columns without a repeated value, by predicate. They are only asked for if they may let the head fix all variables of the body."""
    atoms = [(a, set(a.vars)) for a in rule.body]
    likely = {p: frozenset(n for n, d in enumerate(stats[p].distinct) if d >= LIKELY * stats[p].rows) for p in frames}
    if not any(likely.values()) or not set(rule.vars) <= determined(set(rule.head.vars), atoms, likely):
        return {}
    unique = lambda df, n: df.groupBy(df.columns[n]).count().where("count > 1").isEmpty()
    return {p: frozenset(n for n in sorted(likely[p]) if unique(frames[p], n)) for p in sorted(likely)}


def edge_cost(a: float, b: float) -> float:
    """Semi-joins along a tree edge."""
    return 2 * (a + b)


def tree_cost(tree: JoinTree, rule: Rule, stats: Stats) -> float:
    sizes = [stats.join_rows([rule.body[a] for a in g]) for g in tree.guard]
    return sum(sizes) + sum(edge_cost(sizes[p], sizes[c]) for c, p in enumerate(tree.parent) if p is not None)


def best_tree(rule: Rule, stats: Stats, k_max: int | None = None) -> JoinTree:
    """The cheapest tree under the cost model. Widths up to one above the least are tried unless told otherwise."""
    k = k_max or min(len(rule.body), hypertree_width(rule) + 1)
    found = search(rule, k, lambda g: stats.join_rows([rule.body[a] for a in g]), edge_cost)
    if found is None:
        raise ValueError(f"no tree of width {k} for {rule}")
    return found[0]


def greedy_order(atoms: list[Atom], first: int | None, stats: Stats) -> list[int]:
    """The given atom first (else the smallest), then the one that keeps the estimate least,
    connected ones before others."""
    left = list(range(len(atoms)))
    out = [first if first is not None else min(left, key=lambda i: stats.of(atoms[i])[0])]
    left.remove(out[0])
    while left:
        bound = {v for i in out for v in atoms[i].vars}
        done = [atoms[i] for i in out]
        nxt = min(left, key=lambda i: (not (bound & set(atoms[i].vars)) and bool(atoms[i].vars), stats.join_rows([*done, atoms[i]]), i))
        out.append(nxt)
        left.remove(nxt)
    return out
