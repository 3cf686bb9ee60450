"""Plan-based rule evaluation: one binary-join plan for each atom that may be new."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from treefix.engines.context import COLUMNS, WIDE, Round, apart, union
from treefix.operators.bodies import counted, delta_joins, join_atoms
from treefix.operators.scan import project_head
from treefix.plans.stats import Stats, determined, greedy_order
from treefix.rules import Atom, Compare, Const, Rule, Var
from treefix.store import COUNT


#: Two atoms meet first only where they are estimated to give so many times fewer rows: estimates are rough.
PAIRED = 4


def paired(atoms: list[Atom], frames: list[DataFrame], order: list[int], stats: Stats, needed: set[str]) -> tuple[list[Atom], list[DataFrame], list[int]]:
    """The same joins, but an atom meets a later one before it meets the rows so far, as an atom of both their variables, where the two
    are estimated to give far fewer rows than it would give with those: what ties the later one to the rows so far then filters within the join."""
    rest, done, steps = list(order), [], []
    atoms, frames = list(atoms), list(frames)
    while rest:
        i = rest.pop(0)
        known = {v for a in done for v in a.vars}
        ties = [j for j in rest if set(atoms[j].vars) & known and set(atoms[j].vars) & set(atoms[i].vars) - known]
        j = min(ties, key=lambda j: stats.join_rows([atoms[i], atoms[j]]), default=None)
        if j is not None and PAIRED * stats.join_rows([atoms[i], atoms[j]]) < stats.join_rows([*done, atoms[i]]):
            rest.remove(j)
            done += [atoms[i], atoms[j]]
            outside = needed | known | {v for k in rest for v in atoms[k].vars}
            rows = join_atoms([atoms[i], atoms[j]], [frames[i], frames[j]], [0, 1], outside)
            steps.append(len(atoms))
            atoms.append(Atom("paired_", tuple(map(Var, rows.columns))))
            frames.append(rows)
        else:
            done.append(atoms[i])
            steps.append(i)
    return atoms, frames, steps


@dataclass
class PlanRule:
    """``order``: ``greedy`` puts the new atom first and joins small connected atoms next (where all facts are asked, two of them may
    meet first); ``written`` joins left to right."""

    rule: Rule
    columns: COLUMNS
    order: str = "greedy"

    @property
    def names(self) -> list[str]:
        return [c for c, _ in self.columns]

    def _order(self, stats: Stats):
        atoms = list(self.rule.body)
        return (lambda i: list(range(len(atoms)))) if self.order == "written" else (lambda i: greedy_order(atoms, i, stats))

    def _heads(self, bindings: DataFrame | None, counts: bool, once: bool = False) -> DataFrame | None:
        """``once``: no two bindings have the same head."""
        if bindings is None:
            return None
        heads = project_head(self.rule, bindings, self.names)
        return counted(heads, self.names, COUNT) if counts else heads if once else heads.distinct()

    def whole(self, here: Round) -> DataFrame | None:
        """One application to all facts."""
        atoms = list(self.rule.body)
        frames = [here.slice(a.pred, "full") for a in atoms]
        if any(f is None for f in frames):
            return None
        order = self._order(here.stats)(None if self.order == "greedy" else 0)
        if self.order == "greedy":
            atoms, frames, order = paired(atoms, frames, order, here.stats, {*self.rule.head.vars, *(v for b in self.rule.builtins for v in b.vars)})
        rows = join_atoms(atoms, frames, order, self.rule.head.vars, self.rule.builtins, here.watch(self.rule.name))
        once = here.keys is not None and bool(self.rule.head.vars) and set(self.rule.vars) <= determined(set(self.rule.head.vars), [(a, set(a.vars)) for a in self.rule.body], here.keys)
        return self._heads(rows, here.counts, once)

    def changed(self, here: Round) -> DataFrame | None:
        """Heads of instances that use a fact of the change, each instance once. Serves additions (``full`` holds the
        new facts) and deletions (``full`` still holds the lost ones)."""
        if not here.touches(self.rule):
            return None
        atoms = list(self.rule.body)
        joins = delta_joins(atoms, lambda j, which: here.slice(atoms[j].pred, which), self._order(here.stats), self.rule.head.vars, self.rule.builtins, here.watch(self.rule.name))
        if len(joins) * len(atoms) <= WIDE:
            return self._heads(union(joins), here.counts)
        return union(apart(here, [self._heads(j, here.counts) for j in joins], self.columns, len(atoms), self.rule.name))

    add = delete = changed

    def rederive(self, here: Round) -> DataFrame | None:
        """Nothing to restore: a plan keeps no rows, and counts of facts are kept by the caller."""
        return None

    def instances(self, here: Round, heads: DataFrame | None, keep: list[str] | None = None) -> DataFrame | None:
        """Bindings over all facts whose heads are among ``heads`` (distinct). These are joined first, as an atom with the head's
        terms, so the body is evaluated for them alone; a head value that the rule computes is compared at the end."""
        atoms = list(self.rule.body)
        frames = [here.slice(a.pred, "full") for a in atoms]
        if any(f is None for f in frames):
            return None
        builtins, wanted = self.rule.builtins, keep or list(self.rule.vars)
        if heads is None or not self.rule.head.terms:
            return join_atoms(atoms, frames, greedy_order(atoms, None, here.stats), wanted, builtins)
        terms = []
        for n, t in enumerate(self.rule.head.terms):
            if isinstance(t, Const) or t.name in self.rule.vars:
                terms.append(t)
            else:
                terms.append(Var(f"given{n}_"))
                builtins = (*builtins, Compare(f"given{n}_ = {t.name}", (f"given{n}_", t.name)))
        atoms, frames = [Atom("given_", tuple(terms)), *atoms], [heads, *frames]
        rows = join_atoms(atoms, frames, greedy_order(atoms, 0, here.stats), wanted, builtins)
        return rows.select(*[c for c in rows.columns if c in wanted])

    def supported(self, here: Round, heads: DataFrame) -> DataFrame | None:
        """Those of ``heads`` that the rule derives in one step: the query form of the oracle."""
        rows = self.instances(here, heads, list(dict.fromkeys(self.rule.head.vars)))
        return None if rows is None else project_head(self.rule, rows, self.names, None).distinct()
