"""One application of one rule to given frames, by plan or by tree; nothing is stored."""

from __future__ import annotations

from pyspark.sql import DataFrame

from treefix.engines.context import Given
from treefix.engines.plan import PlanRule
from treefix.engines.tree import TreeRule
from treefix.operators.reducer import join_up, reduce_tree
from treefix.plans.stats import Stats, best_tree, collect, useful_keys
from treefix.plans.trees import JoinTree
from treefix.rules import Atom, Program, Rule, Schemas


def prepared(rule: Rule, facts: dict[str, DataFrame]) -> tuple[dict[str, DataFrame], Schemas, Stats]:
    """Facts as sets without nulls, their types, and their statistics."""
    used = {a.pred for a in rule.body}
    frames = {p: df.dropna().distinct() for p, df in facts.items() if p in used}
    schemas = Schemas({p: [t for _, t in df.dtypes] for p, df in frames.items()})
    return frames, schemas, Stats({p: collect(df) for p, df in frames.items()})


def _columns(rule: Rule, schemas: Schemas) -> tuple[tuple[str, str], ...]:
    own = Schemas(dict(schemas.types))
    head = Atom("head_", rule.head.terms)  # under a name that no body has
    own.infer(Program((Rule(head, rule.body, rule.builtins),)))
    names = [getattr(t, "name", f"c{n}") for n, t in enumerate(rule.head.terms)]
    names = [v if names.index(v) == n else f"{v}{n}" for n, v in enumerate(names)]
    return tuple(zip(names, own.types["head_"])) or (("flag_", "boolean"),)


def by_plan(rule: Rule, facts: dict[str, DataFrame], order: str = "greedy", counts: bool = False, watch=None) -> DataFrame:
    frames, schemas, stats = prepared(rule, facts)
    return PlanRule(rule, _columns(rule, schemas), order).whole(Given(frames, stats, counts, watch, None if counts else useful_keys(rule, frames, stats)))


def tree_of(rule: Rule, facts: dict[str, DataFrame], tree: JoinTree | None = None, pivot_sweep: str = "auto") -> tuple[TreeRule, Given]:
    frames, schemas, stats = prepared(rule, facts)
    types = {t.name: k for a in rule.body for t, k in zip(a.terms, schemas.types[a.pred]) if hasattr(t, "name")}
    return TreeRule(rule, _columns(rule, schemas), tree or best_tree(rule, stats), types, pivot_sweep), Given(frames, stats)


def by_tree(rule: Rule, facts: dict[str, DataFrame], tree: JoinTree | None = None, counts: bool = False, watch=None) -> DataFrame:
    own, here = tree_of(rule, facts, tree)
    here.counts, here.watch = counts, watch or here.watch
    here.keys = None if counts else useful_keys(rule, here.given, here.stats)
    return own.whole(here)


def reduced_nodes(rule: Rule, facts: dict[str, DataFrame], tree: JoinTree | None = None, pivot: int | None = None) -> list[DataFrame]:
    """The bags after two sweeps, or after three with a pivot: what takes part in some answer."""
    own, here = tree_of(rule, facts, tree)
    frames = [own.fill(p, here).select(*own.vars(p)) for p in own.tree.nodes]
    return reduce_tree(own.tree, frames, pivot)


def answers(rule: Rule, facts: dict[str, DataFrame], tree: JoinTree | None = None, pivot: int | None = None) -> DataFrame:
    """Head bindings from reduced nodes."""
    own, _ = tree_of(rule, facts, tree)
    return join_up(own.tree, reduced_nodes(rule, facts, own.tree, pivot), rule, False)
