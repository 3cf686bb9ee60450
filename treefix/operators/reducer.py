"""Evaluation over a decomposition tree: live rows by label, the three-sweep reducer, the bottom-up join."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce as fold

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.operators.scan import apply_builtins, project_head
from treefix.plans.stats import determined
from treefix.plans.trees import JoinTree
from treefix.rules import Compare, Rule
from treefix.store import COUNT, minus, semi

STORED, GAIN, WITH_GAIN, LOSS, WITHOUT_LOSS = "stored", "gain", "stored+gain", "loss", "stored-loss"
PIVOT_RATIO = 3


def label_add(pivot: int, node: int) -> str:
    """Before the pivot old and new rows, after it old rows: every new combination once, by its last gain."""
    return GAIN if node == pivot else WITH_GAIN if node < pivot else STORED


def label_add_mirrored(pivot: int, node: int) -> str:
    """The mirror image, which counts each new combination by its first gain."""
    return GAIN if node == pivot else STORED if node < pivot else WITH_GAIN


def label_delete(pivot: int, node: int) -> str:
    """Before the pivot all stored rows, after it those not lost."""
    return LOSS if node == pivot else STORED if node < pivot else WITHOUT_LOSS


def live(label: str, keys: list[str], stored: DataFrame | None, change: DataFrame | None) -> DataFrame | None:
    """The five cases; None for a set known to be empty. ``change``: the gain, or the loss."""
    if label in (GAIN, LOSS):
        return change
    if label == STORED or change is None:
        return stored
    if label == WITH_GAIN:
        return change if stored is None else stored.unionByName(change)
    return None if stored is None else minus(stored, change, keys)


def live_rows(label: str, stored: int, change: int) -> int:
    """How many rows the cases have. A gain isn't stored yet, a loss still is."""
    return {GAIN: change, LOSS: change, STORED: stored, WITH_GAIN: stored + change, WITHOUT_LOSS: stored - change}[label]


def use_pivot_sweep(rows: list[int], pivot: int, mode: str = "auto", ratio: int = PIVOT_RATIO) -> bool:
    """The extra sweep pays if the pivot has over ``ratio`` times fewer rows than the largest node."""
    if mode != "auto":
        return mode == "always"
    return rows[pivot] * ratio < max(rows)


def _shared(a: DataFrame, b: DataFrame) -> list[str]:
    return [c for c in a.columns if c in b.columns]


def reduce_tree(tree: JoinTree, frames: list[DataFrame], pivot: int | None) -> list[DataFrame]:
    """Semi-joins along the edges: outwards from the pivot (if any), to the root, and from the root."""
    out = list(frames)
    if pivot is not None:
        for node, source in tree.order_from(pivot)[1:]:
            out[node] = semi(out[node], out[source], _shared(out[node], out[source]))
    order = tree.order_from(tree.root)
    for node, up in reversed(order[1:]):
        out[up] = semi(out[up], out[node], _shared(out[up], out[node]))
    for node, up in order[1:]:
        out[node] = semi(out[node], out[up], _shared(out[node], out[up]))
    return out


def join_up(tree: JoinTree, frames: list[DataFrame], rule: Rule, counts: bool, watch: Callable[[DataFrame, str], DataFrame] | None = None, keys: dict[str, frozenset[int]] | None = None) -> DataFrame:
    """Head bindings: each node joined with its children's results, kept to its bag and what the head and
    built-ins need. Counts are numbers of combinations of bag rows; without them rows are distinct. ``keys``:
    columns of sets of facts that hold no value twice; where they let the head fix all that the root's rows hold, these are distinct as they are."""
    done: set[int] = set()
    wanted = set(rule.carried) | {v for b in rule.builtins if isinstance(b, Compare) for v in b.vars}

    def up(node: int) -> DataFrame:
        out, factors = frames[node], []
        for n, child in enumerate(tree.children(node)):
            below = up(child)
            if COUNT in below.columns:
                below = below.withColumnRenamed(COUNT, f"{COUNT}{n}")
                factors.append(f"{COUNT}{n}")
            shared = _shared(out, below)
            out = out.join(below, shared) if shared else out.crossJoin(below)
            if watch:
                out = watch(out, f"up{node}")
        if factors:
            out = out.withColumn(COUNT, fold(lambda a, b: a * b, [F.col(f) for f in factors])).drop(*factors)
        names = [c for c in out.columns if c != COUNT]
        root = node == tree.root
        if root:
            out = apply_builtins(out, rule.builtins, done, set(names))
            keep = list(dict.fromkeys(rule.head.vars))
        else:
            parent_bag = tree.bag[tree.parent[node]]
            keep = [c for c in names if c in parent_bag or c in wanted]
        if set(keep) == set(names) and not root:
            return out if counts or COUNT not in out.columns else out.drop(COUNT)
        if root and not counts and keep and keys is not None:
            atoms = [(rule.body[a], set(rule.body[a].vars) & tree.bag[p] & set(names)) for p in tree.nodes for a in tree.atoms(p)]
            if set(names) <= determined(set(keep), atoms, keys):
                return out.select(*keep)
        if not counts:
            return out.select(*keep).distinct() if keep else out.limit(1).select(F.lit(True).alias("any_"))
        total = (F.sum(COUNT) if COUNT in out.columns else F.count(F.lit(1))).alias(COUNT)
        return out.groupBy(*keep).agg(total) if keep else out.agg(total).where(F.coalesce(F.col(COUNT), F.lit(0)) > 0)

    return up(tree.root)


def head_rows(tree: JoinTree, frames: list[DataFrame], rule: Rule, columns: list[str], pivot: int | None, counts: bool, watch=None, keys: dict[str, frozenset[int]] | None = None) -> DataFrame:
    """One pass of cross-node evaluation: reduce, join up, project to the head. Two nodes meet in one join, whose rows are
    the same whether the nodes are reduced before or not, so without a sweep from the pivot they aren't."""
    reduced = frames if pivot is None and len(frames) <= 2 else reduce_tree(tree, frames, pivot)
    return project_head(rule, join_up(tree, reduced, rule, counts, watch, keys), columns)
