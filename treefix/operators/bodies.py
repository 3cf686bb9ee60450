"""Joins of atoms, whole or by what is new: the plan-based side of rule evaluation.

Bindings are rows whose columns are variables. Joins keep duplicates after a projection, so counts
of rows stay counts of bindings.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.operators.scan import apply_builtins, scan_atom
from treefix.rules import Atom, Builtin

#: (atom's number, "full" | "old" | "delta") -> facts of its predicate, or None if it is known to be empty
Slice = Callable[[int, str], DataFrame | None]


def join_atoms(atoms: list[Atom], frames: list[DataFrame], order: list[int], needed: Iterable[str], builtins: tuple[Builtin, ...] = (), watch: Callable[[DataFrame, str], DataFrame] | None = None) -> DataFrame:
    """Joins atoms in order; variables go as soon as neither a later atom, a built-in nor ``needed`` uses them."""
    done: set[int] = set()
    out, known = None, set()
    needed = set(needed)
    for step, i in enumerate(order):
        rest = {v for j in order[step + 1 :] for v in atoms[j].vars}
        keep = needed | rest | known | {v for n, b in enumerate(builtins) if n not in done for v in b.vars}
        here = scan_atom(atoms[i], frames[i], keep)
        if out is None:
            out = here
        else:
            shared = [v for v in here.columns if v in out.columns]
            out = out.join(here, shared) if shared else out.crossJoin(here)
            if watch:
                out = watch(out, f"join{step}")
        known = set(out.columns)
        out = apply_builtins(out, builtins, done, known)
        keep = needed | rest | {v for n, b in enumerate(builtins) if n not in done for v in b.vars}
        dropped = [c for c in out.columns if c not in keep]
        if dropped and len(dropped) < len(out.columns):
            out = out.drop(*dropped)
    return out


def delta_joins(atoms: list[Atom], slices: Slice, order_of: Callable[[int], list[int]], needed: Iterable[str], builtins: tuple[Builtin, ...] = (), watch=None) -> list[DataFrame]:
    """Bindings with at least one new fact, each in one of the joins: in the i-th the i-th atom is new, earlier
    atoms are old and later ones any. Joins with a side known to be empty are left out."""
    parts = []
    for i in range(len(atoms)):
        frames = [slices(j, "delta" if j == i else "old" if j < i else "full") for j in range(len(atoms))]
        if all(f is not None for f in frames):
            parts.append(join_atoms(atoms, frames, order_of(i), needed, builtins, watch))
    return parts


def counted(df: DataFrame, keys: list[str], name: str) -> DataFrame:
    """Distinct keys with how many rows have them (or the sum of their counts)."""
    total = F.sum(name) if name in df.columns else F.count(F.lit(1))
    return df.groupBy(*keys).agg(total.alias(name)) if keys else df.agg(total.alias(name)).where(F.col(name).isNotNull() & (F.col(name) != 0))
