"""Atoms as scans and heads as projections."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.rules import Atom, Bind, Builtin, Compare, Const, Rule
from treefix.store import COUNT


def scan_atom(atom: Atom, facts: DataFrame, keep: set[str] | None = None) -> DataFrame:
    """Bindings of an atom: constants and repeated variables filter, arguments become variables. The filters
    and the chosen columns reach the scan of the facts."""
    where, out = [], {}
    for t, column in zip(atom.terms, facts.columns):
        c = F.col(f"`{column}`")
        if isinstance(t, Const):
            where.append(c == F.lit(t.value))
        elif t.name in out:
            where.append(c == out[t.name])
        else:
            out[t.name] = c
    if where:
        facts = facts.where(reduce(lambda a, b: a & b, where))
    return facts.select(*[c.alias(v) for v, c in out.items() if keep is None or v in keep])


def apply_builtins(df: DataFrame, builtins: tuple[Builtin, ...], done: set[int], known: set[str]) -> DataFrame:
    """Those built-ins whose variables are there and that were not applied yet."""
    again = True
    while again:
        again = False
        for n, b in enumerate(builtins):
            if n not in done and set(b.vars) <= known:
                done.add(n)
                again = True
                if isinstance(b, Compare):
                    df = df.where(F.expr(b.text))
                else:
                    df = df.withColumn(b.var, F.expr(b.text))
                    known.add(b.var)
    return df


def project_head(rule: Rule, bindings: DataFrame, columns: list[str], count: str | None = COUNT) -> DataFrame:
    """Head facts of bindings, with constants and repeated variables; the count column stays if there is one."""
    terms = [(F.lit(t.value) if isinstance(t, Const) else F.col(t.name)).alias(c) for t, c in zip(rule.head.terms, columns)]
    if not terms:
        terms = [F.lit(True).alias(columns[0])]
    return bindings.select(*terms, *([count] if count and count in bindings.columns else []))


def later_binds(rule: Rule) -> set[str]:
    return {v for b in rule.builtins if isinstance(b, Bind) for v in b.vars}
