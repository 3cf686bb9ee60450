"""The rule language: terms, atoms, rules, programs, their checks and analysis.

Syntax, one rule a line or ended by a full stop::

    Head(x, y) <- Body(x, z), Other(z, 'text', 3), z <= y, v := a * b.

Names are variables; quoted texts and numbers are constants; ``_`` is a variable of its
own at each place. ``%`` starts a comment. An atom may have no argument: ``Flag()``.
"""

from __future__ import annotations

import itertools
import re
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field
from typing import Any


class RuleError(ValueError):
    """A rule that cannot be parsed or is not safe."""


@dataclass(frozen=True)
class Var:
    name: str

    def __str__(self) -> str:
        return self.name


@dataclass(frozen=True)
class Const:
    value: Any

    def __str__(self) -> str:
        return "'" + self.value.replace("'", "\\'") + "'" if isinstance(self.value, str) else str(self.value)


Term = Var | Const


@dataclass(frozen=True)
class Atom:
    pred: str
    terms: tuple[Term, ...] = ()

    @property
    def vars(self) -> tuple[str, ...]:
        """Distinct variables in order of appearance."""
        return tuple(dict.fromkeys(t.name for t in self.terms if isinstance(t, Var)))

    def __str__(self) -> str:
        return f"{self.pred}({', '.join(map(str, self.terms))})"


@dataclass(frozen=True)
class Compare:
    """A condition in SQL over variables; no hyperedge of its own."""

    text: str
    vars: tuple[str, ...]

    def __str__(self) -> str:
        return self.text


@dataclass(frozen=True)
class Bind:
    """A new variable computed in SQL from bound ones."""

    var: str
    text: str
    vars: tuple[str, ...]

    def __str__(self) -> str:
        return f"{self.var} := {self.text}"


Builtin = Compare | Bind


@dataclass(frozen=True)
class Rule:
    head: Atom
    body: tuple[Atom, ...]
    builtins: tuple[Builtin, ...] = ()
    name: str = ""

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for a in self.body for v in a.vars))

    @property
    def carried(self) -> tuple[str, ...]:
        """Variables that the head or a computed value needs, so joins must keep them."""
        bound = {b.var for b in self.builtins if isinstance(b, Bind)}
        needed = [*self.head.vars, *(v for b in self.builtins if isinstance(b, Bind) for v in b.vars)]
        return tuple(dict.fromkeys(v for v in needed if v not in bound))

    def validate(self) -> None:
        """Safety: all head variables and inputs of built-ins are bound by the body."""
        if not self.body:
            raise RuleError(f"{self}: a rule needs a body atom")
        known = set(self.vars)
        for b in self.builtins:
            if missing := set(b.vars) - known:
                raise RuleError(f"{self}: {b} uses {', '.join(sorted(missing))}, which nothing binds")
            if isinstance(b, Bind):
                if b.var in known:
                    raise RuleError(f"{self}: {b.var} is bound twice")
                known.add(b.var)
        if missing := set(self.head.vars) - known:
            raise RuleError(f"{self}: head variables {', '.join(sorted(missing))} don't occur in the body")

    def __str__(self) -> str:
        return f"{self.head} <- {', '.join(map(str, [*self.body, *self.builtins]))}"


_TOKEN = re.compile(r"\s*(?:(?P<text>'(?:\\.|[^'\\])*')|(?P<number>-?\d+(?:\.\d+)?)|(?P<name>[A-Za-z_]\w*))\s*")
_HEAD = re.compile(r"\s*([A-Za-z_]\w*)\s*\((.*)\)\s*$", re.S)


def _split(text: str) -> list[str]:
    """At commas outside brackets and quotes."""
    out, depth, quoted, start, i = [], 0, False, 0, 0
    while i < len(text):
        c = text[i]
        if quoted:
            i += c == "\\"
            quoted = c != "'"
        elif c == "'":
            quoted = True
        elif c in "()":
            depth += 1 if c == "(" else -1
        elif c == "," and depth == 0:
            out.append(text[start:i])
            start = i + 1
        i += 1
    return [*out, text[start:]] if text[start:].strip() or out else []


def _statements(text: str) -> Iterable[str]:
    for line in re.split(r"\n", re.sub(r"%.*", "", text)):
        if line.strip():
            yield line.strip().removesuffix(".")


def _term(text: str, fresh: Iterable[int]) -> Term:
    m = _TOKEN.fullmatch(text)
    if not m:
        raise RuleError(f"not a term: {text!r}")
    if m["text"] is not None:
        return Const(re.sub(r"\\(.)", r"\1", m["text"][1:-1]))
    if m["number"] is not None:
        return Const(float(m["number"]) if "." in m["number"] else int(m["number"]))
    return Var(f"_any{next(iter(fresh))}" if m["name"] == "_" else m["name"])


def _atom(text: str, fresh: Iterable[int]) -> Atom:
    m = _HEAD.match(text)
    if not m:
        raise RuleError(f"not an atom: {text.strip()!r}")
    return Atom(m[1], tuple(_term(t, fresh) for t in _split(m[2])))


_WORDS = {"and", "or", "not", "in", "between", "like", "is", "null", "true", "false", "as", "bigint", "int", "string", "double", "cast"}


def _names(expression: str) -> tuple[str, ...]:
    """Variables of an SQL expression: names that are no function, word or quoted text."""
    bare = re.sub(r"'(?:\\.|[^'\\])*'", " ", expression)
    found = re.findall(r"\b([A-Za-z_]\w*)\b(?!\s*\()", bare)
    return tuple(dict.fromkeys(n for n in found if n.lower() not in _WORDS))


def parse_rule(text: str, name: str = "") -> Rule:
    head, arrow, body = text.partition("<-")
    if not arrow:
        raise RuleError(f"a rule needs '<-': {text!r}")
    fresh, atoms, builtins = itertools.count(), [], []
    for part in _split(body):
        if ":=" in part:
            var, _, expression = part.partition(":=")
            builtins.append(Bind(var.strip(), expression.strip(), _names(expression)))
        elif _HEAD.match(part) and not re.search(r"[<>=!]", re.sub(r"'[^']*'", "", part)):
            atoms.append(_atom(part, fresh))
        else:
            builtins.append(Compare(part.strip(), _names(part)))
    rule = Rule(_atom(head, fresh), tuple(atoms), tuple(builtins), name)
    rule.validate()
    return rule


@dataclass(frozen=True)
class Program:
    rules: tuple[Rule, ...]

    def __post_init__(self):
        arity: dict[str, int] = {}
        for a in (a for r in self.rules for a in (r.head, *r.body)):
            if arity.setdefault(a.pred, len(a.terms)) != len(a.terms):
                raise RuleError(f"{a.pred} occurs with {arity[a.pred]} and with {len(a.terms)} arguments")

    @property
    def preds(self) -> dict[str, int]:
        return {a.pred: len(a.terms) for r in self.rules for a in (r.head, *r.body)}

    @property
    def derived(self) -> set[str]:
        return {r.head.pred for r in self.rules}

    def __add__(self, other: Program) -> Program:
        return Program(self.rules + other.rules)


def parse_program(text: str, prefix: str = "r") -> Program:
    """Rules from text; ``name: rule`` names one, others are numbered."""
    found = []
    for n, line in enumerate(_statements(text)):
        m = re.match(r"\s*(\w+)\s*:(?!=)\s*(.*)$", line, re.S)
        found.append(parse_rule(m[2], m[1]) if m else parse_rule(line, f"{prefix}{n + 1}"))
    return Program(tuple(found))


@dataclass(frozen=True)
class Module:
    """Rules that one engine evaluates: ``standard``, ``tree`` or ``combined``, or a function (rule, columns of the head) -> object
    with the steps ``add``, ``delete``, ``rederive`` and ``whole``, each of which takes a round and returns head rows or None."""

    rules: Program
    engine: str | Callable[[Rule, tuple[tuple[str, str], ...]], object] = "combined"


def stratify(program: Program) -> list[tuple[Rule, ...]]:
    """Rules grouped by strongly connected head predicates, sources first."""
    edges = {p: set() for p in program.preds}
    for r in program.rules:
        edges[r.head.pred] |= {a.pred for a in r.body}
    index: dict[str, int] = {}
    low: dict[str, int] = {}
    stack: list[str] = []
    groups: list[set[str]] = []
    for start in edges:  # depth first, without recursion: a group comes after what it reads
        if start in index:
            continue
        work = [(start, iter(sorted(edges[start])))]
        index[start] = low[start] = len(index)
        stack.append(start)
        while work:
            node, rest = work[-1]
            nxt = next(rest, None)
            if nxt is None:
                work.pop()
                if work:
                    low[work[-1][0]] = min(low[work[-1][0]], low[node])
                if low[node] == index[node]:
                    group = set()
                    while node not in group:
                        group.add(stack.pop())
                    groups.append(group)
            elif nxt not in index:
                index[nxt] = low[nxt] = len(index)
                stack.append(nxt)
                work.append((nxt, iter(sorted(edges[nxt]))))
            elif nxt in stack:
                low[node] = min(low[node], index[nxt])
    layers = [tuple(r for r in program.rules if r.head.pred in g) for g in groups]
    return [x for x in layers if x]


def is_recursive(rules: Iterable[Rule]) -> bool:
    heads = {r.head.pred for r in rules}
    return any(a.pred in heads for r in rules for a in r.body)


def edges_of(rule: Rule) -> list[frozenset[str]]:
    return [frozenset(a.vars) for a in rule.body]


def is_acyclic(rule: Rule) -> bool:
    """Ear removal: drop variables of one edge and edges within others until nothing is left."""
    left = [set(e) for e in edges_of(rule)]
    changed = True
    while changed:
        changed = False
        for v in {v for e in left for v in e}:
            holders = [e for e in left if v in e]
            if len(holders) == 1:
                holders[0].discard(v)
                changed = True
        for n, e in enumerate(left):
            if any(e <= o for m, o in enumerate(left) if m != n):
                del left[n]
                changed = True
                break
    return len(left) <= 1 and not any(left)


def split_by_width(program: Program) -> tuple[Program, Program]:
    """The simple (acyclic) and the complex (cyclic) rules."""
    simple = tuple(r for r in program.rules if is_acyclic(r))
    return Program(simple), Program(tuple(r for r in program.rules if r not in simple))


@dataclass
class Schemas:
    """Argument types by predicate; those of derived predicates follow from rule bodies."""

    types: dict[str, list[str]] = field(default_factory=dict)

    def infer(self, program: Program) -> None:
        pending = True
        while pending:
            pending = False
            for r in program.rules:
                if r.head.pred in self.types:
                    continue
                known: dict[str, str] = {}
                for a in r.body:
                    for t, kind in zip(a.terms, self.types.get(a.pred, [])):
                        if isinstance(t, Var):
                            known.setdefault(t.name, kind)
                for b in r.builtins:
                    if isinstance(b, Bind) and all(v in known for v in b.vars):
                        known[b.var] = "bigint"
                kinds = [known.get(t.name) if isinstance(t, Var) else "string" if isinstance(t.value, str) else "double" if isinstance(t.value, float) else "bigint" for t in r.head.terms]
                if None not in kinds:
                    self.types[r.head.pred] = kinds
                    pending = True
        if missing := set(program.preds) - set(self.types):
            raise RuleError(f"no schema is known for {', '.join(sorted(missing))}: load facts or declare it")
