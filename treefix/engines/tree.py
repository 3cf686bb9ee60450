"""Tree-based rule evaluation: bags filled by what is new, passes over the tree, deletion and rederivation.

Every node keeps the rows of its bag between rounds and updates, and a ledger of signed counts: how many
bindings of its guard project to a row. A row leaves as soon as one of its bindings is lost; the ledger
tells later whether another remains.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.engines.context import COLUMNS, WIDE, Round, apart, marked, union
from treefix.operators.bodies import counted, delta_joins, join_atoms
from treefix.operators.reducer import head_rows, label_add, label_delete, live, live_rows, use_pivot_sweep
from treefix.plans.stats import greedy_order
from treefix.plans.trees import JoinTree
from treefix.rules import Atom, Compare, Rule, Var
from treefix.store import COUNT, FRESH, Layer, Table, semi


@dataclass
class Bag:
    """The stored rows of a node, its ledger, and rows that deletions took in this update."""

    rows: Table
    ledger: tuple[str, ...] = ()
    suspects: tuple[str, ...] = ()


@dataclass
class TreeRule:
    rule: Rule
    columns: COLUMNS
    tree: JoinTree
    types: dict[str, str]
    pivot_sweep: str = "auto"
    labels: Callable[[int, int], str] = label_add
    bags: list[Bag] = field(default_factory=list)
    lean: bool = False

    def __post_init__(self):
        if not self.bags:
            self.bags = [Bag(Table(tuple((v, self.types[v]) for v in self.vars(p)) or (("any_", "boolean"),))) for p in self.tree.nodes]

    @property
    def names(self) -> list[str]:
        return [c for c, _ in self.columns]

    def borrowed(self, node: int) -> Atom | None:
        """The atom whose facts are a lean node's rows: its only one, none of whose variables the bag leaves out. Such a row has
        one binding, so it needs no ledger and never comes back while its fact is gone."""
        atoms = self.atoms(node)
        return atoms[0] if self.lean and len(atoms) == 1 and atoms[0].vars and set(atoms[0].vars) == self.tree.bag[node] else None

    @property
    def kept(self) -> list[int]:
        """Nodes with rows of their own."""
        return [p for p in self.tree.nodes if self.borrowed(p) is None]

    def _scan(self, node: int, here: Round, which: str) -> DataFrame | None:
        atom = self.borrowed(node)
        frame = here.slice(atom.pred, which)
        return None if frame is None else join_atoms([atom], [frame], [0], self.vars(node), self._builtins(node)).select(*self.vars(node))

    def vars(self, node: int) -> list[str]:
        return sorted(self.tree.bag[node])

    def atoms(self, node: int) -> list[Atom]:
        return [self.rule.body[a] for a in self.tree.atoms(node)]

    def _builtins(self, node: int) -> tuple[Compare, ...]:
        """Comparisons within one node are applied while its bag is filled."""
        inner = {v for a in self.atoms(node) for v in a.vars}
        return tuple(b for b in self.rule.builtins if isinstance(b, Compare) and set(b.vars) <= inner)

    def fill(self, node: int, here: Round, within: DataFrame | None = None) -> DataFrame | None:
        """All rows of a bag (or those among ``within``, which are distinct) with their numbers of bindings."""
        atoms = self.atoms(node)
        frames = [here.slice(a.pred, "full") for a in atoms]
        if any(f is None for f in frames):
            return None
        if within is not None and self.tree.bag[node]:  # the wanted rows first, as an atom of their own
            atoms, frames = [Atom("within_", tuple(map(Var, self.vars(node)))), *atoms], [within.select(*self.vars(node)), *frames]
        order = greedy_order(atoms, None if within is None else 0, here.stats)
        rows = join_atoms(atoms, frames, order, self.vars(node), self._builtins(node), here.watch(self.rule.name))
        return counted(self._flagless(rows, node), self.bags[node].rows.names, COUNT)

    def _flagless(self, rows: DataFrame, node: int) -> DataFrame:
        return rows.select(*self.vars(node)) if self.tree.bag[node] else rows.select(F.lit(True).alias("any_"))

    def _changed(self, node: int, here: Round) -> DataFrame | None:
        """Rows of a bag with bindings that use a fact of the change, and how many."""
        atoms = self.atoms(node)
        if not any(a.pred in here.delta for a in atoms):
            return None
        joins = delta_joins(atoms, lambda j, which: here.slice(atoms[j].pred, which), lambda i: greedy_order(atoms, i, here.stats), self.vars(node), self._builtins(node), here.watch(self.rule.name))
        bag = self.bags[node].rows
        if len(joins) * len(atoms) > WIDE:
            joins = apart(here, [counted(self._flagless(j, node), bag.names, COUNT) for j in joins], bag.columns, len(atoms), f"{self.rule.name}-{node}")
        else:
            joins = [self._flagless(j, node) for j in joins]
        return counted(union(joins), bag.names, COUNT) if joins else None

    def _stored(self, node: int, here: Round) -> DataFrame | None:
        rows = self.bags[node].rows
        return here.store.read(rows) if rows.rows > 0 else None

    def _passes(self, here: Round, changes: list[tuple[DataFrame | None, int]], label: Callable[[int, int], str], base: str = "full") -> DataFrame | None:
        """The union over pivots: a pass for each node that has changed rows. ``base``: the slice that lean nodes' stored rows are."""
        stored, held = [], []
        for p in self.tree.nodes:
            atom = self.borrowed(p)
            stored.append(self._stored(p, here) if atom is None else self._scan(p, here, base))
            table = None if atom is None else (here.old if base == "old" else here.full).get(atom.pred)
            held.append(self.bags[p].rows.rows if atom is None else max(table.rows, 0) if table else 0)
        found = []
        for pivot in self.tree.nodes:
            if not changes[pivot][1]:
                continue
            frames, sizes = [], []
            for p in self.tree.nodes:
                which, (change, rows) = label(pivot, p), changes[p]
                frames.append(live(which, self.bags[p].rows.names, stored[p], change if rows else None))
                sizes.append(live_rows(which, held[p], rows))
            if all(f is not None for f in frames):
                small = len(sizes) > 2 or self.pivot_sweep != "auto"  # two nodes meet in one join anyway
                start = pivot if small and use_pivot_sweep(sizes, pivot, self.pivot_sweep) else None
                found.append(head_rows(self.tree, frames, self.rule, self.names, start, here.counts, here.watch(self.rule.name)))
        return union(apart(here, found, self.columns, 3 * len(frames), self.rule.name)) if found else None

    def _write(self, here: Round, node: int, rows: DataFrame, what: str) -> tuple[str, int, int]:
        return here.store.put(rows, self.bags[node].rows.columns, f"{self.rule.name}-{node}-{what}")

    def _marked(self, here: Round, node: int, rows: DataFrame, fresh_if_known: bool, scratch: list[str]) -> DataFrame:
        bag = self.bags[node].rows
        return marked(here.store, rows, bag.columns, bag, fresh_if_known, f"{self.rule.name}-{node}", scratch)

    def _fresh(self, here: Round, node: int, path: str) -> DataFrame:
        bag = self.bags[node].rows
        return here.store.part(bag.columns, path).where(F.col(FRESH)).select(*bag.names)

    def _written(self, here: Round, losing: bool, what: str) -> tuple[list[tuple[DataFrame | None, int]], list[str | None]]:
        """For each node its changed rows, how many they are, and the part that holds them; nodes are written side by side."""

        def one(p: int) -> tuple[tuple[DataFrame | None, int], str | None]:
            if (atom := self.borrowed(p)) is not None:
                table = here.delta.get(atom.pred)
                return ((self._scan(p, here, "delta"), table.rows) if table and table.rows > 0 else (None, 0)), None
            rows = self._changed(p, here)
            if rows is None:
                return (None, 0), None
            rows = self._marked(here, p, rows, losing, scratch := [])
            path, fresh, _ = self._write(here, p, rows.withColumn(COUNT, -F.col(COUNT)) if losing else rows, what)
            here.store.drop(scratch)
            return (self._fresh(here, p, path), fresh), path

        with ThreadPoolExecutor(max(1, len(self.tree.nodes))) as pool:
            found = list(pool.map(one, self.tree.nodes))
        return [c for c, _ in found], [path for _, path in found]

    def add(self, here: Round) -> DataFrame | None:
        """Consequences of added facts: gains of the bags, a pass for each, then the gains are stored."""
        if not here.touches(self.rule):
            return None
        changes, paths = self._written(here, False, "gain")
        heads = self._passes(here, changes, self.labels, "old")
        for p in self.tree.nodes:
            if paths[p]:
                self.bags[p].ledger += (paths[p],)
                self.bags[p].rows = self.bags[p].rows.plus(Layer("add", paths[p], changes[p][1]))
        return heads

    def delete(self, here: Round) -> DataFrame | None:
        """Consequences that lost facts touch: losses of the bags become suspects, a pass for each, then they leave."""
        if not here.touches(self.rule):
            return None
        changes, paths = self._written(here, True, "loss")
        heads = self._passes(here, changes, label_delete)
        for p in self.tree.nodes:
            if paths[p]:
                bag = self.bags[p]
                bag.ledger += (paths[p],)
                if changes[p][1]:
                    bag.suspects += (paths[p],)
                    bag.rows = bag.rows.plus(Layer("del", paths[p], changes[p][1]))  # its other rows weren't stored
        return heads

    def rederive(self, here: Round) -> DataFrame | None:
        """Suspects that still have a binding return, and are passed through the tree like gains."""
        changes = []
        layers: list[Layer | None] = []
        for p in self.tree.nodes:
            bag = self.bags[p]
            if not bag.suspects:
                changes.append((None, 0))
                layers.append(None)
                continue
            names = bag.rows.names
            suspects = here.store.part(bag.rows.columns, *bag.suspects).where(F.col(FRESH)).select(*names).distinct()
            if here.counts:
                held = semi(here.store.part(bag.rows.columns, *bag.ledger), suspects, names)
                back = held.groupBy(*names).agg(F.sum(COUNT).alias(COUNT)).where(F.col(COUNT) > 0).select(*names)
            else:
                found = self.fill(p, here, suspects)
                back = found.select(*names) if found is not None else suspects.limit(0)
            path, rows, _ = self._write(here, p, back, "back")
            changes.append((self._fresh(here, p, path), rows))
            layers.append(Layer("add", path, rows))
        heads = self._passes(here, changes, self.labels)
        for p in self.tree.nodes:
            self.bags[p].rows = self.bags[p].rows.plus(layers[p])
            self.bags[p].suspects = ()
        return heads

    def whole(self, here: Round) -> DataFrame | None:
        """One-shot evaluation: every bag is filled from the facts, and nothing is kept."""
        frames = [self.fill(p, here) for p in self.tree.nodes]
        if any(f is None for f in frames):
            return None
        frames = [f.select(*self.bags[p].rows.names) for p, f in enumerate(frames)]
        return head_rows(self.tree, frames, self.rule, self.names, None, here.counts, here.watch(self.rule.name), here.keys)

    def compact(self, here: Round) -> None:
        """Many layers become one, and so does a long ledger."""
        for p in self.tree.nodes:
            bag = self.bags[p]
            bag.rows = here.store.compact(bag.rows, f"{self.rule.name}-{p}-rows")
            if len(bag.ledger) > 24:
                names = bag.rows.names
                rows = here.store.part(bag.rows.columns, *bag.ledger).groupBy(*names).agg(F.sum(COUNT).alias(COUNT)).where(F.col(COUNT) != 0)
                bag.ledger = (self._write(here, p, rows, "ledger")[0],)
