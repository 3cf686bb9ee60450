"""Hypertree decompositions of rule bodies: validation, width, search by width and cost.

The search is the published one over (component, connecting variables) with a table of results; a node's bag
is its guard's variables within the component and the connection, which meets
all four conditions of a hypertree decomposition. Bodies have a handful of atoms.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from itertools import combinations

from treefix.rules import Rule, edges_of


@dataclass
class JoinTree:
    """Nodes 0..n-1, the root first. ``guard``: numbers of body atoms; ``enforced``: atoms
    whose variables lie within the bag and that no guard holds, joined here too."""

    bag: list[frozenset[str]]
    guard: list[tuple[int, ...]]
    parent: list[int | None]
    enforced: list[tuple[int, ...]] = field(default_factory=list)

    def __post_init__(self):
        self.enforced = self.enforced or [() for _ in self.bag]

    @property
    def nodes(self) -> range:
        return range(len(self.bag))

    @property
    def root(self) -> int:
        return self.parent.index(None)

    @property
    def width(self) -> int:
        return max(map(len, self.guard))

    def children(self, node: int) -> list[int]:
        return [c for c in self.nodes if self.parent[c] == node]

    def atoms(self, node: int) -> tuple[int, ...]:
        return self.guard[node] + self.enforced[node]

    def order_from(self, node: int) -> list[tuple[int, int | None]]:
        """(node, the neighbour it is reached from), breadth first from any node."""
        out, seen = [(node, None)], {node}
        for here, _ in out:
            near = [*self.children(here), *([] if self.parent[here] is None else [self.parent[here]])]
            for n in near:
                if n not in seen:
                    seen.add(n)
                    out.append((n, here))
        return out

    def subtree(self, node: int) -> list[int]:
        out = [node]
        for n in out:
            out += self.children(n)
        return out


def check_tree(tree: JoinTree, rule: Rule) -> list[str]:
    """Violations of the four conditions, and whether it is a tree at all; empty if it is valid."""
    edges, found = edges_of(rule), []
    if tree.parent.count(None) != 1 or len(tree.order_from(tree.root)) != len(tree.bag):
        return ["not one rooted tree"]
    for n, e in enumerate(edges):
        if not any(e <= b for b in tree.bag):
            found.append(f"atom {rule.body[n]} lies in no bag")
    for v in rule.vars:
        own = {p for p in tree.nodes if v in tree.bag[p]}
        if own:
            tops = [p for p in own if tree.parent[p] not in own]
            if len(tops) > 1:
                found.append(f"the nodes of variable {v} are not connected")
    for p in tree.nodes:
        held = frozenset().union(*(edges[a] for a in tree.guard[p]))
        if not tree.bag[p] <= held:
            found.append(f"bag of node {p} exceeds its guard")
        below = frozenset().union(*(tree.bag[q] for q in tree.subtree(p)))
        if not held & below <= tree.bag[p]:
            found.append(f"guard variables of node {p} come again below it")
    return found


def complete_tree(tree: JoinTree, rule: Rule) -> JoinTree:
    """Atoms of no guard are attached to a node whose bag covers them."""
    edges, held = edges_of(rule), {a for g in tree.guard for a in g}
    enforced = [list(e) for e in tree.enforced]
    for n in range(len(edges)):
        if n not in held and not any(n in e for e in enforced):
            enforced[next(p for p in tree.nodes if edges[n] <= tree.bag[p])].append(n)
    return JoinTree(tree.bag, tree.guard, tree.parent, [tuple(e) for e in enforced])


def trivial_tree(rule: Rule) -> JoinTree:
    """One node with all atoms: evaluation by one plan."""
    return JoinTree([frozenset(rule.vars)], [tuple(range(len(rule.body)))], [None])


def _parts(component: frozenset[int], bag: frozenset[str], edges: list[frozenset[str]]) -> list[frozenset[int]]:
    """Edges not covered by ``bag``, grouped by shared variables outside it."""
    left, out = [e for e in sorted(component) if not edges[e] <= bag], []
    while left:
        group, reach, grown = {left[0]}, set(edges[left[0]] - bag), True
        while grown:
            more = {e for e in left if e not in group and edges[e] & reach}
            grown = bool(more)
            group |= more
            reach |= set().union(*(edges[e] - bag for e in more)) if more else set()
        out.append(frozenset(group))
        left = [e for e in left if e not in group]
    return out


def _choices(component: frozenset[int], link: frozenset[str], edges: list[frozenset[str]], k: int) -> Iterator[tuple[tuple[int, ...], frozenset[str], list[frozenset[int]]]]:
    """Guards for a component: they hold its connection, touch it, and leave less than it."""
    inner = frozenset().union(*(edges[e] for e in component))
    for size in range(1, k + 1):
        for guard in combinations(range(len(edges)), size):
            held = frozenset().union(*(edges[e] for e in guard))
            if not link <= held or not (held & inner or not inner):
                continue
            bag = held & (link | inner)
            parts = _parts(component, bag, edges)
            if all(p != component and len(p) < len(component) or p < component for p in parts):
                yield guard, bag, parts


def _nested(tree: JoinTree, root: tuple[tuple[int, ...], frozenset[str]], below: list[JoinTree]) -> JoinTree:
    bag, guard, parent = [root[1]], [root[0]], [None]
    for t in below:
        base = len(bag)
        bag += t.bag
        guard += t.guard
        parent += [0 if p is None else p + base for p in t.parent]
    return JoinTree(bag, guard, parent)


def search(rule: Rule, k: int, node_cost: Callable[[tuple[int, ...]], float], edge_cost: Callable[[float, float], float]) -> tuple[JoinTree, float] | None:
    """The cheapest tree of width at most k: summed node costs and costs of tree edges."""
    edges = edges_of(rule)
    table: dict[tuple[frozenset[int], frozenset[str]], tuple[float, float, JoinTree] | None] = {}

    def solve(component: frozenset[int], link: frozenset[str]) -> tuple[float, float, JoinTree] | None:
        """(cost, size of the root, tree)."""
        key = component, link
        if key in table:
            return table[key]
        table[key] = None
        best = None
        for guard, bag, parts in _choices(component, link, edges, k):
            size = node_cost(guard)
            cost, below = size, []
            for p in parts:
                inner = frozenset().union(*(edges[e] for e in p))
                found = solve(p, inner & bag)
                if found is None:
                    break
                cost += found[0] + edge_cost(size, found[1])
                below.append(found[2])
            else:
                if best is None or (cost, len(guard)) < (best[0], best[3]):
                    best = cost, size, _nested(None, (guard, bag), below), len(guard)
        table[key] = best and best[:3]
        return table[key]

    found = solve(frozenset(range(len(edges))), frozenset())
    return found and (complete_tree(found[2], rule), found[0])


def enumerate_trees(rule: Rule, k: int, most: int = 10_000) -> Iterator[JoinTree]:
    """Trees of width at most k in the search's normal form, at most ``most``."""
    edges, count = edges_of(rule), 0

    def solve(component: frozenset[int], link: frozenset[str]) -> Iterator[JoinTree]:
        for guard, bag, parts in _choices(component, link, edges, k):
            yield from expand(guard, bag, parts, [])

    def expand(guard, bag, parts, below) -> Iterator[JoinTree]:
        if len(below) == len(parts):
            yield _nested(None, (guard, bag), below)
            return
        p = parts[len(below)]
        for t in solve(p, frozenset().union(*(edges[e] for e in p)) & bag):
            yield from expand(guard, bag, parts, [*below, t])

    for tree in solve(frozenset(range(len(edges))), frozenset()):
        yield complete_tree(tree, rule)
        count += 1
        if count == most:
            return


def hypertree_width(rule: Rule) -> int:
    for k in range(1, len(rule.body) + 1):
        if search(rule, k, lambda g: 1.0, lambda a, b: 0.0):
            return k
    return len(rule.body)


def structural_tree(rule: Rule) -> JoinTree:
    """A tree of least width with few nodes; blind to the data."""
    return search(rule, hypertree_width(rule), lambda g: float(len(g)), lambda a, b: 0.0)[0]
