"""What a rule engine sees of a round, and a common frame for both kinds of engine."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.plans.stats import Stats
from treefix.rules import Rule
from treefix.store import COUNT, FRESH, Store, Table

COLUMNS = tuple[tuple[str, str], ...]


@dataclass
class Round:
    """Facts of one round by slice: ``full`` holds the change too, ``old`` lacks it.

    A slice that is known to be empty is None, so whole joins can be left out. ``keys``: columns of sets of facts that hold no value
    twice; None if that isn't known. ``scratch``: parts that nothing reads once the round's heads are written."""

    store: Store
    full: dict[str, Table]
    old: dict[str, Table]
    delta: dict[str, Table]
    stats: Stats
    counts: bool = True
    watch: Callable[[str], Callable[[DataFrame, str], DataFrame] | None] = lambda rule: None
    frames: dict[tuple[str, str], DataFrame] = field(default_factory=dict)
    keys: dict[str, frozenset[int]] | None = None
    scratch: list[str] = field(default_factory=list)

    def slice(self, pred: str, which: str) -> DataFrame | None:
        tables = {"full": self.full, "old": self.old, "delta": self.delta}[which]
        table = tables.get(pred)
        if table is None or (table.rows <= 0 and which != "old") or not table.layers:
            return None
        if which == "old" and table.rows <= 0:
            return None
        key = pred, which
        if key not in self.frames:
            self.frames[key] = self.store.read(table)
        return self.frames[key]

    def touches(self, rule: Rule) -> bool:
        return any(a.pred in self.delta and self.delta[a.pred].rows > 0 for a in rule.body)


class Given(Round):
    """A round over frames that are simply given: for evaluating a rule once, with nothing stored."""

    def __init__(self, frames: dict[str, DataFrame], stats: Stats, counts: bool = False, watch=None, keys: dict[str, frozenset[int]] | None = None):
        super().__init__(None, {}, {}, {}, stats, counts, watch or (lambda rule: None), keys=keys)
        self.given = frames

    def slice(self, pred: str, which: str) -> DataFrame | None:
        return self.given.get(pred) if which == "full" else None


def union(frames: list[DataFrame]) -> DataFrame | None:
    return reduce(lambda a, b: a.unionByName(b), frames) if frames else None


def flagged(rows: DataFrame, names: list[str], known: DataFrame | None, fresh_if_known: bool) -> DataFrame:
    """Rows marked fresh by whether their key is known (or is not)."""
    if known is None:
        return rows.withColumn(FRESH, F.lit(not fresh_if_known))
    marked = rows.join(known.select(*names).withColumn("known_", F.lit(True)), names, "left")
    found = F.col("known_").isNotNull() if fresh_if_known else F.col("known_").isNull()
    return marked.withColumn(FRESH, found).drop("known_")


#: A union of several frames that join over this many atoms together is written frame by frame: the driver holds a plan, and
#: what adaptive execution makes of it, for as long as it runs, and sixteen delta joins of ten atoms took over a gigabyte.
WIDE = 12


def apart(here: Round, frames: list[DataFrame], columns: COLUMNS, width: int, name: str) -> list[DataFrame]:
    """Frames of keys and counts, each written as a part of its own if the plan of their union would be wide."""
    if here.store is None or len(frames) < 2 or len(frames) * width <= WIDE:
        return frames
    paths = [here.store.put(f, columns, f"{name}-apart")[0] for f in frames]
    here.scratch += paths
    return [here.store.part(columns, p).drop(FRESH) for p in paths]


#: Stored tables above this are not shuffled for a small set of rows: those are written first, and if there are
#: no more than SMALL of them they are broadcast against the scan.
LARGE, SMALL = 200_000, 100_000


def marked(store: Store, rows: DataFrame, columns: COLUMNS, table: Table | None, fresh_if_known: bool, name: str, scratch: list[str]) -> DataFrame:
    """As ``flagged``, against a stored table. ``scratch`` gets the parts that only the result reads."""
    names = [c for c, _ in columns]
    if table is None or table.rows <= 0:
        return flagged(rows, names, None, fresh_if_known)
    known = store.read(table)
    if table.rows > LARGE and names:
        path, _, count = store.put(rows, columns, f"{name}-rows")
        scratch.append(path)
        rows = store.part(columns, path).drop(FRESH)
        if not count:
            return rows.withColumn(FRESH, F.lit(False))
        if count <= SMALL:
            known = known.join(F.broadcast(rows.select(*names)), names, "left_semi")
    return flagged(rows, names, known, fresh_if_known)


def summed(frames: list[DataFrame], names: list[str], counts: bool, sign: int = 1) -> DataFrame | None:
    """Head rows of several rules as distinct keys with signed counts."""
    rows = union([f if COUNT in f.columns else f.withColumn(COUNT, F.lit(1)) for f in frames])
    if rows is None:
        return None
    if not counts:
        return rows.select(*names).distinct().withColumn(COUNT, F.lit(0))
    return rows.groupBy(*names).agg((F.sum(COUNT) * sign).alias(COUNT))
