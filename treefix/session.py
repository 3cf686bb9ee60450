"""``Reasoner``: load facts and rules, materialise, update, query.

One loop serves all engines. Deletions first overdelete everything that a lost fact may support, then
put back what still has support or is explicit, then additions (and what came back) are carried to the fixpoint. Engines
only differ in how one rule finds its consequences: plans for all rules (``standard``), trees for all (``tree``),
or trees for cyclic rules alone (``combined``).
"""

from __future__ import annotations

import copy
import time
import uuid
from collections import Counter, defaultdict
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from treefix.engines.context import COLUMNS, Round, marked, summed, union
from treefix.engines.plan import PlanRule
from treefix.engines.tree import TreeRule
from treefix.operators.reducer import label_add
from treefix.plans.stats import Stats, best_tree, collect, tree_cost
from treefix.plans.trees import JoinTree, check_tree, complete_tree, structural_tree, trivial_tree
from treefix.rules import Module, Program, RuleError, Rule, Schemas, is_acyclic, is_recursive, parse_program, split_by_width, stratify
from treefix.store import COUNT, FRESH, Layer, Store, Table, end_idle_threads, minus, semi, short_descriptions, work_dir

ENGINES = ("combined", "standard", "tree", "naive", "tree-naive")


@dataclass
class RunReport:
    """What a run did. ``history``: (phase, round, predicate, derived rows, new rows)."""

    task: str
    engine: str
    seconds: float = 0.0
    tree_seconds: float = 0.0
    rounds: int = 0
    history: list[tuple[str, int, str, int, int]] = field(default_factory=list)
    join_rows: int = 0
    added: int = 0
    deleted: int = 0
    observed: list[tuple[str, Observation]] = field(default_factory=list)

    def rows_through_joins(self) -> dict[str, int]:
        """Rows out of each rule's joins, if the session measures them."""
        out: dict[str, int] = defaultdict(int)
        for rule, seen in self.observed:
            try:
                out[rule] += seen.get["rows"]
            except Py4JError:  # the join was found to be empty at run time and left out
                pass
        self.join_rows = sum(out.values())
        return dict(out)


@dataclass
class State:
    explicit: dict[str, Table] = field(default_factory=dict)
    facts: dict[str, Table] = field(default_factory=dict)
    ledger: dict[str, tuple[str, ...]] = field(default_factory=dict)
    rules: list = field(default_factory=list)


class Reasoner:
    """``oracle``: ``count`` keeps numbers of derivations, ``query`` asks again. ``order``: of plans, ``greedy`` or ``written``.
    ``tree_choice``: ``cost``, ``width`` or ``trivial``. ``pivot_sweep``: ``auto``, ``always``, ``never``. ``measure``: watch join outputs. ``storage``: ``lean`` keeps no bag that a stored
    predicate already holds. ``deletion``: ``counting`` takes a fact when its last derivation goes, for programs without recursion."""

    def __init__(self, spark: SparkSession, path: str | None = None, engine: str = "combined", oracle: str = "count", order: str = "greedy", tree_choice: str = "cost", pivot_sweep: str = "auto", max_rounds: int = 10_000, measure: bool = False, labels=label_add, threads: int = 2, storage: str = "full", deletion: str = "rederive"):
        if engine not in ENGINES:
            raise ValueError(f"engine must be one of {', '.join(ENGINES)}")
        self.spark, self.engine, self.counts, self.order = spark, engine, oracle == "count", order
        self.tree_choice, self.pivot_sweep, self.max_rounds, self.measure, self.labels, self.threads = tree_choice, pivot_sweep, max_rounds, measure, labels, threads
        if storage not in ("full", "lean") or deletion not in ("rederive", "counting"):
            raise ValueError("storage is full or lean, deletion is rederive or counting")
        if deletion == "counting" and (engine != "standard" or not self.counts):
            raise ValueError("deletion by counts needs the standard engine with counts")
        self.storage, self.deletion = storage, deletion
        self.store = Store(spark, path or f"{work_dir(spark)}/treefix/{uuid.uuid4().hex}")
        end_idle_threads(spark)
        self.program, self.schemas, self.stats_, self.state = Program(()), Schemas(), Stats(), State()
        self.trees: dict[str, JoinTree] = {}
        self.engine_of: dict[str, object] = {}
        self.pending: dict[str, list[DataFrame]] = defaultdict(list)
        self.dropped_nulls: dict[str, int] = {}
        self.runs: list[RunReport] = []
        self.tree_seconds = 0.0

    # --- what is given

    def declare(self, pred: str, *types: str) -> Reasoner:
        self.schemas.types[pred] = list(types)
        return self

    def facts(self, pred: str, df: DataFrame) -> Reasoner:
        """Facts for the next materialisation. Columns are arguments in order; rows with a null are left out; map columns can't be facts."""
        kinds = [t for _, t in df.dtypes]
        if any(t.startswith("map") for t in kinds):
            raise RuleError(f"{pred}: a map can't be an argument")
        held = self.schemas.types.setdefault(pred, [] if df.columns == ["flag_"] else kinds)
        if len(held) != (0 if df.columns == ["flag_"] else len(kinds)):
            raise RuleError(f"{pred} has {len(held)} arguments, not {len(kinds)}")
        self.pending[pred].append(df)
        return self

    def facts_from(self, pred: str, path: str, fmt: str = "parquet", **options) -> Reasoner:
        return self.facts(pred, self.spark.read.format(fmt).options(**options).load(path))

    def rules(self, text: str | Program) -> Reasoner:
        more = parse_program(text, f"q{len(self.program.rules)}_") if isinstance(text, str) else text
        for r in more.rules:
            r.validate()
        self.program = self.program + more
        return self

    def module(self, module: Module) -> Reasoner:
        """Rules with an engine of their own; those of other modules, and rules given without, share the fixpoint loop with them."""
        if isinstance(module.engine, str) and module.engine not in ("combined", "standard", "tree"):
            raise ValueError("a module's engine must be combined, standard, tree or a function")
        self.engine_of |= {r.name: module.engine for r in module.rules.rules}
        return self.rules(module.rules)

    def with_tree(self, name: str, tree: JoinTree) -> Reasoner:
        """A tree of the user's for a rule; it must meet all conditions."""
        rule = self._rule(name)
        if problems := check_tree(tree, rule):
            raise ValueError("; ".join(problems))
        self.trees[name] = complete_tree(tree, rule)
        return self

    def _rule(self, name: str) -> Rule:
        return next(r for r in self.program.rules if r.name == name)

    def columns(self, pred: str) -> COLUMNS:
        types = self.schemas.types[pred]
        return tuple((f"a{n}", t) for n, t in enumerate(types)) or (("flag_", "boolean"),)

    def _named(self, pred: str, df: DataFrame) -> DataFrame:
        cols = self.columns(pred)
        if len(df.columns) != len(cols):
            raise RuleError(f"{pred} has {len(self.schemas.types[pred])} arguments, not {len(df.columns)}")
        return df.toDF(*[c for c, _ in cols]).select(*[F.col(c).cast(t).alias(c) for c, t in cols]).dropna(subset=[c for c, _ in cols]).distinct()

    # --- set up

    def _prepare(self, loads: dict[str, Table]) -> None:
        self.schemas.infer(self.program)
        for pred in {*self.program.preds, *self.schemas.types}:
            self.state.explicit.setdefault(pred, Table(self.columns(pred)))
            self.state.facts.setdefault(pred, Table(self.columns(pred)))
            self.state.ledger.setdefault(pred, ())
        known = {r.rule.name for r in self.state.rules}
        fresh = [r for r in self.program.rules if r.name not in known]
        if not fresh:
            return
        read = [p for p in loads if any(p in {a.pred for a in r.body} for r in fresh)]
        with ThreadPoolExecutor(self.threads) as pool:
            for p, s in zip(read, pool.map(lambda p: collect(self.store.read(loads[p])), read)):
                self.stats_[p] = s
        began = time.perf_counter()
        for layer in stratify(self.program):
            self.stats_.extend(list(layer))
        for r in fresh:
            self.state.rules.append(self._engine(r))
        self.tree_seconds += time.perf_counter() - began

    def _engine(self, rule: Rule) -> PlanRule | TreeRule:
        columns, engine = self.columns(rule.head.pred), self.engine_of.get(rule.name, self.engine)
        if callable(engine):
            return engine(rule, columns)
        tree_wanted = engine in ("tree", "tree-naive") or rule.name in self.trees or engine == "combined" and not is_acyclic(rule)
        if not tree_wanted or engine in ("standard", "naive"):
            return PlanRule(rule, columns, self.order)
        if rule.name not in self.trees:
            choose = {"cost": lambda: best_tree(rule, self.stats_), "width": lambda: structural_tree(rule), "trivial": lambda: trivial_tree(rule)}
            self.trees[rule.name] = choose[self.tree_choice]()
        if self.storage == "lean" and len(self.trees[rule.name].nodes) == 1:  # its one bag would hold all bindings
            return PlanRule(rule, columns, self.order)
        types = {t.name: k for a in rule.body for t, k in zip(a.terms, self.schemas.types[a.pred]) if hasattr(t, "name")}
        return TreeRule(rule, columns, self.trees[rule.name], types, self.pivot_sweep, self.labels, lean=self.storage == "lean")

    # --- rounds

    def _round(self, state: State, old: dict[str, Table], delta: dict[str, Table], report: RunReport) -> Round:
        def watch(rule: str):
            if not self.measure:
                return None

            def seen(df: DataFrame, where: str) -> DataFrame:
                o = Observation()
                report.observed.append((rule, o))
                return df.observe(o, F.count(F.lit(1)).alias("rows"))

            return seen

        return Round(self.store, state.facts, {**state.facts, **old}, delta, self.stats_, self.counts, watch)

    def _heads(self, state: State, here: Round, step: str) -> dict[str, list[DataFrame]]:
        """Every engine's consequences by head predicate; rules run side by side."""
        out: dict[str, list[DataFrame]] = defaultdict(list)
        with ThreadPoolExecutor(self.threads) as pool:
            for r, heads in zip(state.rules, pool.map(lambda r: getattr(r, step)(here), state.rules)):
                if heads is not None:
                    out[r.rule.head.pred].append(heads)
        return out

    def _commit(self, state: State, heads: dict[str, list[DataFrame]], known: dict[str, Table | None], fresh_if_known: bool, sign: int, what: str) -> dict[str, tuple[str, int, int]]:
        """One part for each head predicate: its keys, signed counts, and which are fresh."""

        def one(pred: str):
            names = [c for c, _ in self.columns(pred)]
            rows = summed(heads[pred], names, self.counts, sign)
            rows = marked(self.store, rows, self.columns(pred), known[pred], fresh_if_known, f"{pred}-{what}", scratch := [])
            written = self.store.put(rows, self.columns(pred), f"{pred}-{what}")
            self.store.drop(scratch)
            return pred, written

        with ThreadPoolExecutor(self.threads) as pool:
            out = dict(pool.map(one, sorted(heads)))
        for pred, (path, *_) in out.items():
            if self.counts:
                state.ledger[pred] = (*state.ledger[pred], path)
        return out

    def _add_loop(self, state: State, new: dict[str, Layer], report: RunReport) -> None:
        """Carries new facts (one layer a predicate) to the fixpoint."""
        n = 0
        while new:
            n += 1
            if n > self.max_rounds:
                raise RuntimeError(f"no fixpoint after {self.max_rounds} rounds")
            old = {p: state.facts[p] for p in new}
            for p, layer in new.items():
                state.facts[p] = state.facts[p].plus(layer)
            here = self._round(state, old, {p: Table(self.columns(p), (x,)) for p, x in new.items()}, report)
            heads = self._heads(state, here, "add")
            known = {p: state.facts[p] for p in heads}
            written = self._commit(state, heads, known, False, 1, f"add{n}")
            self.store.drop(here.scratch)
            new = {p: Layer("add", path, fresh) for p, (path, fresh, _) in written.items() if fresh}
            report.history += [("add", n, p, rows, fresh) for p, (_, fresh, rows) in sorted(written.items())]
            report.added += sum(x.rows for x in new.values())
        report.rounds += n

    def _delete_loop(self, state: State, lost: dict[str, Layer], report: RunReport) -> dict[str, list[str]]:
        """Overdeletes; the parts of overdeleted facts by predicate."""
        gone: dict[str, list[str]] = defaultdict(list)
        n = 0
        while lost:
            n += 1
            after = self._settled(state, {p: state.facts[p].plus(Layer("del", x.path, x.rows)) for p, x in lost.items()})
            delta = {p: Table(self.columns(p), (x,)) for p, x in lost.items()}
            here = self._round(state, after, delta, report)
            heads = self._heads(state, here, "delete")
            left = {**state.facts, **after}
            known = {p: left[p] for p in heads}
            written = self._commit(state, heads, known, True, -1, f"del{n}")
            self.store.drop(here.scratch)
            if self.deletion == "rederive":
                for p, x in lost.items():
                    gone[p].append(x.path)
            state.facts.update(after)
            lost = {}
            for p, (path, fresh, _) in written.items():
                if fresh and self.deletion == "counting":
                    path, fresh = self._without_support(state, p, path)
                if fresh:  # as a deletion the part's other rows take nothing: they aren't there any more
                    lost[p] = Layer("add", path, fresh)
            report.history += [("delete", n, p, rows, fresh) for p, (_, fresh, rows) in sorted(written.items())]
            report.deleted += sum(x.rows for x in lost.values())
        report.rounds += n
        return gone

    def _settled(self, state: State, tables: dict[str, Table]) -> dict[str, Table]:
        """What several atoms are about to read without its lost rows, as one part: else each of them has an anti-join of its own for
        each deletion, in every delta join of every rule."""
        read = Counter(a.pred for r in state.rules for a in r.rule.body)
        often = sorted(p for p, t in tables.items() if read[p] > 1 and t.rows > 0)
        with ThreadPoolExecutor(self.threads) as pool:
            whole = pool.map(lambda p: self.store.compact(tables[p], f"{p}-settled", most_deletions=0), often)
            return {**tables, **dict(zip(often, whole))}

    def _without_support(self, state: State, pred: str, path: str) -> tuple[str, int]:
        """Of a part's facts those whose last derivation is gone and that aren't explicit, as a part of their own."""
        names = [c for c, _ in self.columns(pred)]
        touched = self.store.part(self.columns(pred), path).where(F.col(FRESH)).select(*names)
        held = semi(self.store.part(self.columns(pred), *state.ledger[pred]), touched, names)
        left = held.groupBy(*names).agg(F.sum(COUNT).alias(COUNT)).where(F.col(COUNT) > 0)
        rows = minus(touched, left, names)
        if state.explicit[pred].rows > 0:
            rows = minus(rows, self.store.read(state.explicit[pred]), names)
        path, fresh, _ = self.store.put(rows, self.columns(pred), f"{pred}-unsupported")
        return path, fresh

    def _rederive(self, state: State, gone: dict[str, list[str]], report: RunReport) -> dict[str, DataFrame]:
        """Overdeleted facts that still have a derivation or are explicit."""
        here = self._round(state, {}, {}, report)
        heads = self._heads(state, here, "rederive")
        if self.counts and heads:
            self._commit(state, heads, dict.fromkeys(heads), True, 1, "red")
        self.store.drop(here.scratch)
        out = {}
        for p, paths in gone.items():
            names = [c for c, _ in self.columns(p)]
            taken = self.store.part(self.columns(p), *paths).where(F.col(FRESH)).select(*names).distinct()
            back = []
            if self.counts:
                if state.ledger[p]:
                    held = semi(self.store.part(self.columns(p), *state.ledger[p]), taken, names)
                    back.append(held.groupBy(*names).agg(F.sum(COUNT).alias(COUNT)).where(F.col(COUNT) > 0).select(*names))
            else:
                for r in state.rules:
                    if r.rule.head.pred == p:
                        found = PlanRule(r.rule, r.columns).supported(here, taken)
                        back += [] if found is None else [found]
            if state.explicit[p].rows > 0:
                back.append(semi(self.store.read(state.explicit[p]), taken, names))
            if back:
                out[p] = union(back).distinct()
        return out

    # --- runs

    def materialise(self, task: str = "materialise") -> RunReport:
        """Loads pending facts and carries them to the fixpoint."""
        pending, self.pending = dict(self.pending), defaultdict(list)
        add = {p: union([d.toDF(*[c for c, _ in self.columns(p)]) for d in frames]) for p, frames in pending.items()}
        return self.update(add=add, task=task)

    def update(self, add: dict[str, DataFrame] | None = None, delete: dict[str, DataFrame] | None = None, task: str = "update") -> RunReport:
        """Explicit facts to add and to delete; a fact in both stays. A failed update leaves the state as it was."""
        if self.pending:
            self.materialise()
        with short_descriptions(self.spark):
            return self._update(add, delete, task)

    def _update(self, add: dict[str, DataFrame] | None, delete: dict[str, DataFrame] | None, task: str) -> RunReport:
        report, began = RunReport(task, self.engine), time.perf_counter()
        before = self.tree_seconds
        add, delete = add or {}, delete or {}
        if unknown := [p for p in (*add, *delete) if p not in self.schemas.types and p not in self.program.preds]:
            raise RuleError(f"unknown predicates: {', '.join(unknown)}")
        self.schemas.infer(self.program)
        for p in {*self.program.preds, *self.schemas.types}:
            for tables in (self.state.explicit, self.state.facts):
                tables.setdefault(p, Table(self.columns(p)))
            self.state.ledger.setdefault(p, ())
        with ThreadPoolExecutor(self.threads) as pool:
            plus = dict(pool.map(lambda p: self._normalised(p, add[p], None, True), sorted(add)))
            minus_ = dict(pool.map(lambda p: self._normalised(p, delete[p], add.get(p), False), sorted(delete)))
        self._prepare({p: Table(self.columns(p), (*self.state.facts[p].layers, x)) for p, x in plus.items()})
        state = copy.deepcopy(self.state)
        report.tree_seconds = self.tree_seconds - before
        lost = {p: x for p, x in minus_.items() if x.rows}
        if lost and self.deletion == "counting" and any(is_recursive(layer) for layer in stratify(self.program)):
            raise RuleError("deletion by counts is right only without recursion: a cycle of facts would support itself")
        for p, x in lost.items():
            state.explicit[p] = state.explicit[p].plus(Layer("del", x.path, x.rows))
        if self.engine in ("naive", "tree-naive"):
            self._recompute(state, plus, lost, report)
        else:
            if self.deletion == "counting":  # an explicit fact that has a derivation stays a fact
                held = {p: self._without_support(state, p, x.path) for p, x in lost.items()}
                lost = {p: Layer("add", path, fresh) for p, (path, fresh) in held.items() if fresh}
            gone = self._delete_loop(state, lost, report)
            back = self._rederive(state, gone, report) if gone else {}
            for p, x in plus.items():
                state.explicit[p] = state.explicit[p].plus(x)
            self._add_loop(state, self._seeds(state, plus, back), report)
        here = self._round(state, {}, {}, report)
        for p in state.facts:
            state.facts[p] = self.store.compact(state.facts[p], f"{p}-facts")
            state.explicit[p] = self.store.compact(state.explicit[p], f"{p}-explicit")
            if len(state.ledger[p]) > 24:
                names = [c for c, _ in self.columns(p)]
                rows = self.store.part(self.columns(p), *state.ledger[p]).groupBy(*names).agg(F.sum(COUNT).alias(COUNT)).where(F.col(COUNT) != 0)
                state.ledger[p] = (self.store.put(rows, self.columns(p), f"{p}-ledger")[0],)
        for r in state.rules:
            if isinstance(r, TreeRule):
                r.compact(here)
        self.state = state
        self.store.history.append((task, report.rounds))
        self.store.write_manifest(self._manifest())
        report.seconds = time.perf_counter() - began
        self.runs.append(report)
        return report

    def _normalised(self, pred: str, df: DataFrame, kept: DataFrame | None, adding: bool) -> tuple[str, Layer]:
        """What an update changes of the explicit facts: additions not explicit yet, deletions that are explicit and not added again."""
        names = [c for c, _ in self.columns(pred)]
        rows = self._named(pred, df)
        if kept is not None:
            rows = minus(rows, self._named(pred, kept), names)
        held = self.state.explicit[pred]
        if held.rows > 0:
            rows = (minus if adding else semi)(rows, self.store.read(held), names)
        elif not adding:
            return pred, Layer("add", "", 0)
        path, fresh, _ = self.store.put(rows, self.columns(pred), f"{pred}-{'plus' if adding else 'minus'}")
        return pred, Layer("add", path, fresh)

    def _seeds(self, state: State, plus: dict[str, Layer], back: dict[str, DataFrame]) -> dict[str, Layer]:
        """What came back and what was added, without facts that are there."""

        def one(p: str) -> tuple[str, Layer]:
            x, names = plus.get(p), [c for c, _ in self.columns(p)]
            if p not in back and state.facts[p].rows <= 0:
                return p, x
            rows = [back[p]] if p in back else []
            if x is not None and x.rows:
                rows.append(self.store.read(Table(self.columns(p), (x,))))
            if not rows:
                return p, Layer("add", "", 0)
            seeds = union(rows).distinct()
            if state.facts[p].rows > 0:
                seeds = minus(seeds, self.store.read(state.facts[p]), names)
            path, fresh, _ = self.store.put(seeds, self.columns(p), f"{p}-seed")
            return p, Layer("add", path, fresh)

        with ThreadPoolExecutor(self.threads) as pool:
            return {p: x for p, x in pool.map(one, sorted({*plus, *back})) if x.rows}

    def _recompute(self, state: State, plus: dict[str, Layer], lost: dict[str, Layer], report: RunReport) -> None:
        """The naive engines: all rules on all facts, every round, from the explicit facts."""
        for p, x in plus.items():
            state.explicit[p] = state.explicit[p].plus(x)
        state.facts = dict(state.explicit)
        state.ledger = dict.fromkeys(state.ledger, ())
        n, grown = 0, True
        while grown:
            n += 1
            here = self._round(state, {}, {}, report)
            here.counts = False
            heads = self._heads(state, here, "whole")
            held, self.counts = self.counts, False
            known = {p: state.facts[p] for p in heads}
            written = self._commit(state, heads, known, False, 1, f"naive{n}")
            self.counts = held
            for p, (path, fresh, _) in written.items():
                state.facts[p] = state.facts[p].plus(Layer("add", path, fresh))
            report.history += [("naive", n, p, rows, fresh) for p, (_, fresh, rows) in sorted(written.items())]
            grown = any(fresh for _, fresh, _ in written.values())
        report.rounds += n

    # --- what is read

    def table(self, pred: str) -> DataFrame:
        return self.store.read(self.state.facts[pred])

    def explicit(self, pred: str) -> DataFrame:
        return self.store.read(self.state.explicit[pred])

    def views(self, prefix: str = "treefix_") -> Reasoner:
        for p in self.state.facts:
            self.table(p).createOrReplaceTempView(f"{prefix}{p}")
        return self

    def sql(self, text: str) -> DataFrame:
        return self.views().spark.sql(text)

    def query(self, body: str) -> DataFrame:
        """Answers of a conjunctive query over the materialisation, e.g. ``Answer(x) <- P(x, y), Q(y, 3)``."""
        rule = parse_program(body).rules[0]
        kinds = {t.name: k for a in rule.body for t, k in zip(a.terms, self.schemas.types[a.pred]) if hasattr(t, "name")}
        cols = tuple((getattr(t, "name", f"c{n}"), kinds.get(getattr(t, "name", ""), "string")) for n, t in enumerate(rule.head.terms))
        here = self._round(self.state, {}, {}, RunReport("query", self.engine))
        here.counts = False
        if self.engine in ("standard", "naive") or self.engine == "combined" and is_acyclic(rule):
            found = PlanRule(rule, cols).whole(here)
        else:  # bags are filled and reduced, and nothing is kept
            types = {t.name: k for a in rule.body for t, k in zip(a.terms, self.schemas.types[a.pred]) if hasattr(t, "name")}
            found = TreeRule(rule, cols, best_tree(rule, self.stats_), types, self.pivot_sweep, self.labels).whole(here)
        return self.spark.createDataFrame([], ", ".join(f"{c} {k}" for c, k in cols)) if found is None else found

    def why(self, pred: str, df: DataFrame) -> DataFrame:
        """One-step derivations of the given facts: the rule, and its bindings as JSON."""
        here = self._round(self.state, {}, {}, RunReport("why", self.engine))
        wanted, found = self._named(pred, df), []
        for r in self.program.rules:
            if r.head.pred == pred:
                rows = PlanRule(r, self.columns(pred)).instances(here, wanted)
                if rows is not None:
                    found.append(rows.select(F.lit(r.name).alias("rule"), F.to_json(F.struct(*sorted(rows.columns))).alias("bindings")))
        return union(found) if found else self.spark.createDataFrame([], "rule string, bindings string")

    def explain(self, name: str) -> DataFrame:
        """The tree of a rule: bags, guards, estimated and stored rows."""
        rule, tree = self._rule(name), self.trees.get(name)
        held = next((r for r in self.state.rules if r.rule.name == name and isinstance(r, TreeRule)), None)
        if tree is None:
            return self.spark.createDataFrame([(0, None, ",".join(rule.vars), "; ".join(map(str, rule.body)), 1, self.stats_.join_rows(list(rule.body)), None)], "node int, parent int, bag string, guard string, width int, estimate double, stored bigint")
        rows = [
            (p, tree.parent[p], ",".join(sorted(tree.bag[p])), "; ".join(str(rule.body[a]) for a in tree.atoms(p)), tree.width, float(self.stats_.join_rows([rule.body[a] for a in tree.guard[p]])), held.bags[p].rows.rows if held else None)
            for p in tree.nodes
        ]
        return self.spark.createDataFrame(rows, "node int, parent int, bag string, guard string, width int, estimate double, stored bigint")

    def cost(self, name: str) -> float:
        return tree_cost(self.trees[name], self._rule(name), self.stats_)

    def bag(self, name: str, node: int) -> DataFrame:
        held = next(r for r in self.state.rules if r.rule.name == name)
        return self.store.read(held.bags[node].rows)

    def derivations(self, pred: str) -> DataFrame:
        """Facts with their numbers of derivations, from the ledger."""
        names = [c for c, _ in self.columns(pred)]
        rows = self.store.part(self.columns(pred), *self.state.ledger[pred])
        return rows.groupBy(*names).agg(F.sum(COUNT).alias("derivations")).where("derivations > 0")

    def stats(self) -> DataFrame:
        simple, complex_ = split_by_width(self.program)
        explicit, facts = (sum(t.rows for t in x.values()) for x in (self.state.explicit, self.state.facts))
        return self.spark.createDataFrame([(explicit, facts, len(self.program.rules), len(simple.rules), len(complex_.rules))], "explicit bigint, facts bigint, rules int, simple int, complex int")

    def space(self) -> DataFrame:
        """Rows and bytes of facts against bags and ledgers, and their ratio to the facts alone."""
        facts = [x.path for t in self.state.facts.values() for x in t.layers]
        trees = [r for r in self.state.rules if isinstance(r, TreeRule)]
        bags = [p for r in trees for b in r.bags for p in (*(x.path for x in b.rows.layers), *b.ledger)]
        ledgers = [p for v in self.state.ledger.values() for p in v]
        n_facts = sum(t.rows for t in self.state.facts.values())
        n_bags = sum(b.rows.rows for r in trees for b in r.bags)
        size = self.store.bytes_of(facts)
        extra = self.store.bytes_of([p for p in [*bags, *ledgers] if p not in set(facts)])
        return self.spark.createDataFrame([(n_facts, n_bags, size, extra, (size + extra) / max(size, 1))], "fact_rows bigint, bag_rows bigint, fact_bytes bigint, extra_bytes bigint, factor double")

    def verify(self) -> dict[str, int]:
        """Rows that differ from a recomputation, by predicate and bag; all zero if the state is right."""
        other = Reasoner(self.spark, engine="standard", oracle="query")
        other.schemas, other.program = copy.deepcopy(self.schemas), self.program
        for p, t in self.state.explicit.items():
            if t.rows > 0:
                other.facts(p, self.store.read(t))
        other.materialise("verify")
        out = {}
        for p in self.state.facts:
            a, b = self.table(p), other.table(p)
            out[p] = a.exceptAll(b).count() + b.exceptAll(a).count()
        here = self._round(self.state, {}, {}, RunReport("verify", self.engine))
        for r in self.state.rules:
            if isinstance(r, TreeRule) and self.engine != "tree-naive":
                for p in r.kept:
                    names = r.bags[p].rows.names
                    want = r.fill(p, here)
                    if self.counts:
                        held = self.store.part(r.bags[p].rows.columns, *r.bags[p].ledger).groupBy(*names).agg(F.sum(COUNT).alias(COUNT)).where(F.col(COUNT) != 0)
                        kept = self.store.read(r.bags[p].rows).join(held, names)
                    else:
                        kept, want = self.store.read(r.bags[p].rows), want and want.select(*names)
                    out[f"{r.rule.name}[{p}]"] = self.store.read(r.bags[p].rows).count() if want is None else kept.exceptAll(want).count() + want.exceptAll(kept).count()
        return out

    def migrate_tree(self, name: str, tree: JoinTree) -> Reasoner:
        """Another tree for a rule in use: its bags are filled again from the facts."""
        if problems := check_tree(tree, self._rule(name)):
            raise ValueError("; ".join(problems))
        state = copy.deepcopy(self.state)
        at = next(n for n, r in enumerate(state.rules) if r.rule.name == name)
        self.trees[name] = complete_tree(tree, self._rule(name))
        if self.counts and isinstance(state.rules[at], TreeRule):
            raise_if = {x.rule.head.pred for x in state.rules[:at] + state.rules[at + 1 :]}
            if state.rules[at].rule.head.pred in raise_if:
                raise ValueError("derivations of a predicate with several rules are counted together; rebuild the state instead")
        new = self._engine(self._rule(name))
        here = self._round(state, {}, {}, RunReport("migrate", self.engine))
        for p in new.kept if isinstance(new, TreeRule) else ():
            rows = new.fill(p, here)
            if rows is not None:
                path, fresh, _ = new._write(here, p, rows, "moved")
                new.bags[p].rows, new.bags[p].ledger = new.bags[p].rows.plus(Layer("add", path, fresh)), (path,)
        state.rules[at] = new
        if self.counts:
            pred = new.rule.head.pred
            heads = new.whole(here)
            state.ledger[pred] = ()
            if heads is not None:
                self._commit(state, {pred: [heads]}, {pred: None}, True, 1, "moved")
        self.state = state
        return self

    def _manifest(self) -> dict:
        tables = lambda d: {p: [[x.kind, x.path, x.rows] for x in t.layers] for p, t in d.items()}
        return {
            "history": self.store.history, "schemas": self.schemas.types, "explicit": tables(self.state.explicit), "facts": tables(self.state.facts), "ledger": {p: list(v) for p, v in self.state.ledger.items()},
            "bags": {r.rule.name: [[[[x.kind, x.path, x.rows] for x in b.rows.layers], list(b.ledger)] for b in r.bags] for r in self.state.rules if isinstance(r, TreeRule)},
            "trees": {n: [[sorted(b) for b in t.bag], [list(g) for g in t.guard], t.parent, [list(e) for e in t.enforced]] for n, t in self.trees.items()},
        }

    @classmethod
    def open(cls, spark: SparkSession, path: str, program: str | Program, **options) -> Reasoner:
        """The state that the newest finished manifest names; rules are given again."""
        self = cls(spark, path, **options).rules(program)
        held = self.store.newest_manifest()
        self.schemas.types = held["schemas"]
        self.store.history = [tuple(x) for x in held["history"]]
        self.trees = {n: JoinTree([frozenset(x) for x in b], [tuple(x) for x in g], p, [tuple(x) for x in e]) for n, (b, g, p, e) in held["trees"].items()}
        layers = lambda rows: tuple(Layer(*x) for x in rows)
        self.state = State({p: Table(self.columns(p), layers(x)) for p, x in held["explicit"].items()}, {p: Table(self.columns(p), layers(x)) for p, x in held["facts"].items()}, {p: tuple(x) for p, x in held["ledger"].items()})
        self._prepare({})
        for r in self.state.rules:
            if isinstance(r, TreeRule):
                for bag, (rows, ledger) in zip(r.bags, held["bags"][r.rule.name]):
                    bag.rows, bag.ledger = Table(bag.rows.columns, layers(rows)), tuple(ledger)
        return self
