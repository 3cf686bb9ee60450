"""Every method, variant, workload and operator as a query over the tables, with SQL for the other side."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treefix import sqlgen, workloads
from treefix.evaluate import answers, by_plan, by_tree, tree_of
from treefix.functions.values import json_facts, map_facts, register_bindings
from treefix.operators import relational
from treefix.plans.trees import JoinTree, hypertree_width
from treefix.rules import Module, Program, Rule, parse_program, parse_rule, split_by_width
from treefix.session import Reasoner
from treefix.sources import generators, tables
from treefix.store import work_dir
from treefix.streaming.updates import apply_updates, to_files, windowed_counts

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def _add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def _names(rule: Rule) -> list[str]:
    names = [getattr(t, "name", f"c{n}") for n, t in enumerate(rule.head.terms)]
    return [v if names.index(v) == n else f"{v}{n}" for n, v in enumerate(names)]


def _materialised(program: Program, pred: str, names: list[str], **options) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = Reasoner(spark, **options)
        workloads.load(r, workloads.Workload(program, workloads.inputs(spark, sf_dir, program))).materialise()
        return r.table(pred).toDF(*names)

    return run


def _single(name: str, rule: Rule, how: Callable) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return how(rule, workloads.inputs(spark, sf_dir, Program((rule,))))

    _add(name, run, sqlgen.facts_sql(Program((rule,)), rule.head.pred, _names(rule)))


# --- single rules

for _name, _text in {
    "rule_scan_constants": "InNation(c) <- LivesIn(c, 3)",
    "rule_repeated_vars": "Same(x) <- LivesIn(x, x)",
    "rule_projection": "Buyer(c) <- Placed(c, o)",
    "rule_head_constants": "Tagged(o, 'open', 1, o) <- Status(o, 'O')",
    "rule_comparison": "Near(u, v) <- Handoff_view(u, v), u < v, v - u <= 50",
    "rule_bind": "Sized(p, z, w) <- HasSize(p, z), w := z * z + 1",
    "rule_disconnected": "Pairs(r, g) <- RegionName(r, 'ASIA'), Segment(1, g)",
}.items():
    _rule = parse_rule(_text, _name)
    for _how in (by_plan,) if _name != "rule_disconnected" else (by_plan, by_tree):
        _single(_name if _how is by_plan else f"{_name}_tree", _rule, _how)

_RECURSIVE = {r.name for r in (*workloads.COMPLEX.rules, *workloads.SHAPES.rules) if r.head.pred in {a.pred for a in r.body}}
for _rule in workloads.COMPLEX.rules:
    if _rule.name in _RECURSIVE:
        for _prefix, _engine in (("plan", "standard"), ("tree", "tree"), ("combined", "combined")):
            _add(f"{_prefix}_{_rule.name}", _materialised(Program((_rule,)), _rule.head.pred, _names(_rule), engine=_engine), sqlgen.facts_sql(Program((_rule,)), _rule.head.pred, _names(_rule)))
    else:
        _single(f"plan_{_rule.name}", _rule, by_plan)
        _single(f"tree_{_rule.name}", _rule, by_tree)
for _rule in workloads.SHAPES.rules:
    if _rule.name in _RECURSIVE:
        _add(f"shape_{_rule.name}", _materialised(Program((_rule,)), _rule.head.pred, _names(_rule)), sqlgen.facts_sql(Program((_rule,)), _rule.head.pred, _names(_rule)))
    else:
        _single(f"shape_{_rule.name}", _rule, by_tree)
_C = {r.name: r for r in workloads.COMPLEX.rules}
_single("plan_left_to_right_C02", _C["C02"], lambda rule, facts: by_plan(rule, facts, order="written"))

# --- fixpoints and variants

_THREAD = Program(tuple(r for r in workloads.simple_rules().rules if r.head.pred == "ThreadAfter"))
_THREAD_SQL = sqlgen.facts_sql(_THREAD, "ThreadAfter", ["k", "x", "y"])
for _name, _options in {"naive_closure": {"engine": "naive"}, "seminaive_closure": {"engine": "standard"}, "tree_closure": {"engine": "tree"}}.items():
    _add(_name, _materialised(_THREAD, "ThreadAfter", ["k", "x", "y"], **_options), _THREAD_SQL)
_LINKED = Program((_C["C15"],))
_LINKED_SQL = sqlgen.facts_sql(_LINKED, "Linked", ["x", "y"])
for _name, _options in {
    "tree_naive_C15": {"engine": "tree-naive"}, "naive_C15": {"engine": "naive"}, "tree_query_oracle_C15": {"engine": "tree", "oracle": "query"}, "tree_width_choice_C15": {"engine": "tree", "tree_choice": "width"},
    "tree_trivial_C15": {"engine": "tree", "tree_choice": "trivial"}, "tree_always_sweep_C15": {"engine": "tree", "pivot_sweep": "always"}, "tree_never_sweep_C15": {"engine": "tree", "pivot_sweep": "never"}, "plan_written_order_C15": {"engine": "standard", "order": "written"},
}.items():
    _add(_name, _materialised(_LINKED, "Linked", ["x", "y"], **_options), _LINKED_SQL)

# --- the worked example

_N, _K = 8, 20
_MOTIVATING_SQL = f"""Colleague(a0, a1) AS (SELECT i, 1000000 + i * {_K} + j FROM range(0, {_N}) a(i), range(1, {_K + 1}) b(j) UNION SELECT {_N}, 2),
Cosigner(a0, a1) AS (SELECT i, 2000000 + i * {_K} + j FROM range(0, {_N}) a(i), range(1, {_K + 1}) b(j) UNION SELECT {_N}, 3),
matches(a0, a1) AS (SELECT 1000000 + i * {_K} + j, 3000000 + j FROM range(0, {_N}) a(i), range(1, {_K + 1}) b(j) UNION SELECT 2000000 + i * {_K} + j, 3000000 + j FROM range(0, {_N}) a(i), range(1, {_K + 1}) b(j))"""
_EXAMPLE_SQL = sqlgen.facts_sql(workloads.MOTIVATING, "Match", ["x", "y"], seeds={"Match": "SELECT a0, a1 FROM matches"}, extra={"Colleague": _MOTIVATING_SQL, "Cosigner": "nothing_(a0) AS (SELECT 1)"})


def _example(spark: SparkSession, engine: str = "combined", n: int = _N, k: int = _K, **options) -> tuple[Reasoner, object]:
    r = Reasoner(spark, engine=engine, **options).rules(workloads.MOTIVATING)
    for p, df in generators.motivating(spark, n, k).items():
        r.facts(p, df)
    return r, r.materialise()


def _rederive_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, _ = _example(spark)
    pair = lambda a, b: spark.range(1).select(F.lit(a).cast("bigint").alias("x"), F.lit(b).cast("bigint").alias("z"))
    r.update(add={"Colleague": pair(_N, 4), "Cosigner": pair(_N, 5)})
    r.update(delete={"Cosigner": pair(_N, 3)})
    return r.table("Match").toDF("x", "y")


_add("motivating_fixpoint", lambda s, d: _example(s)[0].table("Match").toDF("x", "y"), _EXAMPLE_SQL)
_add("motivating_fixpoint_standard", lambda s, d: _example(s, "standard")[0].table("Match").toDF("x", "y"), _EXAMPLE_SQL)
_add("rederive_example", _rederive_example, _EXAMPLE_SQL)


def motivating_work(spark: SparkSession, sf_dir: str, n: int = 50, ks: tuple[int, ...] = (10, 100, 1000)) -> DataFrame:
    """Rows out of joins by plan and by tree as k grows: the square of k against k."""
    rows = []
    for k in ks:
        for engine in ("standard", "tree"):
            _, report = _example(spark, engine, n, k, measure=True)
            rows.append((n, k, engine, sum(report.rows_through_joins().values())))
    return spark.createDataFrame(rows, "n int, k int, engine string, join_rows bigint")


_add("motivating_work", motivating_work)

# --- reducer, bags, counts

_single("reducer_two_sweep", _C["C02"], lambda rule, facts: answers(rule, facts))
_single("reducer_three_sweep", _C["C02"], lambda rule, facts: answers(rule, facts, pivot=0))
_TREE_C01 = JoinTree([frozenset("anp"), frozenset("bnp")], [(0, 1), (2, 3)], [None, 0])
for _p, _bag in ((0, "a"), (1, "b")):

    def _bag_rows(spark: SparkSession, sf_dir: str, p: int = _p) -> DataFrame:
        own, here = tree_of(_C["C01"], workloads.inputs(spark, sf_dir, Program((_C["C01"],))), _TREE_C01)
        return own.fill(p, here).withColumnRenamed("n_", "bindings")

    _bag_rule = parse_rule(f"Bag({_bag}, n, p) <- LivesIn({_bag}, n), Bought({_bag}, p)")
    _add(f"bag_rows_C01_p{_p + 1}", _bag_rows, f"{sqlgen.program_ctes(Program((_bag_rule,)))}\nSELECT a0 AS {_bag}, a1 AS n, a2 AS p, CAST(1 AS BIGINT) AS bindings FROM \"Bag\"")
_COUNTS_SQL = f"WITH {', '.join(sqlgen.facts_cte(a.pred) for a in _C['C02'].body[:1])}, {', '.join(sqlgen.facts_cte(p) for p in ('Line', 'LivesIn', 'BasedIn'))}\n" + sqlgen.rule_select(_C["C02"], names=["c", "s"], count=", CAST(count(*) AS BIGINT) AS bindings")
_add("counts_C02", lambda s, d: by_plan(_C["C02"], workloads.inputs(s, d, Program((_C["C02"],))), counts=True).withColumnRenamed("n_", "bindings"), _COUNTS_SQL)


def _estimates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Estimated against actual rows of the nodes of each non-recursive complex rule of moderate size."""
    out = []
    for name in ("C01", "C02", "C07", "C10", "C13", "C14"):
        own, here = tree_of(_C[name], workloads.inputs(spark, sf_dir, Program((_C[name],))))
        for p in own.tree.nodes:
            guard = [own.rule.body[a] for a in own.tree.guard[p]]
            out.append((name, p, own.tree.width, float(here.stats.join_rows(guard)), own.fill(p, here).agg(F.coalesce(F.sum("n_"), F.lit(0))).first()[0]))
    return spark.createDataFrame(out, "rule string, node int, width int, estimate double, actual bigint")


def _widths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Atoms and widths of all rules; there is a simple rule for each constant that the tables hold."""
    every = (*workloads.simple_rules(workloads.constants(spark, sf_dir)).rules, *workloads.COMPLEX.rules, *workloads.SHAPES.rules, *workloads.EXPRESSIONS.rules)
    return spark.createDataFrame([(r.name, len(r.body), hypertree_width(r)) for r in every], "rule string, atoms int, width int")


_add("estimator_vs_actual", _estimates)
_add("rule_widths", _widths)

# --- whole rule sets and updates


def _digests(spark: SparkSession, r: Reasoner, preds: list[str]) -> DataFrame:
    """A row for each predicate: how many facts are stored, and a sum over hashes of their arguments, which holds what they are."""

    def one(p: str) -> tuple[str, int, int]:
        rows = r.table(p)
        mark = F.conv(F.substring(F.md5(F.concat_ws("|", *[F.col(c).cast("string") for c in rows.columns])), 1, 8), 16, 10).cast("bigint")
        return p, *rows.agg(F.count(F.lit(1)), F.coalesce(F.sum(mark), F.lit(0))).first()

    with ThreadPoolExecutor(r.threads) as pool:
        return spark.createDataFrame(list(pool.map(one, preds)), "pred string, facts bigint, digest bigint")


def _digest_sql(pred: str, arity: int) -> str:
    mark = f"CAST('0x' || substring(md5(concat_ws('|', {', '.join(f'CAST(a{n} AS VARCHAR)' for n in range(arity))})), 1, 8) AS BIGINT)"
    return f"SELECT '{pred}' AS pred, CAST(count(*) AS BIGINT) AS facts, CAST(coalesce(sum({mark}), 0) AS BIGINT) AS digest FROM \"{pred}\""


_SETS: dict[str, tuple[Program, list[str]]] = {}
for _set, _program in {"simple": workloads.simple_rules(), "mixed": workloads.simple_rules() + workloads.COMPLEX, "shapes": workloads.SHAPES}.items():
    _SETS[_set] = _program, sorted(_program.derived)
_CHARGE_ROWS = """lines_(d, price, disc, tax) AS (SELECT concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber), min(CAST(round(l_extendedprice * 100) AS BIGINT)), min(CAST(round(l_discount * 100) AS BIGINT)), min(CAST(round(l_tax * 100) AS BIGINT)) FROM lineitem GROUP BY ALL)"""
_CHARGE_RAW = {
    "IsExpr": ("a0", "SELECT CAST(unnest([5, 6, 7, 8]) AS BIGINT)"),
    "OpOf": ("a0, a1", "SELECT * FROM (VALUES (CAST(5 AS BIGINT), 'sub'), (6, 'add'), (7, 'mul'), (8, 'mul'))"),
    "Left": ("a0, a1", "SELECT * FROM (VALUES (CAST(5 AS BIGINT), CAST(2 AS BIGINT)), (6, 2), (7, 1), (8, 7))"),
    "Right": ("a0, a1", "SELECT * FROM (VALUES (CAST(5 AS BIGINT), CAST(3 AS BIGINT)), (6, 4), (7, 5), (8, 6))"),
    "Row": ("a0", "SELECT d FROM lines_"),
    "AddOp": ("a0", "SELECT 'add'"), "SubOp": ("a0", "SELECT 'sub'"), "MulOp": ("a0", "SELECT 'mul'"),
    "Val": ("a0, a1, a2", "SELECT CAST(1 AS BIGINT), d, price FROM lines_ UNION ALL SELECT 2, d, 100 FROM lines_ UNION ALL SELECT 3, d, disc FROM lines_ UNION ALL SELECT 4, d, tax FROM lines_"),
}


def _update_sql(which: str, task: str) -> str:
    """Facts after a task: the same rules over the explicit facts that are left."""
    if which == "expr":
        program, preds, head = workloads.EXPRESSIONS, ["Val"], [_CHARGE_ROWS]
        raw = {p: (c, t) for p, (c, t) in _CHARGE_RAW.items()}
    else:
        program, preds = _SETS[which]
        head = []
        given = sorted({a.pred for r in program.rules for a in r.body if a.pred in sqlgen.TABLES})
        raw = {p: (", ".join(f"a{n}" for n in range(len(sqlgen.COLUMNS[p]))), sqlgen.TABLES[p].format(gap=tables.GAP)) for p in given}
        for p in workloads.SEEDS:
            if p in program.derived:
                source, cols = workloads.SEEDS[p]
                at = [sqlgen.COLUMNS[source].index(c) for c in cols]
                inner = sqlgen.TABLES[source].format(gap=tables.GAP)
                columns = ", ".join(f"a{n}" for n in range(len(sqlgen.COLUMNS[source])))
                raw[p] = ("a0, a1", f"SELECT DISTINCT {', '.join(f'a{i}' for i in at)} FROM ({inner}) s({columns})")
    arity = {p: len(c.split(",")) for p, (c, _) in raw.items()}
    parts = [*head, *(f"raw_{p}({c}) AS (SELECT DISTINCT * FROM ({t}) s({c}))" for p, (c, t) in raw.items())]
    where = ""
    if task == "small_delete":
        marks = " UNION ALL ".join(f"SELECT {sqlgen.md5_of(p, arity[p])} AS h FROM raw_{p}" for p in raw)
        parts += [f"marks_(h) AS ({marks})", "limit_(h) AS (SELECT coalesce(max(h), '') FROM (SELECT h FROM marks_ ORDER BY h LIMIT (SELECT CASE WHEN count(*) >= 10000 THEN 1000 ELSE count(*) // 10 END FROM marks_)))"]
        where = "WHERE {m} > (SELECT h FROM limit_)"
    if task == "large_delete":
        where = "WHERE substring({m}, 1, 1) NOT IN ('0', '1', '2', '3')"
    kept = {p: f"SELECT * FROM raw_{p} {where.format(m=sqlgen.md5_of(p, arity[p]))}" for p in raw}
    parts += [f'"{p}"({raw[p][0]}) AS ({t})' for p, t in kept.items() if p not in program.derived]
    seeds = {p: t for p, t in kept.items() if p in program.derived}
    extra = {p: "" for p in raw}
    ctes = sqlgen.program_ctes(program, seeds=seeds, extra={**extra, "": ",\n".join(parts)})
    ctes = ctes.replace("WITH RECURSIVE " + ",\n" * len(extra), "WITH RECURSIVE ")
    return f"{ctes}\n" + " UNION ALL ".join(_digest_sql(p, program.preds[p]) for p in preds)


def _after_task(spark: SparkSession, sf_dir: str, which: str, task: str, **options) -> DataFrame:
    r, _ = workloads.run_task(spark, sf_dir, "charge" if which == "expr" else which, task, **options)
    return _digests(spark, r, ["Val"] if which == "expr" else _SETS[which][1])


for _set in ("simple", "mixed", "shapes", "expr"):
    for _task in workloads.TASKS:
        # the sets of over 90 rules by the other engines only for the task that goes through all steps
        for _engine in ("combined", "standard", "tree") if _set in ("shapes", "expr") or _task == "large_delete" else ("combined",):
            _title = f"{_set}_set_counts" if _task == "materialise" else f"update_{_task}_{_set}"
            _add(_title if _engine == "combined" else f"{_title}_{_engine}", partial(_after_task, which=_set, task=_task, engine=_engine), _update_sql(_set, _task))
for _task in ("small_delete", "large_delete"):  # suspects are rederived by asking the facts again
    for _engine in ("standard", "tree"):
        _add(f"update_{_task}_shapes_{_engine}_query_oracle", partial(_after_task, which="shapes", task=_task, engine=_engine, oracle="query"), _update_sql("shapes", _task))


def _stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Explicit and materialised facts and rules of each set."""
    out = None
    for which in ("simple", "mixed", "shapes", "charge"):
        r, _ = workloads.run_task(spark, sf_dir, which, "materialise")
        row = r.stats().select(F.lit(which).alias("set"), "*")
        out = row if out is None else out.unionByName(row)
    return out


_add("stats_table", _stats)


def _space(spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    r, _ = workloads.run_task(spark, sf_dir, "shapes", "materialise", "tree", **options)
    return r.space()


_add("space_overhead", _space)
_add("space_overhead_lean", partial(_space, storage="lean"))

# --- other ways to keep the same state

for _task in ("small_delete", "large_delete"):  # shapes without recursion: the last derivation that goes takes a fact along
    _FLAT = Program(tuple(r for r in workloads.SHAPES.rules if r.name not in _RECURSIVE))
    _SETS["flat"] = _FLAT, sorted(_FLAT.derived)
    _add(f"counting_{_task}", partial(_after_task, which="flat", task=_task, engine="standard", deletion="counting"), _update_sql("flat", _task))
for _task in workloads.TASKS:
    _add(f"lean_{_task}", partial(_after_task, which="shapes", task=_task, engine="tree", storage="lean"), _update_sql("shapes", _task))


def _modules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Simple rules by plan and cyclic ones by tree, as two modules of one program."""
    program = workloads.simple_rules() + Program((_C["C02"], _C["C15"]))
    simple, cyclic = split_by_width(program)
    r = Reasoner(spark, engine="standard").module(Module(simple, "standard")).module(Module(cyclic, "tree"))
    for p, df in workloads.inputs(spark, sf_dir, program).items():
        r.facts(p, df)
    r.materialise()
    return _digests(spark, r, sorted(program.derived))


_MODULES = workloads.simple_rules() + Program((_C["C02"], _C["C15"]))
_add("modules", _modules, f"{sqlgen.program_ctes(_MODULES)}\n" + " UNION ALL ".join(_digest_sql(p, _MODULES.preds[p]) for p in sorted(_MODULES.derived)))

# --- expressions

_LINE_ID = "concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber)"


def _charge(spark: SparkSession, sf_dir: str) -> DataFrame:
    r, _ = workloads.run_task(spark, sf_dir, "charge", "materialise")
    return r.table("Val").where("a0 = 8").select(F.col("a1").alias("d"), F.col("a2").alias("v"))


_add("expr_charge", _charge, f"WITH {_CHARGE_ROWS} SELECT d, price * (100 - disc) * (100 + tax) AS v FROM lines_")


def _generated(spark: SparkSession, sf_dir: str) -> DataFrame:
    line, part = (tables.read(spark, sf_dir, t) for t in ("lineitem", "part"))
    facts, roots = generators.generated(line, part, workloads.GENERATED, workloads.GENERATED)
    r = Reasoner(spark)
    workloads.load(r, workloads.Workload(workloads.EXPRESSIONS, facts)).materialise()
    return r.table("Val").toDF("e", "d", "v").join(roots, "e", "left_semi")


_LEAF = "[q, n, z][p % 3 + 1] + t % 3"


def _generated_sql(depth: int = 5, n: int = workloads.GENERATED) -> str:
    """The value of each tree by levels from the leaves up: a place's value is that of its operator over its children's."""
    lines = f"""chosen(d, q, n, z) AS (SELECT {_LINE_ID} AS d, CAST(min(l_quantity) AS BIGINT) % 10, CAST(min(l_linenumber) AS BIGINT) % 10, CAST(min(p_size) AS BIGINT) % 10 FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1 ORDER BY md5(d), d LIMIT {n})"""
    parts = [lines, f"shape(t, levels) AS (SELECT i, i % {depth - 1} + 1 FROM range(0, {n}) r(i))"]
    parts.append(f"l{depth - 1}(t, p, d, v) AS (SELECT t, p, d, CAST({_LEAF} AS BIGINT) FROM shape, range(1, {2 ** depth}) g(p), chosen WHERE levels = {depth - 1} AND p >= {2 ** (depth - 1)})")
    for lv in range(depth - 2, -1, -1):
        low = 2**lv
        op = "CASE WHEN a.p // 2 < 4 AND (a.t + a.p // 2) % 3 = 0 THEN a.v * b.v WHEN (a.t * 7 + (a.p // 2) * 5) % 2 = 0 THEN a.v + b.v ELSE a.v - b.v END"
        inner = f"SELECT a.t, a.p // 2, a.d, {op} FROM l{lv + 1} a JOIN l{lv + 1} b ON a.t = b.t AND a.d = b.d AND b.p = a.p + 1 WHERE a.p % 2 = 0"
        leaves = f" UNION ALL SELECT t, p, d, CAST({_LEAF} AS BIGINT) FROM shape, range({low}, {2 * low}) g(p), chosen WHERE levels = {lv}" if lv else ""
        parts.append(f"l{lv}(t, p, d, v) AS ({inner}{leaves})")
    return f"WITH {', '.join(parts)} SELECT t * 1000 + 1 AS e, d, v FROM l0"


_add("expr_generated", _generated, _generated_sql())

# --- what users do around it

_TRADE = parse_program("""
cr: CustomerRegion(c, r) <- LivesIn(c, n), InRegion(n, r)
sr: SupplierRegion(s, r) <- BasedIn(s, n), InRegion(n, r)
lb: LocalBuy(c, s) <- Placed(c, o), Line(o, p, s), LivesIn(c, n), BasedIn(s, n)
""")
_TRADE_CTES = sqlgen.program_ctes(_TRADE)


def _trade(spark: SparkSession, sf_dir: str) -> Reasoner:
    r = Reasoner(spark)
    workloads.load(r, workloads.Workload(_TRADE, workloads.inputs(spark, sf_dir, _TRADE))).materialise()
    return r


_add("query_over_materialisation", lambda s, d: _trade(s, d).query("Answer(c, r) <- LocalBuy(c, s), SupplierRegion(s, r), CustomerRegion(c, r)"), f"{_TRADE_CTES}\n{sqlgen.rule_select(parse_rule('Answer(c, r) <- LocalBuy(c, s), SupplierRegion(s, r), CustomerRegion(c, r)'), names=['c', 'r'])}")
_add(
    "rollup_by_region",
    lambda s, d: relational.grouped(_trade(s, d).sql("SELECT r.a1 AS r, l.a0 AS c FROM treefix_LocalBuy l JOIN treefix_CustomerRegion r ON l.a0 = r.a0"), "rollup", ["r"], F.count(F.lit(1)).alias("buys"), F.count_distinct("c").alias("buyers")),
    f'{_TRADE_CTES}\nSELECT r.a1 AS r, CAST(count(*) AS BIGINT) AS buys, CAST(count(DISTINCT l.a0) AS BIGINT) AS buyers FROM "LocalBuy" l JOIN "CustomerRegion" r ON l.a0 = r.a0 GROUP BY ROLLUP (r.a1)',
)
_add("cube_by_region_nation", lambda s, d: relational.grouped(tables.TABLES["LivesIn"](s, d).join(tables.TABLES["InRegion"](s, d), "n"), "cube", ["r", "n"], F.count(F.lit(1)).alias("customers")), f"WITH {sqlgen.facts_cte('LivesIn')}, {sqlgen.facts_cte('InRegion')} SELECT i.a1 AS r, l.a1 AS n, CAST(count(*) AS BIGINT) AS customers FROM \"LivesIn\" l JOIN \"InRegion\" i ON l.a1 = i.a0 GROUP BY CUBE (i.a1, l.a1)")
_add("topk_hubs", lambda s, d: relational.top_k(tables.TABLES["Bought"](s, d).distinct().groupBy("p").agg(F.count(F.lit(1)).alias("buyers")), 20, F.desc("buyers"), F.asc("p")), f"WITH {sqlgen.facts_cte('Bought')} SELECT a1 AS p, CAST(count(*) AS BIGINT) AS buyers FROM \"Bought\" GROUP BY a1 ORDER BY buyers DESC, p LIMIT 20")
_add("topk_by_supplier", lambda s, d: relational.top_k_by(tables.TABLES["Supplies"](s, d).distinct(), ["s"], 3, F.desc("p")), f"WITH {sqlgen.facts_cte('Supplies')} SELECT s, p, CAST(r AS INTEGER) AS rank FROM (SELECT a0 AS s, a1 AS p, row_number() OVER (PARTITION BY a0 ORDER BY a1 DESC) AS r FROM \"Supplies\") WHERE r <= 3")
_TWO = f"WITH {sqlgen.facts_cte('Handoff_view')}, {sqlgen.facts_cte('Handoff_click')}"
_views = lambda s, d: (tables.TABLES["Handoff_view"](s, d), tables.TABLES["Handoff_click"](s, d))
_add("union_facts", lambda s, d: relational.union_facts(*_views(s, d)), f'{_TWO} SELECT a0 AS u, a1 AS v FROM "Handoff_view" UNION SELECT a0, a1 FROM "Handoff_click"')
_add("intersect_facts", lambda s, d: relational.intersect_facts(*_views(s, d)), f'{_TWO} SELECT a0 AS u, a1 AS v FROM "Handoff_view" INTERSECT SELECT a0, a1 FROM "Handoff_click"')
_add("except_facts", lambda s, d: relational.except_facts(*_views(s, d)), f'{_TWO} SELECT a0 AS u, a1 AS v FROM "Handoff_view" EXCEPT SELECT a0, a1 FROM "Handoff_click"')
_add("semi_facts", lambda s, d: relational.semi_facts(*_views(s, d), ["u"]), f'{_TWO} SELECT a0 AS u, a1 AS v FROM "Handoff_view" a SEMI JOIN "Handoff_click" b ON a.a0 = b.a0')
_add("anti_facts", lambda s, d: relational.anti_facts(*_views(s, d), ["u"]), f'{_TWO} SELECT a0 AS u, a1 AS v FROM "Handoff_view" a ANTI JOIN "Handoff_click" b ON a.a0 = b.a0')
_add("full_difference", lambda s, d: relational.full_difference(*_views(s, d)), f"{_TWO} (SELECT a0 AS u, a1 AS v, 'left' AS side FROM \"Handoff_view\" EXCEPT SELECT a0, a1, 'left' FROM \"Handoff_click\") UNION ALL (SELECT a0, a1, 'right' FROM \"Handoff_click\" EXCEPT SELECT a0, a1, 'right' FROM \"Handoff_view\")")
_add("salted_join", lambda s, d: relational.salted_join(tables.TABLES["LivesIn"](s, d), tables.TABLES["BasedIn"](s, d), ["n"]).select("c", "n", "s"), f"WITH {sqlgen.facts_cte('LivesIn')}, {sqlgen.facts_cte('BasedIn')} SELECT l.a0 AS c, l.a1 AS n, b.a0 AS s FROM \"LivesIn\" l JOIN \"BasedIn\" b ON l.a1 = b.a1")
_add(
    "range_join_events",
    lambda s, d: relational.range_join(tables.read(s, d, "events").where("event_type = 'signup'").select(F.col("event_id").alias("a")), tables.read(s, d, "events").where("event_type = 'error'").select(F.col("event_id").alias("b")), "a", "b", 5),
    "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON b.event_id > a.event_id AND b.event_id - a.event_id <= 5 WHERE a.event_type = 'signup' AND b.event_type = 'error'",
)
_add(
    "as_of_last_view",
    lambda s, d: relational.as_of_join(tables.read(s, d, "events").where("event_type = 'purchase'").select("event_id", "user_id", "ts"), tables.read(s, d, "events").where("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("event_id").alias("seen")), "ts", ["user_id"], "seen").select("event_id", "seen"),
    "SELECT p.event_id, v.seen FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS seen FROM events WHERE event_type = 'view' GROUP BY ALL) v ON p.user_id = v.user_id AND p.ts >= v.ts",
)


def _why(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = _trade(spark, sf_dir)
    return r.why("CustomerRegion", r.table("CustomerRegion")).groupBy("rule").count()


def _bindings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The values of each variable in the proofs of local sales, through a table function."""
    r = _trade(spark, sf_dir)
    register_bindings(spark)
    r.why("LocalBuy", r.table("LocalBuy")).createOrReplaceTempView("treefix_proofs")
    return spark.sql("SELECT variable, count(*) AS n, count(DISTINCT value) AS n_values FROM treefix_proofs, LATERAL bindings_of(bindings) GROUP BY variable")


_LOCAL = parse_rule("Bound(c, o, p, s, n) <- Placed(c, o), Line(o, p, s), LivesIn(c, n), BasedIn(s, n)")
_BOUND = f"{sqlgen.program_ctes(Program((_LOCAL,)))} SELECT * FROM (" + " UNION ALL ".join(f"SELECT '{v}' AS variable, CAST(count(*) AS BIGINT) AS n, CAST(count(DISTINCT a{n}) AS BIGINT) AS n_values FROM \"Bound\"" for n, v in enumerate("copsn")) + ") WHERE n > 0"
_add("udtf_bindings", _bindings, _BOUND)
_add("json_facts", lambda s, d: json_facts(tables.read(s, d, "events"), "event_id", "props"), "SELECT CAST(event_id AS BIGINT) AS k, 'k' AS name, regexp_extract(props, '^\\{\"k\": ([0-9]+)\\}$', 1) AS value FROM events")
_add(
    "map_facts",
    lambda s, d: map_facts(tables.read(s, d, "events").groupBy(F.col("user_id").alias("u"), "event_type").count().groupBy("u").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m")), "u", "m"),
    "SELECT user_id AS u, event_type AS name, CAST(count(*) AS BIGINT) AS value FROM events GROUP BY ALL",
)


def _recursive_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A control: the thread closure by Spark's own recursive query, which follows one chain a step and keeps no state.
    Chains are paths, so no fact is reached twice."""
    tables.TABLES["NextTurn"](spark, sf_dir).distinct().createOrReplaceTempView("treefix_next_turn")
    return spark.sql(
        "WITH RECURSIVE after(k, x, y) AS (SELECT k, x, y FROM treefix_next_turn UNION ALL SELECT a.k, a.x, n.y FROM after a JOIN treefix_next_turn n ON a.k = n.k AND a.y = n.x) SELECT k, x, y FROM after"
    )


_add("recursive_sql_closure", _recursive_sql, _THREAD_SQL)
_add("proofs_of_facts", _why, f"{_TRADE_CTES}\nSELECT 'cr' AS rule, CAST(count(*) AS BIGINT) AS count FROM \"CustomerRegion\"")


def _stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Forward edges arrive in five batches, out of order, with retractions; a tenth is retracted and half of that added again."""
    r = Reasoner(spark).rules(Program((workloads.rule("G21"),)))
    facts = workloads.inputs(spark, sf_dir, r.program)
    late = facts.pop("Guarded").distinct()
    for p, df in facts.items():
        r.facts(p, df)
    r.materialise()
    h = F.pmod(F.crc32(F.concat_ws("|", "s0", "s1").cast("binary")), F.lit(100))
    base = f"{work_dir(spark)}/treefix/{uuid.uuid4().hex}-stream"
    batch = late.select("s0", "s1", F.lit("+").alias("op"), ((F.lit(7) * h) % 5).alias("n"))
    lost = late.where(h < 10).select("s0", "s1", F.lit("-").alias("op"), F.lit(5).cast("bigint").alias("n"))
    again = late.where(h < 5).select("s0", "s1", F.lit("+").alias("op"), F.lit(6).cast("bigint").alias("n"))
    every = batch.unionByName(lost).unionByName(again)
    for n in (3, 1, 0, 4, 2, 5, 6):
        every.where(F.col("n") == n).select("s0", "s1", "op").coalesce(1).write.mode("append").parquet(f"{base}/in")
        apply_updates(r, spark.readStream.schema("s0 bigint, s1 bigint, op string").parquet(f"{base}/in"), "Guarded", checkpoint=f"{base}/state").awaitTermination()
    return r.table("Guarded").toDF("x", "y")


_add("stream_updates", _stream)


def _windows(spark: SparkSession, sf_dir: str, **kind) -> DataFrame:
    events = tables.read(spark, sf_dir, "events")
    stream = spark.readStream.schema(events.schema).parquet(f"{sf_dir}/events.parque[t]").withColumn("time", F.col("ts").cast("timestamp"))
    path = to_files(windowed_counts(stream, "time", ["event_type"], **kind), f"{work_dir(spark)}/treefix/{uuid.uuid4().hex}-windows")
    return spark.read.parquet(path).select(F.unix_seconds("start").alias("start"), "event_type", "n")


_add("stream_windowed_facts", lambda s, d: _windows(s, d, length="6 hours"), "SELECT CAST(floor(epoch(ts) / 21600) * 21600 AS BIGINT) AS start, event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY ALL")
_add("stream_sliding_facts", lambda s, d: _windows(s, d, length="6 hours", slide="3 hours"), "SELECT CAST((floor(epoch(ts) / 10800) - k) * 10800 AS BIGINT) AS start, event_type, CAST(count(*) AS BIGINT) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY ALL")
