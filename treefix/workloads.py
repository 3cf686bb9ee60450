"""Rule sets and update tasks of the experiments, over the given tables."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treefix.rules import Program, Rule, parse_program
from treefix.session import Reasoner
from treefix.sources import generators, tables

# Constant domains of the simple rules
NATIONS = tuple(range(25))
BRANDS = tuple(f"Brand#{n}" for n in range(1, 26))
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
STATUSES = ("F", "O", "P")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
TYPES = ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")


def _safe(value: object) -> str:
    return "".join(c if c.isalnum() else "_" for c in str(value))


def constants(spark: SparkSession, sf_dir: str) -> dict[str, list]:
    """The constant domains as the tables have them; the fixed ones only name how many to expect."""

    def one(table: str, column: str, most: int = 1000) -> list:
        found = sorted(r[0] for r in tables.read(spark, sf_dir, table).select(column).distinct().limit(most + 1).collect())
        if len(found) > most:
            raise ValueError(f"{table}.{column} has more than {most} constants, each of which needs a rule")
        return found

    return {"brand": one("part", "p_brand"), "type": one("part", "p_type"), "segment": one("customer", "c_mktsegment"), "status": one("orders", "o_orderstatus"), "priority": one("orders", "o_orderpriority")}


def simple_rules(domains: dict[str, list] | None = None) -> Program:
    """98 rules with one or two body atoms."""
    d = domains or {"brand": BRANDS, "type": TYPES, "segment": SEGMENTS, "status": STATUSES, "priority": PRIORITIES}
    out = [f"sn{i}: InNation_{i}(c) <- LivesIn(c, {i})" for i in NATIONS]
    for short, name, pred, key in (("sb", "Brand", "HasBrand", "brand"), ("st", "Type", "HasType", "type"), ("sg", "InSegment", "Segment", "segment"), ("so", "Order", "Status", "status"), ("sp", "Prio", "Priority", "priority")):
        out += [f"{short}{n}: {name}_{_safe(v)}(x) <- {pred}(x, '{v}')" for n, v in enumerate(d[key])]
    out += [f"se{n}: User_{t}(u) <- Did(u, '{t}')" for n, t in enumerate(tables.EVENT_TYPES)]
    typed = ("Customer(c) <- Placed(c, o)", "Order(o) <- Placed(c, o)", "Order(o) <- Line(o, p, s)", "Part(p) <- Line(o, p, s)", "Supplier(s) <- Supplies(s, p)", "Part(p) <- Supplies(s, p)", "Customer(c) <- LivesIn(c, n)", "Nation(n) <- LivesIn(c, n)", "Supplier(s) <- BasedIn(s, n)", "Nation(n) <- BasedIn(s, n)", "Nation(n) <- InRegion(n, r)", "Region(r) <- InRegion(n, r)")
    out += [f"sa{n}: {r}" for n, r in enumerate(typed)]
    inverse = ("PlacedBy(o, c) <- Placed(c, o)", "SuppliedBy(p, s) <- Supplies(s, p)", "HostsCustomer(n, c) <- LivesIn(c, n)", "HostsSupplier(n, s) <- BasedIn(s, n)")
    out += [f"si{n}: {r}" for n, r in enumerate(inverse)]
    wider = ("TradesIn(c, p) <- Bought(c, p)", "TradesWith(c, s) <- BoughtFrom(c, s)", "Touches(u, v) <- Handoff_view(u, v)", "Touches(u, v) <- Handoff_click(u, v)")
    out += [f"su{n}: {r}" for n, r in enumerate(wider)]
    out += ["sc0: CustomerRegion(c, r) <- LivesIn(c, n), InRegion(n, r)", "sc1: SupplierRegion(s, r) <- BasedIn(s, n), InRegion(n, r)"]
    out += ["sr0: ThreadAfter(k, x, y) <- NextTurn(k, x, y)", "sr1: ThreadAfter(k, x, y) <- ThreadAfter(k, x, z), NextTurn(k, z, y)"]
    return parse_program("\n".join(out))


COMPLEX = parse_program("""
C01: SameTaste(a, b) <- LivesIn(a, n), Bought(a, p), LivesIn(b, n), Bought(b, p)
C02: LocalBuy(c, s) <- Placed(c, o), Line(o, p, s), LivesIn(c, n), BasedIn(s, n)
C03: RegionalBuy(c, s) <- Placed(c, o), Line(o, p, s), LivesIn(c, m), InRegion(m, r), BasedIn(s, n), InRegion(n, r)
C04: BrandTwin(p, q) <- HasBrand(p, b), Supplies(s, p), HasBrand(q, b), Supplies(s, q)
C05: LookAlike(p, q) <- HasBrand(p, b), HasType(p, t), HasBrand(q, b), HasType(q, t)
C06: SharedDeal(a, b) <- Bought(a, p), BoughtFrom(a, s), Bought(b, p), BoughtFrom(b, s), Supplies(s, p)
C07: Rival(s, t) <- Supplies(s, p), Supplies(t, p), BasedIn(s, n), BasedIn(t, n)
C08: DealTriple(c, p, s) <- Bought(c, p), Supplies(s, p), BoughtFrom(c, s)
C09: SegmentPeer(a, b) <- Segment(a, g), Segment(b, g), Bought(a, p), Bought(b, p)
C10: SiblingPage(a, b) <- OnHost(a, h), OnHost(b, h), LinksTo(a, t), LinksTo(b, t)
C11: SourceTwin(d, e) <- DocFrom(d, s), DocFrom(e, s), HasLine(d, f), HasLine(e, f)
C12: LeakPeer(d, e) <- DocLang(d, l), DocLang(e, l), Mentions(d, i), Mentions(e, i)
C13: LabelTie(v, w) <- InBucket(v, x), InBucket(w, x), HasLabel(v, l), HasLabel(w, l)
C14: UserTriad(u, v) <- Handoff_view(u, w), Handoff_click(v, w), Handoff_purchase(u, v)
C15: Linked(x, y) <- Forward_view(x, a), Forward_click(x, b), Linked(a, y), Linked(b, y)
C16: TieChain(v, w) <- TieChain(v, u), InBucket(u, x), InBucket(w, x), HasLabel(v, l), HasLabel(w, l)
""")


def _shapes() -> Program:
    out = []
    kinds = ("view", "click", "purchase", "signup", "error")
    for n, t in enumerate(kinds):
        h = f"Handoff_{t}"
        out.append(f"G{n + 1:02d}: Tri_{t}(x, y, z) <- {h}(x, y), {h}(y, z), {h}(z, x)")
        out.append(f"G{n + 6:02d}: Sq_{t}(x, z) <- {h}(x, y), {h}(y, z), {h}(z, w), {h}(w, x)")
    v, c, p, s = (f"Forward_{t}" for t in kinds[:4])
    V, C, P, S = (f"Handoff_{t}" for t in kinds[:4])
    f = "Forward_any"
    five = ", ".join(f"{f}({a}, {b})" for i, a in enumerate("abcde") for b in "abcde"[i + 1 :])
    out += [
        f"G11: Pent(x, z) <- {v}(x, a), {v}(a, z), {V}(z, b), {V}(b, c), {C}(c, x)",
        f"G12: Hex(x, w) <- {v}(x, a), {c}(a, b), {p}(b, w), {V}(w, d), {C}(d, e), {P}(e, x)",
        f"G13: K4(w, x, y, z) <- {P}(w, x), {P}(w, y), {P}(w, z), {P}(x, y), {P}(x, z), {P}(y, z)",
        f"G14: K4m(w, x, y, z) <- {V}(w, x), {C}(w, y), {P}(w, z), {C}(x, y), {V}(x, z), {S}(y, z)",
        f"G15: K5(a, b, c, d, e) <- {five}",
        f"G16: Petal2(x, y) <- {V}(x, a), {V}(a, y), {C}(x, b), {C}(b, y)",
        f"G17: Petal3(x, y) <- {V}(x, a), {V}(a, y), {C}(x, b), {C}(b, y), {P}(x, d), {P}(d, y)",
        f"G18: Bloom1(x, y, w) <- {f}(x, a), {f}(a, y), {f}(x, b), {c}(b, y), {p}(y, w)",
        f"G19: Bloom2(x, y, z) <- {v}(x, a), {f}(a, y), {c}(x, b), {f}(b, y), {p}(x, d), {f}(d, z), {s}(x, e), {f}(e, z)",
        f"G20: Linked(x, y) <- {v}(x, a), {c}(x, b), Linked(a, y), Linked(b, y)",
        f"G21: Guarded(x, y) <- Guarded(x, a), {c}(a, y), {p}(x, y)",
        f"G22: Squared(x, y) <- Squared(x, a), {v}(a, y), {c}(x, b), {p}(b, y)",
        f"G23: Petals(x, y) <- Petals(x, a), {v}(a, y), Petals(x, b), {c}(b, y)",
    ]
    return parse_program("\n".join(out))


SHAPES = _shapes()


def _expression(name: str, kind: str, sign: str) -> str:
    return f"{name}: Val(e, d, v) <- IsExpr(e), OpOf(e, o), {kind}(o), Left(e, l), Right(e, r), Row(d), Val(l, d, a), Val(r, d, b), v := a {sign} b"


#: Eight stored atoms and a computed ninth
EXPRESSIONS = parse_program("\n".join([_expression("E1", "AddOp", "+"), _expression("E2", "SubOp", "-"), _expression("E3", "MulOp", "*")]))
#: The same with a stored relation as the ninth atom, for small domains
STORED_EXPRESSIONS = parse_program("\n".join(f"{n}: Val(e, d, v) <- IsExpr(e), OpOf(e, o), {k}(o), Left(e, l), Right(e, r), Row(d), Val(l, d, a), Val(r, d, b), {t}(a, b, v)" for n, k, t in (("E1", "AddOp", "Sum"), ("E2", "SubOp", "Diff"), ("E3", "MulOp", "Prod"))))
MOTIVATING = parse_program("M1: Match(x, y) <- Colleague(x, z1), Cosigner(x, z2), Match(z1, y), Match(z2, y)")

#: Explicit facts of derived predicates: predicate -> (table, columns of it)
SEEDS = {"Linked": ("Forward_purchase", ("u", "v")), "Guarded": ("Forward_view", ("u", "v")), "Squared": ("Forward_view", ("u", "v")), "Petals": ("Forward_purchase", ("u", "v")), "TieChain": ("HasLabel", ("v", "v"))}
#: Trees, and rows for each, of the generated expressions
GENERATED = 300


@dataclass
class Workload:
    program: Program
    facts: dict[str, DataFrame]
    reports: dict[str, object] = field(default_factory=dict)


def inputs(spark: SparkSession, sf_dir: str, program: Program) -> dict[str, DataFrame]:
    """Facts of all predicates of a program that the tables carry, and seeds of derived ones."""
    sources = {p: SEEDS[p][0] for p in program.preds if p in SEEDS}
    found = tables.facts(spark, sf_dir, [*(p for p in program.preds if p in tables.TABLES), *sources.values()])
    out = {p: df for p, df in found.items() if p in program.preds}
    for p, (source, cols) in SEEDS.items():
        if p in program.preds:
            rows = found[source]
            out[p] = rows.select(*[F.col(c).alias(f"s{n}") for n, c in enumerate(cols)])
    return out


def pick(program: Program, *names: str) -> Program:
    return Program(tuple(r for r in program.rules if r.name in names))


def rule(name: str) -> Rule:
    return next(r for r in (*COMPLEX.rules, *SHAPES.rules) if r.name == name)


def workload(spark: SparkSession, sf_dir: str, which: str) -> Workload:
    """``simple`` (98 rules), ``complex`` (16), ``mixed`` (114), ``shapes`` (23), ``flat`` (the 19 of them without recursion), ``charge`` or ``generated`` (3)."""
    if which in ("charge", "generated"):
        line, part = (tables.read(spark, sf_dir, t) for t in ("lineitem", "part"))
        held = generators.charge(line) if which == "charge" else generators.generated(line, part, GENERATED, GENERATED)[0]
        return Workload(EXPRESSIONS, held)
    program = {"simple": lambda: simple_rules(constants(spark, sf_dir)), "complex": lambda: COMPLEX, "mixed": lambda: simple_rules(constants(spark, sf_dir)) + COMPLEX, "shapes": lambda: SHAPES, "flat": lambda: Program(tuple(r for r in SHAPES.rules if r.head.pred not in SEEDS))}[which]()
    return Workload(program, inputs(spark, sf_dir, program))


def load(reasoner: Reasoner, work: Workload) -> Reasoner:
    reasoner.rules(work.program)
    for p, df in work.facts.items():
        reasoner.facts(p, df)
    return reasoner


# --- update tasks: deterministic samples by md5 of predicate and arguments


def digest(pred: str, df: DataFrame):
    return F.md5(F.concat_ws("|", F.lit(pred), *[F.col(c).cast("string") for c in df.columns]))


def large_sample(pred: str, df: DataFrame) -> DataFrame:
    """About a quarter: a first hex digit of 0 to 3."""
    return df.where(F.substring(digest(pred, df), 1, 1).isin("0", "1", "2", "3"))


def small_limit(facts: dict[str, DataFrame], size: int = 1000) -> str:
    """The largest md5 of the sample: of the first ``size`` facts of all predicates, or of a tenth if
    there are fewer than ten times as many. Empty if that is none."""
    marks = None
    for p, df in sorted(facts.items()):
        own = df.distinct().select(digest(p, df).alias("h"))
        marks = own if marks is None else marks.unionByName(own)
    total = marks.count()
    take = size if total >= 10 * size else total // 10
    return (marks.orderBy("h").limit(take).agg(F.max("h")).first()[0] or "") if take else ""


def small_sample(pred: str, df: DataFrame, limit: str) -> DataFrame:
    return df.where(digest(pred, df) <= limit)


TASKS = ("materialise", "small_delete", "large_delete", "small_add")


def run_task(spark: SparkSession, sf_dir: str, which: str, task: str, engine: str = "combined", size: int = 1000, **options) -> tuple[Reasoner, object]:
    """One task of the experiments on one workload by one engine: the session and the measured run."""
    if task not in TASKS:
        raise ValueError(f"task must be one of {', '.join(TASKS)}")
    work = workload(spark, sf_dir, which)
    r = Reasoner(spark, engine=engine, **options)
    limit = small_limit(work.facts, size) if task.startswith("small") else ""
    sample = {p: small_sample(p, df, limit) for p, df in work.facts.items()} if limit else {}
    if task == "small_add":
        rest = Workload(work.program, {p: df.where(digest(p, df) > limit) for p, df in work.facts.items()})
        load(r, rest).materialise()
        return r, r.update(add=sample, task=task)
    report = load(r, work).materialise()
    if task == "small_delete":
        report = r.update(delete=sample, task=task)
    if task == "large_delete":
        report = r.update(delete={p: large_sample(p, df) for p, df in work.facts.items()}, task=task)
    return r, report
