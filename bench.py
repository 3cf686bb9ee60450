"""Headline runs at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``queries`` holds seconds; ``ratios`` what the comparison of approaches is about: standard
over combined and tree over combined for each rule set and task, and rows out of joins by plan and by tree.
Single rules run twice by each engine, in both orders, and the better time counts, so neither has the warmer start.
$BENCH_SETS names the rule sets: ``shapes`` (five cyclic shapes) and ``simple`` (eight simple rules) by default, as the whole sets take
far longer; ``all_shapes``, ``all_simple``, ``mixed`` and ``generated`` are the whole ones. After $BENCH_SECONDS no further run of a set begins; ``left_out`` names those."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

ENGINES = ("combined", "standard", "tree")


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    sets = os.environ.get("BENCH_SETS", "shapes,simple").split(",")
    until = time.perf_counter() + float(os.environ.get("BENCH_SECONDS", "400"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "20g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from treefix import catalog, workloads
    from treefix.session import Reasoner
    from treefix.sources import generators

    seconds: dict[str, float] = {}
    ratios: dict[str, float] = {}
    left_out: list[str] = []

    def timed(name: str, run, best: bool = False) -> object:
        began = time.perf_counter()
        out = run()
        took = round(time.perf_counter() - began, 3)
        seconds[name] = min(took, seconds.get(name, took)) if best else took
        print(f"{name} {took}", file=sys.stderr, flush=True)
        return out

    def drained(name: str):
        return lambda: catalog.QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()

    def ratio(name: str, engine: str, base: str) -> None:
        if f"{name}_{engine}" in seconds and f"{name}_{base}" in seconds:
            ratios[f"{name}_{engine}_over_{base}"] = round(seconds[f"{name}_{engine}"] / max(seconds[f"{name}_{base}"], 1e-3), 2)

    spark.range(1000).selectExpr("sum(id)").collect()
    drained("plan_C02")()
    for rule in ("C01", "C02", "C03", "C13", "C14"):
        for how in ("plan", "tree", "tree", "plan"):
            timed(f"{rule}_{how}", drained(f"{how}_{rule}"), True)
        ratio(rule, "plan", "tree")
    for rule in ("G06", "G13", "G16", "G19"):
        timed(f"shape_{rule}", drained(f"shape_{rule}"))

    def tasks(label: str, make) -> None:
        """Materialise, delete a small and a large set, add the small one, by each engine; all results must agree."""
        sizes: dict[str, set] = {}
        work = make()
        limit = workloads.small_limit(work.facts)
        small = {p: workloads.small_sample(p, df, limit) for p, df in work.facts.items()}
        large = {p: workloads.large_sample(p, df) for p, df in work.facts.items()}
        for engine in ENGINES:
            r = workloads.load(Reasoner(spark, engine=engine), work)
            for task, run in (("materialise", r.materialise), ("small_delete", lambda: r.update(delete=small)), ("small_add", lambda: r.update(add=small)), ("large_delete", lambda: r.update(delete=large))):
                if time.perf_counter() > until:
                    left_out.append(f"{label}_{task}_{engine}")
                    continue
                report = timed(f"{label}_{task}_{engine}", run)
                sizes.setdefault(task, set()).add(tuple(sorted((p, t.rows) for p, t in r.state.facts.items())))
                if task == "materialise":
                    seconds[f"{label}_trees_{engine}"] = round(report.tree_seconds, 3)
        assert all(len(v) == 1 for v in sizes.values()), "engines disagree"
        for task in sizes:
            for engine in ENGINES[1:]:
                ratio(f"{label}_{task}", engine, "combined")

    for k in (2000, 8000):
        for engine in ("tree", "standard"):
            r = Reasoner(spark, engine=engine).rules(workloads.MOTIVATING)
            for p, df in generators.motivating(spark, 50, k).items():
                r.facts(p, df)
            timed(f"motivating_k{k}_{engine}", r.materialise)
        ratio(f"motivating_k{k}", "standard", "tree")
    few = {
        "shapes": workloads.pick(workloads.SHAPES, "G06", "G16", "G21", "G22", "G23"),
        "simple": workloads.pick(workloads.simple_rules(), *(f"sa{n}" for n in range(0, 12, 3)), "sc0", "sc1", "sr0", "sr1"),
    }
    for which in sets:
        tasks(which, lambda: workloads.Workload(few[which], workloads.inputs(spark, sf_dir, few[which])) if which in few else workloads.workload(spark, sf_dir, which.removeprefix("all_")))
    rows = {(r["k"], r["engine"]): r["join_rows"] for r in catalog.motivating_work(spark, sf_dir, ks=(10, 100)).collect()}
    ratios.update({f"join_rows_k100_over_k10_{e}": round(rows[100, e] / rows[10, e], 1) for e in ("standard", "tree")})
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "ratios": ratios, "left_out": left_out, "sf": sf_dir.rsplit("sf", 1)[-1].rstrip("/")}))


if __name__ == "__main__":
    main()
