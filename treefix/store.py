"""Stored tables: parts written once, read as layers, and a manifest that names them.

A table is a list of layers. An ``add`` layer holds rows, a ``del`` layer takes the rows that were there
below it. Writing a round appends one part, so a round costs what it brings, reading the rows of
a round reads its files only, and a part that is written twice after a failure replaces nothing. Layers
are merged when deletions pile up. A manifest is written last: until then the old state stays readable.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field, replace
from functools import reduce

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

COUNT, FRESH = "n_", "fresh_"


def work_dir(spark: SparkSession) -> str:
    """The session's shared folder (``spark.checkpoint.dir``); one below /tmp only where none is set and Spark runs in one process."""
    held = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if held:
        return held.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    own = f"/tmp/treefix-checkpoints-{uuid.uuid4().hex}"
    spark.sparkContext.setCheckpointDir(own)
    return own


#: Parts after which the driver collects its garbage: plans of finished parts, which its heap would else keep until it is full.
COLLECT = 4
#: From the first part with so many rows on it does so after each part: executors keep the shuffle files of a part's plan until then, also where
#: large tables gave few rows.
BULKY = 500_000
#: Characters of a plan's description, of which Spark's listeners keep one for each of the last thousand queries: those of wide rules have a million.
DESCRIBED = 20_000


def give_back(spark: SparkSession) -> str | None:
    """The driver collects its garbage, and its C library hands the pages that it holds free back to the system: compilers and the
    threads of exchanges leave some hundred MB there. What the JVM says of it; None where it has no such command."""
    jvm, array = spark._jvm, spark.sparkContext._gateway.new_array
    jvm.System.gc()
    try:
        kinds, values = array(jvm.Class, 4), array(jvm.Object, 4)
        for n, name in enumerate(("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
            kinds[n] = jvm.Class.forName(name)
        values[0], values[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        server = jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer()
        # the server's class isn't exported, the interface is
        return jvm.Class.forName("javax.management.MBeanServer").getMethod("invoke", kinds).invoke(server, values)
    except Py4JError:
        return None


#: Seconds that an idle thread of Spark's exchanges and adaptive plans lives. Their pools start a thread for each exchange, even where others
#: are idle, and keep it for a minute: wide rules had 900 of them, each with a stack and a share of the C library's arenas.
IDLE = 1


def end_idle_threads(spark: SparkSession) -> int:
    """Threads of the driver that run exchanges and adaptive plans end soon after they have nothing to do; how many pools do so. No thread
    less may run at a time, so nothing waits that didn't before."""
    jvm, done = spark._jvm, 0
    for package, name in (("exchange", "ShuffleExchangeExec$"), ("exchange", "BroadcastExchangeExec$"), ("adaptive", "AdaptiveSparkPlanExec$"), ("adaptive", "ResultQueryStageExec$")):
        try:
            pool = getattr(getattr(getattr(jvm.org.apache.spark.sql.execution, package), name), "MODULE$").executionContext().executor()
            pool.setKeepAliveTime(IDLE, jvm.java.util.concurrent.TimeUnit.SECONDS)
            done += 1
        except (Py4JError, TypeError):  # another release of Spark may have other pools
            continue
    return done


@contextmanager
def short_descriptions(spark: SparkSession) -> Iterator[None]:
    """Plans are described in ``DESCRIBED`` characters at most; the session's setting comes back afterwards."""
    key = "spark.sql.maxPlanStringLength"
    before = spark.conf.get(key)
    spark.conf.set(key, str(DESCRIBED))
    try:
        yield
    finally:
        spark.conf.set(key, before)


@dataclass(frozen=True)
class Layer:
    kind: str  # add or del
    path: str
    rows: int


@dataclass(frozen=True)
class Table:
    """Rows by layers. ``columns``: (name, type) of the key; parts may hold counts beside it."""

    columns: tuple[tuple[str, str], ...]
    layers: tuple[Layer, ...] = ()

    @property
    def names(self) -> list[str]:
        return [c for c, _ in self.columns]

    @property
    def rows(self) -> int:
        return sum(x.rows if x.kind == "add" else -x.rows for x in self.layers)

    def plus(self, layer: Layer | None) -> Table:
        return self if layer is None or not layer.rows else replace(self, layers=(*self.layers, layer))

    def without_last(self, count: int) -> Table:
        return replace(self, layers=self.layers[: len(self.layers) - count])

    def last(self, count: int) -> Table:
        return replace(self, layers=self.layers[len(self.layers) - count :] if count else ())


def part_schema(columns: tuple[tuple[str, str], ...]) -> T.StructType:
    text = ", ".join([*(f"`{c}` {k}" for c, k in columns), f"{COUNT} bigint", f"{FRESH} boolean"])
    return T._parse_datatype_string(text)


@dataclass
class Store:
    """Writes and reads parts below one folder of the shared file system."""

    spark: SparkSession
    path: str
    written: int = 0
    bulky: bool = False
    history: list[tuple[str, int]] = field(default_factory=list)

    def put(self, df: DataFrame, columns: tuple[tuple[str, str], ...], name: str) -> tuple[str, int, int]:
        """Writes rows (key, count, fresh); its path, how many rows are fresh, and all rows."""
        seen = Observation()
        path = f"{self.path}/parts/{name}-{uuid.uuid4().hex}"
        keys = [F.col(c).cast(k).alias(c) for c, k in columns]
        count = F.col(COUNT).cast("bigint").alias(COUNT) if COUNT in df.columns else F.lit(1).cast("bigint").alias(COUNT)
        fresh = F.col(FRESH).cast("boolean").alias(FRESH) if FRESH in df.columns else F.lit(True).alias(FRESH)
        out = df.select(*keys, count, fresh).observe(seen, F.count_if(F.col(FRESH)).alias("fresh"), F.count(F.lit(1)).alias("all"))
        out.write.option("compression", "zstd").parquet(path)
        self.written += 1
        fresh, rows = seen.get["fresh"], seen.get["all"]
        self.bulky = self.bulky or rows > BULKY
        if self.bulky or self.written % COLLECT == 0:
            give_back(self.spark)
        return path, fresh, rows

    def drop(self, paths: list[str]) -> None:
        """Removes parts that served within a round, which no table has as a layer."""
        conf = self.spark._jsc.hadoopConfiguration()
        for p in paths:
            path = self.spark._jvm.org.apache.hadoop.fs.Path(p)
            path.getFileSystem(conf).delete(path, True)
        paths.clear()

    def part(self, columns: tuple[tuple[str, str], ...], *paths: str) -> DataFrame:
        schema = part_schema(columns)
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def read(self, table: Table) -> DataFrame:
        """The rows of a table: one scan for each run of added parts, an anti-join for each deletion."""
        out, run = None, []

        def flush(out):
            if not run:
                return out
            here = self.part(table.columns, *run).where(F.col(FRESH)).select(*table.names)
            run.clear()
            return here if out is None else out.unionByName(here)

        for layer in table.layers:
            if layer.kind == "add":
                run.append(layer.path)
            else:
                out = flush(out)
                gone = self.part(table.columns, layer.path)
                out = minus(out, gone, table.names)
        out = flush(out)
        return self.part(table.columns).select(*table.names) if out is None else out

    def compact(self, table: Table, name: str, most_deletions: int = 2, most_parts: int = 24) -> Table:
        """One part instead of many if deletions or parts pile up, or a tenth of the rows is gone."""
        gone = sum(x.rows for x in table.layers if x.kind == "del")
        deletions = sum(x.kind == "del" for x in table.layers)
        if deletions <= most_deletions and len(table.layers) <= most_parts and 10 * gone <= max(table.rows, 1):
            return table
        path, fresh, _ = self.put(self.read(table), table.columns, name)
        return replace(table, layers=(Layer("add", path, fresh),))

    def bytes_of(self, paths: list[str]) -> int:
        """Bytes of files, from the file system that holds them."""
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        total = 0
        for p in dict.fromkeys(paths):
            path = jvm.org.apache.hadoop.fs.Path(p)
            fs = path.getFileSystem(conf)
            if fs.exists(path):
                total += fs.getContentSummary(path).getLength()
        return total

    def write_manifest(self, state: dict) -> None:
        """The state's tables as one small JSON file under a new name, written last."""
        text = json.dumps(state)
        self.spark.createDataFrame([(text,)], "value string").coalesce(1).write.text(f"{self.path}/manifests/{len(state['history']):06d}-{uuid.uuid4().hex}")

    def _listed(self, name: str) -> list[str]:
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        top = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        fs = top.getFileSystem(conf)
        return sorted(s.getPath().toString() for s in fs.listStatus(top)) if fs.exists(top) else []

    def _manifests(self) -> list[str]:
        """Finished ones, oldest first."""
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        path = jvm.org.apache.hadoop.fs.Path
        return [m for m in self._listed("manifests") if path(m).getFileSystem(conf).exists(path(m, "_SUCCESS"))]

    def newest_manifest(self) -> dict:
        return json.loads(self.spark.read.text(self._manifests()[-1]).first()["value"])

    def clean(self, keep: int = 1) -> int:
        """Removes all but the ``keep`` newest manifests, and the parts that none of those names: what compaction left behind,
        failed updates, and parts that served within a round. Frames that were read from older states can't be evaluated any
        more, so this is asked for, never done by the way. How many parts went."""
        manifests = self._manifests()
        kept = manifests[-keep:]
        if not kept:
            return 0
        named = {p.rsplit("/", 1)[-1] for m in kept for p in _strings(json.loads(self.spark.read.text(m).first()["value"])) if "/parts/" in p}
        jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
        gone = [p for p in self._listed("parts") if p.rsplit("/", 1)[-1] not in named]
        for p in [*manifests[:-keep], *gone]:
            path = jvm.org.apache.hadoop.fs.Path(p)
            path.getFileSystem(conf).delete(path, True)
        return len(gone)


def _strings(value) -> list[str]:
    if isinstance(value, str):
        return [value]
    inner = value.values() if isinstance(value, dict) else value if isinstance(value, list) else ()
    return [s for v in inner for s in _strings(v)]


def same(left: DataFrame, right: DataFrame, names: list[str]):
    return reduce(lambda a, b: a & b, [left[c] == right[c] for c in names])


def semi(left: DataFrame, right: DataFrame, names: list[str], how: str = "left_semi") -> DataFrame:
    """Rows of ``left`` with (``left_anti``: without) an equal key in ``right``. An empty key asks whether
    ``right`` has any row."""
    if names:
        return left.join(right.select(*names), names, how)
    flag = right.limit(1).select(F.lit(1).alias("one_"))
    return left.join(flag, F.lit(True), how)


def minus(left: DataFrame, right: DataFrame, names: list[str]) -> DataFrame:
    return semi(left, right, names, "left_anti")
