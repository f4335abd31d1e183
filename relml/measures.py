"""Cost and accuracy measures."""

from __future__ import annotations

import gc
import re
import time
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .plans.views import naive_join
from .spec import Feature, JoinSpec, build_join_tree, size_of


class Clock:
    """Rows (method, dataset, variant, stage, run, seconds, status)."""

    def __init__(self):
        self.rows: list[tuple] = []

    @contextmanager
    def timed(self, method: str, dataset: str, variant: str, stage: str, run: int = 0):
        t, status = time.perf_counter(), "ok"
        try:
            yield
        except MemoryError as e:
            status = type(e).__name__
        finally:
            self.rows.append((method, dataset, variant, stage, run, time.perf_counter() - t, status))

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "method string, dataset string, variant string, stage string, run int, seconds double, status string")


def let_go(spark: SparkSession) -> None:
    """Lets Spark's cleaner delete the shuffle files of finished queries; else they stay until the driver collects its garbage."""
    gc.collect()  # proxies of frames that are out of scope
    spark.sparkContext._jvm.System.gc()


def benchmark(fn, runs: int = 4, warm: bool = True, after=lambda: None) -> float:
    """Mean seconds of subsequent runs; loading stays outside, and a first run may warm up.  after: called after each run, off
    the clock."""
    total = 0.0
    for run in range(runs + warm):
        t = time.perf_counter()
        fn()
        total += time.perf_counter() - t if run >= warm else 0.0
        after()
    return total / runs


def planning_seconds(df: DataFrame) -> float:
    t = time.perf_counter()
    df._jdf.queryExecution().executedPlan()
    return time.perf_counter() - t


def rmse_gap(a: float, b: float) -> float:
    """Per cent by which a is above b."""
    return 100 * (a / b - 1)


def dataset_profile(spark: SparkSession, spec: JoinSpec) -> DataFrame:
    """(relation, n, bytes, attributes) of each relation and of the join, whose bytes are its rows times the width of all
    columns."""
    join = naive_join(spec, [])
    rows = [(n, spec.rows(n).count(), size_of(r.df), len(r.df.columns)) for n, r in spec.relations.items()]
    n = int(join.agg(F.sum("__mult")).first()[0] or 0)
    width = len({c for r in spec.relations.values() for c in r.df.columns})
    return spark.createDataFrame([*rows, ("__join", n, n * 8 * width, width)], "relation string, n long, bytes long, attributes int")


def counts_of(spec: JoinSpec, features: list[Feature]) -> tuple[int, int, int]:
    """(relations, continuous features, categorical features)."""
    return len(spec.relations), sum(f.kind == "cont" for f in features), sum(f.kind == "cat" for f in features)


def values_of(spec: JoinSpec, features: list[Feature]) -> tuple[int, int]:
    """(rows of all relations, values of all features on their relations that are not null), by a pass over each relation."""
    got = [spec.rows(n).agg(F.count(F.lit(1)), *[F.count(F.expr(f.expr)) for f in features if f.owner == n]).first() for n in spec.relations]
    return sum(r[0] for r in got), sum(sum(r[1:]) for r in got)


def resources(spark: SparkSession, fn) -> dict[str, int]:
    """Bytes that the stages of fn's jobs wrote to shuffles and spilled, rows that they read, and the most memory that one
    stage's tasks held for execution, from the session's own status store."""
    group, sc = f"resources-{time.monotonic_ns()}", spark.sparkContext
    sc.setJobGroup(group, group)
    try:
        fn()
    finally:
        sc._jsc.clearJobGroup()
    sc._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    store, tracker = sc._jsc.sc().statusStore(), sc.statusTracker()
    out = {"stages": 0, "shuffle_bytes": 0, "spill_bytes": 0, "peak_bytes": 0, "input_rows": 0}
    for job in tracker.getJobIdsForGroup(group):
        for stage in tracker.getJobInfo(job).stageIds:
            try:
                s = store.lastStageAttempt(stage)
            except Exception:  # noqa: BLE001  a skipped stage has no attempt
                continue
            out["stages"] += 1
            out["shuffle_bytes"] += s.shuffleWriteBytes()
            out["spill_bytes"] += s.diskBytesSpilled()
            out["peak_bytes"] = max(out["peak_bytes"], s.peakExecutionMemory())
            out["input_rows"] += s.inputRecords()
    return out


def observed(df: DataFrame, name: str, mult: str | None = None):
    """(df, observation): counts rows, and sums multiplicities, as df is run by whatever runs it."""
    from pyspark.sql import Observation

    o = Observation(name)
    total = F.sum(mult).cast("double") if mult else F.count(F.lit(1)).cast("double")
    return df.observe(o, F.count(F.lit(1)).alias("rows"), total.alias("total")), o


def encoded_width(spec: JoinSpec, cont: list[Feature], cats: list[Feature]) -> int:
    """Number of features after one-hot codes."""
    return len(cont) + sum(spec.rows(c.owner).select(F.expr(c.expr)).distinct().count() for c in cats)


def scans(df: DataFrame) -> dict[str, int]:
    """File scans in the plan by the columns' prefix of the relation."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    out: dict[str, int] = {}
    for m in re.finditer(r"FileScan parquet \[(\w+)_", plan):
        out[m[1]] = out.get(m[1], 0) + 1
    return out


def jobs_of(spark: SparkSession, fn) -> int:
    """Number of Spark jobs that fn starts."""
    group = f"count-{time.monotonic_ns()}"
    spark.sparkContext.setJobGroup(group, group)
    try:
        fn()
        return len(spark.sparkContext.statusTracker().getJobIdsForGroup(group))
    finally:
        spark.sparkContext._jsc.clearJobGroup()
