"""Cost measures: times, scans, joins, bytes, latencies, effort."""

from __future__ import annotations

import re
import time
import uuid
from collections.abc import Callable, Iterator, Sequence
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager
from dataclasses import dataclass, field
from statistics import median

from pyspark.sql import DataFrame, SparkSession

MEASURES = "workload string, config string, measure string, value double, unit string, run string"


@dataclass
class Recorder:
    """Measures of one run of a workload."""

    workload: str
    config: str
    run: str = "1"
    rows: list[tuple] = field(default_factory=list)

    def put(self, measure: str, value: float, unit: str = "") -> None:
        self.rows.append((self.workload, self.config, measure, float(value), unit, self.run))

    @contextmanager
    def stage(self, name: str) -> Iterator[None]:
        began = time.perf_counter()
        yield
        self.put(f"{name}_s", time.perf_counter() - began, "s")

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, MEASURES)


def measured_median(fn: Callable[[], object], runs: int = 3) -> float:
    """Median seconds of some runs."""
    times = []
    for _ in range(runs):
        began = time.perf_counter()
        fn()
        times.append(time.perf_counter() - began)
    return median(times)


def percentile(values: Sequence[float], p: float) -> float:
    """Linear between ranks."""
    ordered = sorted(values)
    if not ordered:
        return float("nan")
    at = (len(ordered) - 1) * p
    low = int(at)
    return ordered[low] + (ordered[min(low + 1, len(ordered) - 1)] - ordered[low]) * (at - low)


def cdf(values: Sequence[float]) -> list[tuple[float, float]]:
    ordered = sorted(values)
    return [(v, (i + 1) / len(ordered)) for i, v in enumerate(ordered)]


def replay(queries: Sequence[Callable[[], object]], clients: int = 20) -> tuple[list[float], int]:
    """Latencies of the queries that succeed under concurrent clients, and how many fail."""

    def one(fn: Callable[[], object]) -> float | None:
        began = time.perf_counter()
        try:
            fn()
        except Exception:
            return None
        return time.perf_counter() - began

    with ThreadPoolExecutor(clients) as pool:
        got = list(pool.map(one, queries))
    return [x for x in got if x is not None], sum(x is None for x in got)


def physical_plan(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def scans(df: DataFrame) -> int:
    """File scans in the physical plan."""
    return len(re.findall(r"FileScan ", physical_plan(df)))


def joins(df: DataFrame) -> int:
    return len(re.findall(r"(?:SortMergeJoin|BroadcastHashJoin|ShuffledHashJoin|BroadcastNestedLoopJoin|CartesianProduct)\b", physical_plan(df)))


def throughput_tb_h(size: int, seconds: float) -> float:
    return size / 1e12 / (seconds / 3600)


def cpu_hours(cpu_s: float) -> float:
    return cpu_s / 3600


@dataclass
class Meter:
    """What the stages of a span of work used, by Spark's own status store."""

    cpu_s: float = 0.0
    run_s: float = 0.0
    input_bytes: int = 0
    input_rows: int = 0
    output_bytes: int = 0
    peak_mb: float = 0.0
    stages: int = 0
    scans: int = 0


@contextmanager
def metered(spark: SparkSession) -> Iterator[Meter]:
    """A meter that is filled at the end of the block with the jobs that this thread ran in it.

    scans: stages that read files. peak_mb: the largest execution memory of a task, JVM side.
    """
    sc, jsc = spark.sparkContext, spark.sparkContext._jsc.sc()
    group, before, found = f"meter-{uuid.uuid4().hex}", sc.getLocalProperty("spark.jobGroup.id"), Meter()
    said = sc.getLocalProperty("spark.job.description")
    sc.setLocalProperty("spark.jobGroup.id", group)
    try:
        yield found
    finally:
        sc.setLocalProperty("spark.jobGroup.id", before)
        sc.setLocalProperty("spark.job.description", said)
        jsc.listenerBus().waitUntilEmpty()
        for stage in {s for j in sc.statusTracker().getJobIdsForGroup(group) if (info := sc.statusTracker().getJobInfo(j)) for s in info.stageIds}:
            try:
                d = jsc.statusStore().lastStageAttempt(stage)
            except Exception:  # evicted from the store, or never run
                continue
            if d.status().toString() == "SKIPPED":
                continue
            found.stages += 1
            found.cpu_s += d.executorCpuTime() / 1e9
            found.run_s += d.executorRunTime() / 1e3
            found.input_bytes += d.inputBytes()
            found.output_bytes += d.outputBytes()
            found.input_rows += d.inputRecords()
            found.scans += d.inputRecords() > 0
            found.peak_mb = max(found.peak_mb, d.peakExecutionMemory() / max(1, d.numTasks()) / (1 << 20))


def governance_share(spark: SparkSession, pool: str = "governance") -> float:
    """The share of all executors' run time so far that stages of the governance pool took."""
    jsc = spark.sparkContext._jsc.sc()
    jsc.listenerBus().waitUntilEmpty()
    stages = jsc.statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
    total = own = 0.0
    for i in range(stages.size()):
        d = stages.apply(i)
        total += d.executorRunTime()
        own += d.executorRunTime() if d.schedulingPool() == pool else 0
    return own / total if total else 0.0


def task_cost(hours_last_attempt: float, retries: int, expert: float) -> float:
    """Hours times (1 + retries), relative to the expert's."""
    return hours_last_attempt * (1 + retries) / expert


def degradation(points: Sequence[float]) -> float:
    """Largest to smallest point of a sweep."""
    return max(points) / min(points)


def storage_overhead(snap) -> float:
    """Bytes of views and replica to those of base tables."""
    base = sum(p.bytes for p in snap.physical if p.purpose in ("core", "features"))
    return sum(p.bytes for p in snap.physical if p.purpose in ("view", "replica")) / max(1, base)


def coverage(engine, table: str, wanted: Sequence[str]) -> dict[str, float]:
    """Shares of ids in the index, of wanted columns in the replica, and of batches with a fresh view of them."""
    snap = engine.catalog.snapshot(table)
    synced = {c for p in engine.materializer.replica(snap) for c in p.columns}
    batches = {b.name for b in snap.batches}
    viewed = {p.batch for ps in engine.materializer.views(snap).values() for p in ps if set(wanted) <= set(p.columns)}
    return {"index": engine.index.coverage(table), "replica": len(synced & set(wanted)) / max(1, len(set(wanted))), "views": len(viewed & batches) / max(1, len(batches))}


def catalog_latency_ms(engine, table: str, runs: int = 50) -> float:
    """Median milliseconds of a snapshot with one resolution."""

    def one() -> None:
        snap = engine.catalog.snapshot(table)
        snap.resolve(snap.batches[0].name, snap.columns[-1].name)

    return 1000 * measured_median(one, runs)
