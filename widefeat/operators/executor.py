"""Running a backfill: tasks as lazy plans, bounded concurrency, checkpoints, retries, commit of each pair."""

from __future__ import annotations

import json
import threading
import time
from collections.abc import Callable
from concurrent.futures import FIRST_COMPLETED, ThreadPoolExecutor, wait
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.models import model_of
from ..metrics import metered
from ..model import BATCH, BLOCKED, COMPUTED, FAILED, KEYS, RUNNING, LineageRecord, Physical, PlanningError
from ..plans import translate
from ..plans.planner import FusedTask, minimum_closure, plan_tasks, span_batches
from ..plans.tuning import InputStats, ResourceParams, Run, adapt, after_memory_failure, preset
from .guard import Highest, guarded_arrow, resident_model, split_errors
from .ingest import escaped
from .storage import delete, measured, new_id

ERRORS = "run_id string, entity_id string, batch_name string, column_name string, feature_version int, error_type string, stack_summary string"


@dataclass
class BackfillRequest:
    """(batch, column) pairs to be filled; ancestors that miss come along."""

    table: str
    pairs: tuple[tuple[str, str], ...]
    recompute: bool = False
    run_id: str | None = None
    max_input_chars: int | None = None
    timeout_s: float = 5.0


@dataclass
class TaskResult:
    task: FusedTask
    ok: bool
    attempts: int
    rows_ok: int = 0
    rows_bad: int = 0
    wall_s: float = 0.0
    resumed: bool = False
    error: str = ""
    units: int = 1
    scans: int = 0
    cpu_s: float = 0.0


@dataclass
class BackfillReport:
    run_id: str
    tasks: list[TaskResult] = field(default_factory=list)
    failed: tuple[tuple[str, str], ...] = ()
    blocked: tuple[tuple[str, str], ...] = ()

    @property
    def ok(self) -> bool:
        return not self.failed and not self.blocked

    @property
    def scans(self) -> int:
        """Tasks that read the input; each reads it once, a unit of batches at a time."""
        return sum(t.scans > 0 for t in self.tasks)

    @property
    def cpu_s(self) -> float:
        return sum(t.cpu_s for t in self.tasks)


class Scheduler:
    """Dispatch of tasks whose predecessors are done; a failure blocks only what depends on it. No Spark in here."""

    def __init__(self, concurrency: int, max_retries: int):
        self.concurrency, self.max_retries = concurrency, max_retries

    def run(self, tasks: list[FusedTask], work: Callable[[FusedTask, int], TaskResult]) -> tuple[list[TaskResult], set[int], set[int]]:
        """Results, numbers of failed tasks, numbers of blocked ones."""
        done: set[int] = set()
        failed: set[int] = set()
        blocked: set[int] = set()
        left, results, attempts = {t.number: t for t in tasks}, [], {}
        with ThreadPoolExecutor(max_workers=self.concurrency) as pool:
            running = {}
            while left or running:
                for n, t in list(left.items()):
                    if set(t.after) & (failed | blocked):
                        blocked.add(n)
                        del left[n]
                    elif set(t.after) <= done and len(running) < self.concurrency:
                        attempts[n] = attempts.get(n, 0) + 1
                        running[pool.submit(work, t, attempts[n])] = t
                        del left[n]
                if not running:
                    if not left:
                        break
                    continue
                finished, _ = wait(running, return_when=FIRST_COMPLETED)
                for f in finished:
                    t = running.pop(f)
                    try:
                        results.append(f.result())
                        done.add(t.number)
                    except Exception as e:
                        if attempts[t.number] <= self.max_retries:
                            left[t.number] = t
                        else:
                            failed.add(t.number)
                            results.append(TaskResult(t, False, attempts[t.number], error=f"{type(e).__name__}: {e}"[:500]))
        return results, failed, blocked


def feature_columns(relation: DataFrame, task: FusedTask, guard_mode: str, max_input_chars: int | None, timeout_s: float, max_mb: float | None = 512.0, peak=None) -> tuple[DataFrame, dict[str, str]]:
    """The task's outputs on top of its inputs; results of models come as guarded structs (column to output).

    A row filter that all features share is applied to the input, where it reaches the scan; rows it drops are NULL.
    """
    structs: dict[str, str] = {}
    bound: dict[str, str] = {}
    shared = {f.where for f in task.features}
    common = shared.pop() if len(shared) == 1 else None
    if common:
        relation = relation.where(common)
    resident: list[tuple] = []
    for f in task.features:
        for name, expr in f.lets:  # shared subexpressions are projected once, below the features
            if bound.setdefault(name, expr) != expr:
                raise PlanningError(f"{name} stands for two expressions in one task")
            if name not in relation.columns:
                relation = relation.withColumn(name, F.expr(expr))
        passes = (lambda c, f=f: F.when(F.expr(f.where), c)) if f.where and not common else (lambda c: c)
        if f.fn is None:
            new = {o.name: passes(F.expr(e)).cast(o.type) for o, e in zip(f.outputs, f.exprs, strict=True)}
            relation = relation.withColumns(new)
        else:
            model, out = model_of(f), f.outputs[0]
            structs[f"_{out.name}"] = out.name
            if task.lane == "gpu" and (common or not f.where):
                names = [f"_arg_{out.name}_{i}" for i in range(len(f.exprs))]
                relation = relation.withColumns({n: F.expr(a) for n, a in zip(names, f.exprs, strict=True)})
                resident.append((f"_{out.name}", model.many, model.one, out.type, names))
            else:
                udf = guarded_arrow(model.many, model.one, out.type, timeout_s, max_mb, max_input_chars, guard_mode, peak)
                relation = relation.withColumn(f"_{out.name}", passes(udf(*(F.expr(a) for a in f.exprs))))
    outs = [c for c in task.columns if c not in structs.values()]
    done = [c for c in structs if c not in {r[0] for r in resident}]
    if resident:
        relation = relation.select(*KEYS, *outs, *done, *(a for r in resident for a in r[4]))
        relation = resident_model(relation, resident, timeout_s, max_mb, max_input_chars, guard_mode, peak, gpu_profile(relation))
    return relation.select(*KEYS, *outs, *structs), structs


def gpu_profile(relation: DataFrame):
    """A resource profile with a GPU a task where the cluster manager can give one, else none (the lane is then simulated)."""
    conf = relation.sparkSession.sparkContext.getConf()
    if conf.get("spark.master", "local").startswith("local") or not conf.get("spark.executor.resource.gpu.amount", ""):
        return None
    from pyspark.resource import ResourceProfileBuilder, TaskResourceRequests

    return ResourceProfileBuilder().require(TaskResourceRequests().cpus(1).resource("gpu", 1)).build


class Executor:
    """Backfills of one engine."""

    def __init__(self, engine):
        self.engine = engine
        self.fail_units: Callable[[FusedTask, int], None] | None = None  # tests inject failures here
        self.commit_lock = threading.Lock()
        self.peak_lock = threading.Lock()

    def plan(self, request: BackfillRequest) -> list[FusedTask]:
        snap = self.engine.catalog.snapshot(request.table)
        for batch, column in request.pairs:
            snap.column(column)
            if batch not in {b.name for b in snap.batches}:
                raise PlanningError(f"no batch {batch}")
        config = self.engine.config
        work = minimum_closure(snap.graph, snap.status, request.pairs, request.recompute)
        tasks = plan_tasks(snap, work, config.fuse, self.engine.load, config.max_fused)
        return span_batches(tasks) if config.extra.get("span", True) else tasks

    def units(self, snap, task: FusedTask) -> list[FusedTask]:
        """The task in parts of some batches, each with a checkpoint of its own; a feature over all rows is one part."""
        if task.features[0].scope == "table":
            return [task]
        config, out, held, size = self.engine.config, [], [], 0
        bytes_of: dict[str, int] = {}
        for p in snap.physical:
            if p.purpose in ("core", "features"):
                bytes_of[p.batch] = bytes_of.get(p.batch, 0) + p.bytes
        for b in task.batches:
            if held and (len(held) >= config.unit_batches or size + bytes_of.get(b, 0) > config.unit_bytes):
                out.append(replace(task, batches=tuple(held)))
                held, size = [], 0
            held.append(b)
            size += bytes_of.get(b, 0)
        return [*out, replace(task, batches=tuple(held))]

    def run(self, request: BackfillRequest) -> BackfillReport:
        engine, catalog = self.engine, self.engine.catalog
        run_id = request.run_id or new_id("run")
        tasks = self.plan(request)
        catalog.set_status(request.table, [(b, c) for t in tasks for b in t.batches for c in t.columns], RUNNING, run_id)
        scheduler = Scheduler(engine.config.concurrency, engine.config.max_retries)
        with catalog.store.writing(request.table, "features", run_id):
            results, failed, blocked = scheduler.run(tasks, lambda t, k: self.run_task(request, run_id, t, k))
        now = catalog.snapshot(request.table).status
        pairs = {t.number: tuple((b, c) for b in t.batches for c in t.columns if now.get((b, c)) != COMPUTED) for t in tasks}
        report = BackfillReport(run_id, results, tuple(p for n in sorted(failed) for p in pairs[n]), tuple(p for n in sorted(blocked) for p in pairs[n]))
        catalog.set_status(request.table, report.failed, FAILED, run_id)
        catalog.set_status(request.table, report.blocked, BLOCKED, run_id)
        return report

    def run_task(self, request: BackfillRequest, run_id: str, task: FusedTask, attempt: int) -> TaskResult:
        """All units of a task; those already written in this run are only committed."""
        began, units = time.time(), self.units(self.engine.catalog.snapshot(request.table), task)
        done = [self.run_unit(request, run_id, u, attempt) for u in units]
        return TaskResult(task, True, attempt, sum(d[0] for d in done), sum(d[1] for d in done), time.time() - began, all(d[2] for d in done), "", len(units), max(d[3] for d in done), sum(d[4] for d in done))

    def settings(self, params: ResourceParams) -> dict[str, str]:
        """What a task's parameters mean to its reads and its Arrow batches."""
        return {"spark.sql.files.maxPartitionBytes": str(int(params.split_mb * (1 << 20))), "spark.sql.execution.arrow.maxRecordsPerBatch": str(params.batch_rows)}

    def parameters(self, task: FusedTask, stats: InputStats, attempt: int) -> ResourceParams:
        """By rules and history, or a preset; halved splits and batches and more memory after a failure for lack of memory."""
        engine, feature = self.engine, task.features[0].name
        model_mb = max((f.model_mb for f in task.features), default=0.0)
        mode = engine.config.tuning
        params = adapt(feature, stats, model_mb, engine.history) if mode == "adaptive" else preset(mode if mode in ("default", "expert") else "default", stats, model_mb)
        for _ in range(attempt - 1 if mode != "default" and engine.history.short_of_memory(feature, stats.bytes) else 0):
            params = after_memory_failure(params)
        return params

    def run_unit(self, request: BackfillRequest, run_id: str, task: FusedTask, attempt: int) -> tuple[int, int, bool, int, float]:
        """Read, compute, write, split errors, commit: (good values, bad ones, whether it was there, scans, CPU seconds)."""
        engine, catalog, spark = self.engine, self.engine.catalog, self.engine.spark
        began, unit = time.time(), f"{task.level}:{task.lane}:{','.join(task.columns)}:{','.join(task.batches)}"
        table, snap = request.table, catalog.snapshot(request.table)
        known = catalog.store.query("select location, errors_at from checkpoints where run_id = ? and unit = ?", run_id, unit)
        final, errors_at, scans, cpu_s = f"{engine.root}/{table}/features/{new_id('f')}", "", 0, 0.0
        if known:
            final, errors_at = known[0]["location"], known[0]["errors_at"] or ""
            committed = catalog.store.query("select sum(rows_ok) as ok, sum(rows_bad) as bad from lineage where path = ? and run_id = ? and batch = ? and column_name = ?", table, run_id, task.batches[0], task.columns[0])[0]
            if committed["ok"] is not None:
                return committed["ok"], committed["bad"], True, 0, 0.0
        else:
            spark.sparkContext.setLocalProperty("spark.scheduler.pool", "backfill")
            if self.fail_units:
                self.fail_units(task, attempt)
            source = translate.assemble(spark, snap, task.inputs, task.batches)
            rows = sum(b.rows for b in snap.batches if b.name in task.batches)
            feature, models = task.features[0].name, any(f.fn for f in task.features)
            params = self.parameters(task, InputStats(len(source.tables), rows, source.bytes), attempt)
            tuned = translate.own_session(spark, self.settings(params))  # a scan keeps to the settings of the session that made it
            relation = translate.assemble(tuned, snap, task.inputs, task.batches).relation
            peak, limit = None, engine.config.guard_mb
            if models:
                with self.peak_lock:
                    peak = spark.sparkContext.accumulator(0.0, Highest())
                limit = (params.worker_mb if engine.config.extra.get("enforce_memory") else None) if engine.config.guard == "task" else limit
            try:
                with metered(spark) as meter:
                    if task.features[0].scope == "table":
                        computed, structs = self._set_feature(snap, task), {}
                    else:
                        computed, structs = feature_columns(relation, task, engine.config.guard, request.max_input_chars, request.timeout_s, limit, peak)
                    if structs:
                        staging = f"{final}-staged"
                        self._write(computed, staging)
                        staged = tuned.read.schema(computed.schema).parquet(staging).drop("_b")
                        values, errors = split_errors(staged, structs, KEYS)
                        self._write(values, final)
                        errors_at = f"{engine.root}/{table}/errors/{run_id}-{task.number}-{new_id('e')}"
                        kinds = {o: f for f in task.features for o in f.output_names}
                        version = F.coalesce(*(F.when(F.col("column_name") == o, F.lit(f.version)) for o, f in kinds.items()))
                        errors.select(F.lit(run_id).alias("run_id"), *KEYS, "column_name", version.alias("feature_version"), "error_type", "stack_summary").write.parquet(errors_at)
                        delete(spark, staging)
                    else:
                        self._write(computed, final)
            except BaseException as e:
                delete(spark, final)
                delete(spark, f"{final}-staged")
                held = max(peak.value if peak is not None else 0.0, params.worker_mb)
                engine.history.record(Run(feature, source.bytes, rows, 0.0, held, False, attempt, "MemoryError" in str(e)))
                self._log_run(run_id, table, task, attempt, 0, 0.0, held, source.bytes, 0, rows, params, time.time() - began)
                raise
            scans, cpu_s = meter.scans, meter.cpu_s
            held = max(peak.value if peak is not None else 0.0, meter.peak_mb)
            catalog.store.execute("insert or replace into checkpoints values (?, ?, ?, ?, ?)", run_id, unit, final, errors_at, time.time())
            if errors_at:
                catalog.store.execute("insert into errors values (?, ?, ?)", table, run_id, errors_at)
            engine.history.record(Run(feature, source.bytes, rows, cpu_s, held, True, attempt))
            self._log_run(run_id, table, task, attempt, 1, cpu_s, held, source.bytes, meter.output_bytes, rows, params, time.time() - began)
        bad = self._bad(errors_at)
        with self.commit_lock:
            ok = self._commit(table, run_id, task, final, bad, errors_at)
        return ok, sum(bad.values()), bool(known), scans, cpu_s

    def _log_run(self, run_id, table, task, attempt, ok, cpu_s, peak_mb, bytes_in, bytes_out, rows, params, wall) -> None:
        self.engine.catalog.store.execute("insert into runs values (?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?)", run_id, table, ",".join(f.name for f in task.features), ",".join(task.batches), attempt, ok, cpu_s, peak_mb, bytes_in, bytes_out, rows, json.dumps(params.__dict__), wall, task.lane)

    def _bad(self, errors_at: str) -> dict[tuple[str, str], int]:
        """Isolated records by batch and column."""
        if not errors_at:
            return {}
        counts = self.engine.spark.read.schema(ERRORS).parquet(errors_at).groupBy(BATCH, "column_name").agg(F.count("*").alias("n")).collect()
        return {(r[BATCH], r.column_name): r.n for r in counts}

    def _set_feature(self, snap, task: FusedTask) -> DataFrame:
        """A feature over all rows of its inputs, for the batches asked for."""
        from ..functions.sets import SETS

        engine, f = self.engine, task.features[0]
        rows = translate.assemble(engine.spark, snap, f.inputs).relation

        def staged(df: DataFrame, name: str) -> DataFrame:
            path = f"{engine.root}/{snap.path}/scratch/{new_id(name)}"
            df.write.option("compression", "zstd").parquet(path)
            return engine.spark.read.schema(df.schema).parquet(path)

        return SETS[f.fn](rows, staged, f.output_names[0]).where(F.col(BATCH).isin(list(task.batches)))

    def _write(self, df: DataFrame, path: str) -> None:
        """A folder a batch, without a shuffle: a task writes what it read."""
        df.withColumn("_b", F.col(BATCH)).write.option("compression", "zstd").partitionBy("_b").parquet(path)

    def _commit(self, table: str, run_id: str, task: FusedTask, path: str, bad: dict[tuple[str, str], int], errors_at: str) -> int:
        catalog, spark = self.engine.catalog, self.engine.spark
        snap = catalog.snapshot(table)
        rows = {b.name: b.rows for b in snap.batches}
        lane = f"{task.lane}(simulated)" if task.lane == "gpu" else task.lane
        at, add, records, trimmed, remove = catalog.column_versions(table), [], [], [], []
        for b in task.batches:
            found = measured(spark, Physical(new_id("feat"), "features", f"{path}/_b={escaped(spark, b)}", b, task.columns, "features", rows[b]))
            if found.files:  # a batch without rows, or with none that a row filter passes, has no files: its columns are NULL
                add.append(found)
            for f in task.features:
                inputs = json.dumps({i: at.get((b, i), at.get((b, ""), 0)) for i in f.inputs})
                records += [LineageRecord(run_id, b, o, f.name, f.version, lane, inputs, time.time(), rows[b] - bad.get((b, o), 0), bad.get((b, o), 0), errors_at, f.inputs) for o in f.output_names]
        for p in snap.physical:  # what a recomputation replaces no longer counts
            if p.purpose == "features" and p.batch in task.batches and (gone := set(p.columns) & set(task.columns)):
                kept = tuple(c for c in p.columns if c not in gone)
                if kept:
                    trimmed.append((p.phys_id, Physical(new_id("feat"), p.group, p.path, p.batch, kept, p.purpose, p.rows, p.bytes, p.files, p.lo, p.hi, p.sorted_by)))
                else:
                    remove.append(p.phys_id)
        catalog.commit_pairs(table, records, add, remove, trimmed)
        return sum(r.rows_ok for r in records)

