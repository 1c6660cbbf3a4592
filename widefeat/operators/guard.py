"""Record-level isolation: one bad record gives a NULL and an error row, not a failed task.

Every call runs under a time limit (a timer signal in the worker's main thread) and a cap on its input; exceptions,
timeouts and memory errors become the error part of the result struct. The vectorised form runs whole batches bare
and falls back to guarded single rows only in a batch that fails.
"""

from __future__ import annotations

import ctypes
import gc
import resource
import signal
import traceback
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager, suppress
from functools import lru_cache
from typing import Any

import pandas as pd
from pyspark.accumulators import AccumulatorParam
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.models import unload

DEFAULT_MB = 512.0


class Highest(AccumulatorParam):
    """An accumulator that keeps the largest value."""

    def zero(self, value: float) -> float:
        return 0.0

    def addInPlace(self, value1: float, value2: float) -> float:
        return max(value1, value2)


def resident_mb() -> float:
    """The most memory that this worker process has held (since `renew`, where that was called)."""
    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024


class RecordTimeout(Exception):
    """A record took longer than its limit."""


class RecordTooLarge(Exception):
    """A record is larger than its cap."""


def address_space() -> int:
    """Bytes of address space that this process has."""
    with open("/proc/self/statm") as f:
        return int(f.read().split()[0]) * resource.getpagesize()


@lru_cache(maxsize=1)
def at_start() -> int:
    """The address space that this worker had when it was first asked, before any model was loaded."""
    return address_space()


_run = ""


def renew(run: str) -> None:
    """Before the first batch of another run, make this worker as good as new: Spark hands workers on from job to job.

    Models go, free memory goes back to the system (large arrays always, or a later run would live on what an earlier one
    left behind, within no limit), and start and peak are measured again.
    """
    global _run
    if run == _run:
        return
    _run = run
    unload()
    gc.collect()
    with suppress(AttributeError):  # glibc only
        libc = ctypes.CDLL(None)
        libc.mallopt(-3, 1 << 16)  # M_MMAP_THRESHOLD: it grows with what is freed unless it is set
        libc.malloc_trim(0)
    with suppress(OSError), open("/proc/self/clear_refs", "w") as f:
        f.write("5")
    at_start.cache_clear()
    at_start()


@contextmanager
def limited(seconds: float, max_mb: float | None, whole: bool = False) -> Iterator[None]:
    """Within: an alarm after `seconds`, and at most `max_mb` more address space than now (whole: than the worker began with)."""

    def ring(*_):
        raise RecordTimeout(f"over {seconds} s")

    old = signal.signal(signal.SIGALRM, ring)
    limits = resource.getrlimit(resource.RLIMIT_AS)
    if max_mb:
        ceiling = int((at_start() if whole else address_space()) + max_mb * (1 << 20))
        resource.setrlimit(resource.RLIMIT_AS, (ceiling if limits[1] in (-1, resource.RLIM_INFINITY) else min(ceiling, limits[1]), limits[1]))
    signal.setitimer(signal.ITIMER_REAL, seconds)
    try:
        yield
    finally:
        signal.setitimer(signal.ITIMER_REAL, 0)
        signal.signal(signal.SIGALRM, old)
        if max_mb:
            resource.setrlimit(resource.RLIMIT_AS, limits)


def summary(e: BaseException) -> str:
    """The last frames of a traceback on one line."""
    return " < ".join(f"{f.name}:{f.lineno}" for f in reversed(traceback.extract_tb(e.__traceback__)[-3:]))


def attempt(fn: Callable, values: tuple, timeout_s: float, max_mb: float | None, max_chars: int | None, retries: int) -> tuple[Any, str | None, str | None]:
    """(value, error type, error summary) of one call."""
    for left in range(retries, -1, -1):
        try:
            if max_chars is not None and (n := sum(len(v) for v in values if isinstance(v, str))) > max_chars:
                raise RecordTooLarge(f"{n} characters")
            with limited(timeout_s, max_mb):
                return fn(*values), None, None
        except Exception as e:
            if not left:
                return None, type(e).__name__, summary(e) or str(e)[:200]
    raise AssertionError


def result_type(returns: T.DataType | str) -> T.StructType:
    kind = T.StructType.fromDDL(f"x {returns}")[0].dataType if isinstance(returns, str) else returns
    return T.StructType([T.StructField("value", kind), T.StructField("error_type", T.StringType()), T.StructField("error_stack", T.StringType())])


def guarded(fn: Callable, returns: str, timeout_s: float = 5.0, max_mb: float | None = DEFAULT_MB, max_input_chars: int | None = None, mode: str = "record", record_retries: int = 0) -> Callable[..., Column]:
    """A row-wise function as a UDF of struct<value, error_type, error_stack>. mode task: the bare function, errors fail the task."""

    def run(*values):
        if mode == "task":
            if max_input_chars is not None and sum(len(v) for v in values if isinstance(v, str)) > max_input_chars:
                raise RecordTooLarge("a record over the cap")
            return fn(*values), None, None
        return attempt(fn, values, timeout_s, max_mb, max_input_chars, record_retries)

    return F.udf(run, result_type(returns)).asNondeterministic()


def judged(fn: Callable[..., pd.Series], one: Callable, series: tuple[pd.Series, ...], timeout_s: float, max_mb: float | None, max_input_chars: int | None, mode: str, run: str = "") -> pd.DataFrame:
    """A batch as value, error_type and error_stack: whole if it can be, else row by row under the limits.

    mode task: nothing is isolated, and the worker, models and all, has to do with `max_mb`; run: for which of the runs.
    """
    at_start()
    if run:
        renew(run)
    large = None
    if max_input_chars is not None:
        large = sum((s.str.len().fillna(0) for s in series if s.dtype == object or str(s.dtype).startswith("str")), pd.Series(0, index=series[0].index)) > max_input_chars
    if mode == "task":
        if large is not None and large.any():
            raise RecordTooLarge("a record over the cap")
        with limited(3600.0, max_mb, whole=True):
            return pd.DataFrame({"value": fn(*series), "error_type": None, "error_stack": None})
    try:
        if large is None or not large.any():
            with limited(max(timeout_s, timeout_s * len(series[0]) / 100), max_mb):
                return pd.DataFrame({"value": fn(*series), "error_type": None, "error_stack": None})
    except Exception:
        pass
    rows = [attempt(one, v, timeout_s, max_mb, max_input_chars, 0) for v in zip(*series, strict=True)]
    return pd.DataFrame(rows, columns=["value", "error_type", "error_stack"])


def run_number(max_mb: float | None, mode: str) -> str:
    """Tells runs apart whose workers have all their memory limited."""
    return uuid.uuid4().hex if mode == "task" and max_mb else ""


def guarded_arrow(fn: Callable[..., pd.Series], one: Callable, returns: str, timeout_s: float = 5.0, max_mb: float | None = DEFAULT_MB, max_input_chars: int | None = None, mode: str = "record", peak=None) -> Callable[..., Column]:
    """A vectorised function; `one` is its row-wise form, used where a batch fails or holds a record over the cap.

    peak: an accumulator for the workers' largest resident memory in MB.
    """
    number = run_number(max_mb, mode)

    def run(*series: pd.Series) -> pd.DataFrame:
        out = judged(fn, one, series, timeout_s, max_mb, max_input_chars, mode, number)
        if peak is not None:
            peak.add(resident_mb())
        return out

    return F.pandas_udf(run, result_type(returns))


def resident_model(relation: DataFrame, models: list[tuple[str, Callable, Callable, str, list[str]]], timeout_s: float, max_mb: float | None, max_input_chars: int | None, mode: str, peak=None, profile=None) -> DataFrame:
    """`relation` with guarded structs of models that stay loaded for a whole partition (mapInPandas), for the GPU lane.

    models: (result column, vectorised, row-wise, type, argument columns); argument columns go. profile: the resources
    that a task asks for, where the master can give them.
    """
    args = {a for *_, names in models for a in names}
    kept = [f for f in relation.schema.fields if f.name not in args]
    number = run_number(max_mb, mode)
    schema = T.StructType([*kept, *(T.StructField(out, result_type(kind)) for out, _, _, kind, _ in models)])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            result = batch[[f.name for f in kept]].copy()
            for out, fn, one, _, names in models:
                result[out] = judged(fn, one, tuple(batch[n] for n in names), timeout_s, max_mb, max_input_chars, mode, number).to_dict("records") if len(batch) else []
            if peak is not None:
                peak.add(resident_mb())
            yield result

    return relation.mapInPandas(run, schema, profile=profile)


def split_errors(staged: DataFrame, results: dict[str, str], keys: tuple[str, ...]) -> tuple[DataFrame, DataFrame]:
    """From written structs (result column to output name): values, and error rows (keys, output, type, summary)."""
    values = staged.select(*(c for c in staged.columns if c not in results), *(F.col(f"{c}.value").alias(o) for c, o in results.items()))
    parts = F.filter(F.array(*(F.struct(F.lit(o).alias("column_name"), F.col(f"{c}.error_type").alias("error_type"), F.col(f"{c}.error_stack").alias("stack_summary")) for c, o in results.items())), lambda x: x["error_type"].isNotNull())
    return values, staged.select(*keys, F.inline(parts))


def isolation_report(staged: DataFrame, result: str) -> DataFrame:
    """Rows, good rows, bad rows and their share."""
    bad = F.col(f"{result}.error_type").isNotNull()
    return staged.agg(F.count("*").alias("rows"), F.count(F.when(~bad, 1)).alias("rows_ok"), F.count(F.when(bad, 1)).alias("rows_bad")).withColumn("anomaly_rate", F.try_divide(F.col("rows_bad"), F.col("rows")))
