"""Limits and peaks of a run don't depend on what its workers did before, and the tuning experiment builds each table once."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from widefeat import workloads
from widefeat.functions import models
from widefeat.operators.executor import Executor
from widefeat.operators.guard import Highest, guarded_arrow
from widefeat.operators.storage import ship


def test_a_run_has_only_its_own_memory(spark):
    """Twelve million letters need some 1,200 MB: with 384 MB they fail, also in a worker that has just had more."""
    ship(spark)
    many, one = models.embedding_many, models.embedding_one
    long = spark.range(40, numPartitions=1).select(F.repeat(F.lit("abcdef"), 50_000).alias("t"))
    short = spark.range(2, numPartitions=1).select(F.lit("abc").alias("t"))

    def run(rows, mb):
        peak = spark.sparkContext.accumulator(0.0, Highest())
        udf = guarded_arrow(many, one, "double", max_mb=mb, mode="task", peak=peak)
        rows.select(udf("t").alias("r")).select(F.sum("r.value")).collect()
        return peak.value

    high = run(long, 2500.0)
    assert high > 1000
    with pytest.raises(Exception, match="MemoryError"):
        run(long, 384.0)
    run(long, 2500.0)
    assert run(short, 800.0) < high - 500


def test_embedding_norm_by_its_formula():
    texts = pd.Series([None, "", "a", "☃\U0010ffff and words", "x" * 300_000 + "\U0001f600"])
    weights = models.embedding_weights()
    for got, text in zip(models.embedding_many(texts), texts, strict=True):
        drawn = weights[(np.array([ord(c) for c in text or ""], np.int64)[:, None] * np.arange(1, 9)) % len(weights)]
        assert got == pytest.approx(np.sqrt((drawn * drawn).sum()), rel=1e-12)
    assert len(models.embedding_many(pd.Series([], dtype=object))) == 0


def test_w6_makes_a_table_once_a_scale(spark, small_dir, monkeypatch):
    made, units, build, run_unit = [], [], workloads.repeated, Executor.run_unit
    monkeypatch.setattr(workloads, "repeated", lambda s, d, k, *rest: made.append(k) or build(s, d, k, *rest))
    monkeypatch.setattr(Executor, "run_unit", lambda self, request, run_id, task, attempt: units.append((task.columns, self.engine.config.tuning)) or run_unit(self, request, run_id, task, attempt))
    inner = workloads.WORKLOADS["w6_tuning"].__closure__[0].cell_contents
    rows = {(r.config, r.measure): r.value for r in inner(spark, small_dir, scales=(1, 2)).collect()}
    assert made == [1, 2] and {c for c, _ in units} == {("processed",), ("embedding_norm",)}
    assert {t for c, t in units if c == ("embedding_norm",)} == {"expert", "default", "adaptive"}
    for config in ("expert", "default", "adaptive"):
        assert all(rows[config, f"success_{k}"] == 1 and f"peak_{k}" in {m for c, m in rows if c == config} for k in (1, 2))
