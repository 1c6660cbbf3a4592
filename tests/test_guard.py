"""Record isolation, joins and samples."""

import time

import pytest
from pyspark.sql import functions as F

from widefeat.operators import guard, relational


def poison(x):
    if x % 10 == 0:
        raise ValueError("poison")
    if x % 10 == 1:
        time.sleep(2)
    return float(x)


def test_errors_timeouts_and_caps_become_rows(spark):
    df = spark.range(20).coalesce(1).withColumn("r", guard.guarded(poison, "double", timeout_s=0.2)("id"))
    got = {r.id: r.r for r in df.collect()}
    assert {i for i, r in got.items() if r.error_type == "ValueError"} == {0, 10} and {i for i, r in got.items() if r.error_type == "RecordTimeout"} == {1, 11}
    assert all(r.value == i and r.error_type is None for i, r in got.items() if i % 10 > 1) and "poison" in got[0].error_stack
    texts = spark.createDataFrame([("a" * 5,), ("a" * 50,), (None,)], "t string")
    sizes = texts.select(guard.guarded(lambda t: None if t is None else float(len(t)), "double", max_input_chars=10)("t").alias("r")).collect()
    assert sorted(str(r.r.error_type) for r in sizes) == ["None", "None", "RecordTooLarge"]


def test_memory_limit(spark):
    df = spark.range(2).coalesce(1).select(guard.guarded(lambda i: float(len(bytearray(400 << 20))) if i else 1.0, "double", max_mb=100)("id").alias("r"))
    assert [r.r.error_type for r in df.collect()] == [None, "MemoryError"]


def test_arrow_guard_equals_row_guard(spark):
    def many(s):
        if (s % 7 == 3).any():
            raise ValueError("x")
        return s * 2.0

    def one(x):
        if x % 7 == 3:
            raise ValueError("x")
        return x * 2.0

    df = spark.range(100).repartition(5)
    a = df.select("id", guard.guarded_arrow(many, one, "double")("id").alias("r"))
    b = df.select("id", guard.guarded(one, "double")("id").alias("r"))
    pick = lambda d: sorted((r.id, r.r.value, r.r.error_type) for r in d.collect())
    assert pick(a) == pick(b)
    with pytest.raises(Exception, match="x"):
        df.select(guard.guarded(one, "double", mode="task")("id")).collect()
    report = guard.isolation_report(a, "r").first()
    assert report.rows == 100 and report.rows_bad == sum(i % 7 == 3 for i in range(100))


def test_retry_of_a_passing_error():
    tries = []

    def fn():
        tries.append(1)
        if len(tries) < 3:
            raise OSError
        return 1

    assert guard.attempt(fn, (), 1, None, None, 2) == (1, None, None)


def test_joins(spark):
    points = spark.createDataFrame([(i,) for i in range(0, 100, 3)], "p long")
    spans = spark.createDataFrame([(1, 0, 10), (2, 5, 50), (3, 7, 7), (4, 90, 1000)], "k long, lo long, hi long")
    got = sorted((r.p, r.k) for r in relational.range_join(points, spans, "p", "lo", "hi", 16).collect())
    assert got == sorted((p, k) for p in range(0, 100, 3) for k, lo, hi in [(1, 0, 10), (2, 5, 50), (3, 7, 7), (4, 90, 1000)] if lo <= p < hi)
    left = spark.createDataFrame([("a", 5), ("a", 10), ("b", 1), ("a", 11)], "k string, t long")
    right = spark.createDataFrame([("a", 5, 50), ("a", 5, 51), ("a", 9, 90), ("b", 2, 20)], "k string, t long, v long")
    pick = lambda **o: sorted((r.k, r.t, r.asof_v) for r in relational.asof(left, right, "t", "k", "v", **o).collect())
    assert pick() == [("a", 5, 51), ("a", 10, 90), ("a", 11, 90), ("b", 1, None)]
    assert pick(direction="forward") == [("a", 5, 51), ("a", 10, None), ("a", 11, None), ("b", 1, 20)]
    assert pick(tolerance=1) == [("a", 5, 51), ("a", 10, 90), ("a", 11, None), ("b", 1, None)]
    one, two = (relational.hash_sample(spark.range(1000).repartition(n), 0.2, "id") for n in (2, 9))
    assert sorted(one.collect()) == sorted(two.collect()) and 120 < one.count() < 280
    hot = spark.range(500).select(F.lit(1).alias("k"), "id")
    assert relational.salted_join(hot, spark.createDataFrame([(1, "x")], "k int, y string"), "k").count() == 500
