"""Behaviour that matters at scale: splits, balanced writes, units, memory limits, hot keys, counted models."""

import hashlib
import math
import random
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from widefeat import metrics, registry, worlds
from widefeat.engine import Engine
from widefeat.functions import library, models, sets
from widefeat.model import Column, ColumnLimitError, ConflictError, EngineConfig, FeatureSpec, Output, PlanningError
from widefeat.operators import guard, relational
from widefeat.plans import translate
from widefeat.plans.tuning import InputStats, ResourceParams
from widefeat.sources.adapters import SourceSpec


def test_tables_of_equal_columns(spark, small_dir):
    engine = Engine(spark)
    for name in ("one", "two"):
        source = SourceSpec("parquet", worlds.path_of(small_dir, "documents"), transform=lambda d, k=name: d.where("doc_id < 20" if k == "one" else "doc_id >= 150"))
        engine.ingest(source, name, "b", worlds.WEB_MAPPING, create=worlds.WEB_COLUMNS)
    n = {k: engine.table(k).count() for k in ("one", "two")}
    assert 0 < n["one"] != n["two"] > 0
    assert tuple(engine.sql("select (select count(*) from one), (select count(*) from two)").first()) == (n["one"], n["two"])
    both = engine.sql("select a.raw.source_key as x, b.raw.source_key as y from one a full join two b on a.entity_id = b.entity_id")
    assert both.where("x is not null").count() == n["one"] and both.where("y is not null").count() == n["two"]
    assert engine.sql("select count(*) as n from one p join one q on p.entity_id = q.entity_id").first().n == n["one"]
    assert engine.sql("select count(entity_id) as n from (select entity_id, raw from two where 1 = 0)").first().n == 0
    assert engine.sql("select count(*) as n from (select entity_id, raw.body as body from two)").first().n == n["two"]
    with pytest.raises(PlanningError):
        engine.sql("select * from one, two", version=1)
    assert engine.sql("select (select count(*) from one) as x, (select count(*) from two) as y", version={"one": 1}).first().x == 0


def test_settings_change_splits_and_batches(spark, mid_dir):
    engine = worlds.world(spark, mid_dir, "trade")
    snap = engine.catalog.snapshot("trade")

    def rows(split_mb, batch):
        session = translate.own_session(spark, engine.executor.settings(ResourceParams(split_mb, 400.0, batch, 1)))
        return translate.assemble(session, snap, ["quantity", "price", "shipdate"]).relation

    coarse, fine = rows(128.0, 10_000), rows(0.02, 10_000)
    assert fine.rdd.getNumPartitions() > 2 * coarse.rdd.getNumPartitions() and fine.count() == coarse.count()
    largest = lambda df: df.select(F.pandas_udf(lambda s: s * 0 + len(s), "double")("quantity").alias("n")).agg(F.max("n")).first()[0]
    assert largest(rows(128.0, 100)) <= 100 < largest(rows(128.0, 5000))


def test_runs_are_measured_and_learned_from(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", features=False)
    engine.backfill("web", columns=["quality"])
    runs = [r for r in engine.catalog.store.query("select * from runs") if r["feature"] == "quality"]
    assert runs and all(r["cpu_s"] > 0 and r["peak_mb"] > 50 and r["ok"] == 1 for r in runs)
    assert all(r.cpu_s == x["cpu_s"] and r.peak_mb == x["peak_mb"] for r, x in zip([r for r in engine.history.runs if r.feature == "quality"], runs, strict=True))
    for size, mb in ((10**6, 300.0), (2 * 10**6, 400.0)):
        engine.history.record(type(engine.history.runs[0])("other", size, 10, 1.0, mb))
    task = type("T", (), {"features": (type("F", (), {"name": "other", "model_mb": 10.0})(),)})()
    assert engine.executor.parameters(task, InputStats(1, 10, 4 * 10**6), 1).source == "history"


def test_units_and_counts_of_isolated_records(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", EngineConfig(unit_batches=3, concurrency=1, max_retries=0), features=False)
    report = engine.backfill("web", columns=["math_hit"], max_input_chars=4000)
    assert report.ok and all(t.units == 7 for t in report.tasks)
    errors = Counter(r.batch_name for r in engine.errors("web").where("column_name = 'math_hit'").collect())
    lineage = {r.batch_name: (r.rows_ok, r.rows_bad) for r in engine.sql("select batch_name, rows_ok, rows_bad from sys_lineage where column_name = 'math_hit'").collect()}
    rows = {b.name: b.rows for b in engine.catalog.snapshot("web").batches}
    assert sum(errors.values()) > 0 and lineage == {b: (n - errors[b], errors[b]) for b, n in rows.items()}


def test_resumed_counts(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", EngineConfig(unit_batches=5, concurrency=1, max_retries=1), features=False)
    seen = []

    def once(task, attempt):
        seen.append((task.columns, task.batches))
        if "math_hit" in task.columns and len([s for s in seen if "math_hit" in s[0]]) == 3:
            raise RuntimeError("lost")

    engine.executor.fail_units = once
    assert engine.backfill("web", columns=["math_hit"], max_input_chars=4000).ok
    hits = [b for c, b in seen if "math_hit" in c]
    assert len(hits) == 5 and len(set(hits)) == 4  # the lost unit alone is computed again
    bad = engine.sql("select sum(rows_bad) as n from sys_lineage where column_name = 'math_hit'").first().n
    assert bad == engine.errors("web").where("column_name = 'math_hit'").count() > 0


def test_guard_has_a_memory_limit_by_default(spark):
    def hungry(n):
        return float(len(bytearray(n << 20)) >> 20)

    rows = spark.createDataFrame([(1,), (2000,), (3,)], "n int")
    got = rows.select("n", guard.guarded(hungry, "double")("n").alias("r")).select("n", "r.value", "r.error_type").collect()
    assert {r.n: (r.value, r.error_type) for r in got} == {1: (1.0, None), 2000: (None, "MemoryError"), 3: (3.0, None)}
    many = lambda s: s.map(hungry)
    got = rows.coalesce(1).select("n", guard.guarded_arrow(many, hungry, "double")("n").alias("r")).select("n", "r.value", "r.error_type").collect()
    assert {r.n: r.error_type for r in got} == {1: None, 2000: "MemoryError", 3: None}


def test_resident_lane_gives_the_same_values(spark, small_dir):
    spec = FeatureSpec("quality_gpu", ("char_len", "word_count", "ngram_rep", "digit_ratio"), (Output("quality_gpu", "double"),), ("char_len", "word_count", "ngram_rep", "digit_ratio"), fn="quality", mode="gpu_only")
    engine = worlds.fresh(spark, small_dir, "web", features=False)
    engine.add_feature("web", spec)
    engine.backfill("web", columns=["quality", "quality_gpu"])
    rows = engine.sql("select quality, quality_gpu from web").collect()
    assert rows and all(r.quality == r.quality_gpu for r in rows)
    assert engine.sql("select distinct lane from sys_lineage where column_name = 'quality_gpu'").first().lane == "gpu(simulated)"


def test_shared_row_filter_reaches_the_scan(spark, small_dir):
    from widefeat.operators.executor import feature_columns
    from widefeat.plans.planner import FusedTask

    engine = worlds.world(spark, small_dir, "web")
    specs = tuple(FeatureSpec.sql(f"f{i}", "bigint", f"char_len + {i}", ["char_len"], where="char_len > 500") for i in range(2))
    task = FusedTask(number=0, batches=("src0",), lane="sql", level=0, features=specs, columns=("f0", "f1"), after=())
    out, _ = feature_columns(engine.table("web", ["char_len"]), task, "record", None, 5.0)
    assert "GreaterThan(char_len,500)" in metrics.physical_plan(out)


def test_a_skewed_batch_is_written_by_many_tasks(spark, mid_dir):
    engine = Engine(spark)
    source = SourceSpec("parquet", worlds.path_of(mid_dir, "lineitem"), transform=lambda d: d.repartition(16))
    mapping = {"n": "l_quantity", "t": "array_join(transform(sequence(1, 20), i -> md5(concat(l_orderkey, '-', l_partkey, '-', i))), '')", "source_key": "l_orderkey"}
    columns = [Column("n", "double"), Column("t", "string")]
    engine.ingest(source, "skewed", "if(l_orderkey % 50 = 0, 'small', 'large')", mapping, create=columns, many=True, id_strategy=("key", ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]), dedup=False)
    files = {p.batch: p.files for p in engine.catalog.snapshot("skewed").physical}
    assert files["large"] >= 4 and files["small"] <= 2
    assert engine.table("skewed", ["n"]).count() == spark.read.parquet(worlds.path_of(mid_dir, "lineitem")).count()
    engine.materializer.build_view("skewed", ["n", "t"], view_id="v")
    assert {p.batch: p.files for p in engine.catalog.snapshot("skewed").physical if p.purpose == "view"}["large"] >= 4


def test_writers_and_layout_changes_exclude_each_other(spark, small_dir):
    store = worlds.fresh(spark, small_dir, "web", features=False).catalog.store
    with store.writing("web", "core", "a"), store.writing("web", "core", "b"):
        assert not store.try_lock("web", "core", "governor")
    assert store.try_lock("web", "core", "governor")
    with pytest.raises(ConflictError), store.writing("web", "core", "c", patience_s=0.1):
        pass
    store.unlock("web", "core", "governor")
    with store.writing("web", "core", "c", lease_s=-1):
        assert store.try_lock("web", "core", "governor")  # an expired writer is none


def test_catalog_refuses_tables_over_the_limit(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", EngineConfig(column_limit=10, max_fused=100, max_retries=0), features=False)
    report = engine.backfill("web", columns=library.TEXT_FEATURES)
    assert not report.ok and any("ColumnLimitError" in t.error for t in report.tasks)
    with pytest.raises(ColumnLimitError):
        raise ColumnLimitError("is a planning error of its own")
    engine = worlds.fresh(spark, small_dir, "web", EngineConfig(column_limit=10, max_fused=6), features=False)
    assert engine.backfill("web", columns=library.TEXT_FEATURES).ok


def test_index_buckets_follow_rows(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", features=False)
    engine.index.bucket_rows = 50
    engine.index.catch_up("web")
    assert {int(p.rpartition("-")[2]) for p in engine.index.covered("web").values()} == {4}
    ids = [r.entity_id for r in engine.table("web", []).select("entity_id").collect()]
    assert engine.lookup_many("web", ids, ["raw"]).count() == len(ids)
    located = engine.index.locate("web", ids[:1])
    assert located.count() == 1 and len(located.inputFiles()) == 1


def test_asof_and_packing_in_parts(spark):
    rnd = random.Random(3)
    left = spark.createDataFrame([(rnd.randrange(1000), "hot" if i % 3 else f"k{i % 5}") for i in range(400)], "t long, k string")
    right = spark.createDataFrame([(rnd.randrange(1000), "hot" if i % 3 else f"k{i % 5}", i) for i in range(150)], "t long, k string, v long")
    rows = lambda df: sorted(map(tuple, df.collect()), key=str)
    for direction in ("backward", "forward"):
        for tolerance in (None, 20):
            whole = relational.asof(left, right, "t", "k", "v", direction, tolerance)
            assert rows(relational.asof(left, right, "t", "k", "v", direction, tolerance, width=37)) == rows(whole)
    found = {(r.t, r.k): r.asof_v for r in relational.asof(left, right, "t", "k", "v", width=37).collect()}
    sides = right.collect()
    for (t, k), v in found.items():
        before = [(r.t, r.v) for r in sides if r.k == k and r.t <= t]
        assert v == (max(before)[1] if before else None)
    sized = spark.createDataFrame([("a" if i % 3 else "b", f"{i * 7919 % 4096:03x}", i % 50) for i in range(500)], "g string, o string, n long")
    assert rows(relational.pack_running(sized, "g", "o", "n", 128)) == rows(relational.pack_running(sized, "g", "o", "n", 128, F.substring("o", 1, 1)))


def test_count_min_and_strata(spark):
    rows = spark.range(5000).selectExpr("id", "cast(if(id % 3 = 0, 0, id % 97) as long) as k")
    exact = {r.k: r.n for r in rows.groupBy("k").agg(F.count("*").alias("n")).collect()}
    assert {r.k: r.n for r in relational.count_min(rows, "k", 5, 4096).collect()} == exact
    narrow = {r.k: r.n for r in relational.count_min(rows, "k", 3, 16).collect()}
    assert all(narrow[k] >= n for k, n in exact.items())
    got = relational.stratified_sample(rows, "k", {"0": 0.5}, 0.0, "id")
    assert got.where("k <> 0").count() == 0 and 600 < got.count() < 1100


def test_perplexity_counts_all_rows_of_a_language(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", features=False)
    engine.add_feature("web", library.template("ppl"))
    assert engine.backfill("web", columns=["ppl"]).ok
    rows = engine.sql("select processed.plain as plain, lang_guess, ppl from web").collect()
    three, two = defaultdict(Counter), defaultdict(Counter)
    for r in rows:
        for counts, cells in zip((three, two), sets.trigram_cells(r.plain or ""), strict=True):
            counts[r.lang_guess].update(cells.tolist() if r.plain else [])
    for r in rows:
        if r.plain:
            a, b = (c.tolist() for c in sets.trigram_cells(r.plain))
            want = math.exp(-sum(math.log((three[r.lang_guess][x] + sets.ADDED) / (two[r.lang_guess][y] + sets.ADDED * sets.ALPHABET)) for x, y in zip(a, b, strict=True)) / len(a))
            assert math.isclose(r.ppl, want, rel_tol=1e-9)
        else:
            assert r.ppl is None


def auc(scores, labels):
    pos, neg = ([s for s, y in zip(scores, labels, strict=True) if y == v] for v in (1, 0))
    return np.mean([(p > n) + (p == n) / 2 for p in pos for n in neg])


def test_safety_is_learned(spark):
    sf_dir = "/root/testdata/sf0.1"
    weights = worlds.safety_model(spark, sf_dir)
    held = spark.read.parquet(worlds.path_of(sf_dir, "labels")).where("doc_id % 5 = 0").join(spark.read.parquet(worlds.path_of(sf_dir, "documents")), "doc_id").collect()
    one = models.safety_with(weights).one
    assert auc([one(r.text) for r in held], [r.toxic for r in held]) > 0.85 and one(None) is None
    with pytest.raises(PlanningError):
        models.model_of(library.template("safety"))


def test_w1_exports_the_same_rows_by_both_workflows(spark, small_dir):
    got = {(r.config, r.measure): r.value for r in registry.QUERIES["w1_curation_end_to_end"](spark, small_dir).collect()}
    one = models.safety_with(worlds.safety_model(spark, small_dir)).one
    turns = defaultdict(list)
    for r in spark.read.parquet(worlds.path_of(small_dir, "conversations")).collect():
        turns[r.conv_id].append((r.turn, r.text or ""))
    safe = {hashlib.md5(str(c).encode()).hexdigest() for c, ts in turns.items() if one("\n".join(t for _, t in sorted(ts))) < 0.5}
    want = sum(r.entity_id in safe for r in registry.QUERIES["w1_answer"](spark, small_dir).collect())
    assert got["full", "rows"] == got["legacy", "rows"] == want > 0


def test_garbage_flag(spark):
    expr = library.expressions("t")["garbage_flag"][1]
    rows = spark.createDataFrame([("plain words, and more.",), ("a~b^c_d{e}",), ("bad � mark",), ("###",), ("",), (None,), ("naïve “quotes” are few in a long enough line of words",)], "t string")
    assert [r[0] for r in rows.selectExpr(expr).collect()] == [False, True, True, True, False, None, False]


def test_near_duplicates_in_a_crowded_band(spark, monkeypatch):
    """Bands with thousands of slices give the same groups as one slice a band."""
    rnd = random.Random(9)
    base = [rnd.randrange(1 << 40) for _ in range(sets.HASHES)]
    rows = []
    for i in range(160):
        sig = list(base)
        for _ in range(rnd.choice([0, 3, 6, 20, 40])):
            sig[rnd.randrange(sets.HASHES)] = rnd.randrange(1 << 40)
        rows.append((f"{i:03d}", "b", sig))
    frame = spark.createDataFrame(rows, "entity_id string, batch_name string, minhash_sig array<bigint>")
    staged = lambda df, name: spark.createDataFrame(df.collect(), df.schema)
    monkeypatch.setattr(sets, "SLICE", 8)
    got = {r.entity_id: r.near_dup_group for r in sets.near_dup_groups(frame, staged).collect()}
    parent = {i: i for i, *_ in rows}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, _, a in rows:
        for j, _, b in rows:
            shared = any(a[k * sets.BAND : (k + 1) * sets.BAND] == b[k * sets.BAND : (k + 1) * sets.BAND] for k in range(sets.HASHES // sets.BAND))
            if i < j and shared and sum(x == y for x, y in zip(a, b, strict=True)) >= sets.SIMILAR * sets.HASHES:
                x, y = sorted((root(i), root(j)))
                parent[y] = x
    want = defaultdict(set)
    have = defaultdict(set)
    for i, *_ in rows:
        want[root(i)].add(i)
        have[got[i]].add(i)
    assert sorted(map(sorted, want.values())) == sorted(map(sorted, have.values()))


def test_meter(spark, small_dir):
    with metrics.metered(spark) as m:
        spark.read.parquet(worlds.path_of(small_dir, "documents")).groupBy("lang").count().collect()
    assert m.cpu_s > 0 and m.scans == 1 and m.stages >= 2 and m.input_rows == 200
    assert 0 <= metrics.governance_share(spark) <= 1
