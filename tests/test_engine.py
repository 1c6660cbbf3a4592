"""The engine on the given tables: ingestion, backfill, paths, layout changes, streams."""

import re

import pytest
from pyspark.sql import functions as F

from widefeat import worlds
from widefeat.engine import Engine
from widefeat.functions import library
from widefeat.metrics import physical_plan
from widefeat.model import COMPUTED, Column, ColumnLimitError, EngineConfig, FeatureSpec, PlanningError
from widefeat.operators.executor import BackfillRequest
from widefeat.operators.governance import Policy, ValidationError
from widefeat.sources.adapters import SourceSpec

Q = "select lang_guess, count(*) as n, max(char_len) as m from web where char_len > 100 group by lang_guess"


def rows(df):
    return sorted(map(str, df.collect()))


@pytest.fixture(scope="module")
def web(spark, small_dir):
    return worlds.world(spark, small_dir, "web")


def test_every_path_gives_the_same_answer(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web")
    base = rows(engine.sql(Q, path="base"))
    engine.materializer.sync("web", ["lang_guess", "char_len"])
    engine.materializer.build_view("web", ["char_len", "quality", "raw"], view_id="v")
    assert engine.plan(Q)[0]["web"].route == "replica" and rows(engine.sql(Q)) == base
    wide = "select entity_id, char_len, quality, raw.source_key as k from web where quality > 0.4"
    base_wide = rows(engine.sql(wide, path="base"))
    assert engine.plan(wide)[0]["web"].reason.startswith("full match") and rows(engine.sql(wide)) == base_wide
    partial = wide.replace("char_len,", "char_len, math_hit,")
    assert engine.plan(partial)[0]["web"].reason.startswith("partial match") and rows(engine.sql(partial)) == rows(engine.sql(partial, path="base"))
    engine.refresh("web", [("src3", "char_len"), ("src4", "quality")])
    assert engine.plan(Q)[0]["web"].route != "replica" and rows(engine.sql(Q)) == base
    plan = engine.plan(wide)[0]["web"]
    assert plan.details["compensated"] == 2 and rows(engine.sql(wide)) == base_wide
    assert sorted(engine.materializer.refresh("web", "v")) == ["src3", "src4"] and engine.plan(wide)[0]["web"].details["compensated"] == 0
    engine.materializer.drop_view("web", "v")
    assert engine.plan(wide)[0]["web"].route == "base"


def test_shards_that_are_not_needed_are_not_joined(web):
    a = web.plan("select char_len from web where batch_name = 'src2'")[0]["web"]
    assert a.batches == ("src2",) and a.joins == 1 and len(a.tables) == 2
    plan = physical_plan(web.sql("select batch_name, count(*) from web group by 1"))
    assert "Join" not in plan and len(re.findall("FileScan", plan)) == 1
    pushed = physical_plan(web.sql("select entity_id from web where char_len > 1000"))
    assert "GreaterThan(char_len,1000)" in pushed and "raw" not in pushed


def test_outer_join_null_test_does_not_prune(web):
    text = "select count(*) as n from web a left join (select * from web where batch_name = 'src1') b on a.entity_id = b.entity_id where b.batch_name is null"
    total = web.sql("select count(*) as n from web").first().n
    assert web.sql(text).first().n == total - web.sql("select count(*) as n from web where batch_name = 'src1'").first().n


def test_concurrent_sessions_do_not_mix(spark, small_dir):
    from concurrent.futures import ThreadPoolExecutor

    engine = worlds.world(spark, small_dir, "web")
    with ThreadPoolExecutor(6) as pool:
        got = list(pool.map(lambda i: (i, engine.sql(f"select distinct batch_name as b from web where batch_name = 'src{i}'").collect()), range(12)))
    assert all([r.b for r in found] == [f"src{i}"] for i, found in got)


def test_ingest_rollback_and_conflict(spark, small_dir):
    engine = Engine(spark)
    args = (worlds.documents(small_dir), "web", "all", worlds.WEB_MAPPING)
    with pytest.raises(RuntimeError):
        engine.ingest(*args, create=worlds.WEB_COLUMNS, fail_before_commit=True)
    assert engine.catalog.snapshot("web").batches == () and engine.table("web").count() == 0
    engine.ingest(*args)
    with pytest.raises(PlanningError):
        engine.ingest(*args)
    assert len(engine.catalog.snapshot("web").batches) == 1


def test_broken_source_rows_are_set_aside(spark, tmp_path):
    from widefeat.sources.adapters import adapt

    (tmp_path / "x.json").write_text('{"a": 1, "b": "x"}\nnot json\n{"a": 2}\n')
    good, bad = adapt(spark, SourceSpec("json", str(tmp_path / "x.json"), schema="a long, b string"))
    assert sorted(r.a for r in good.collect()) == [1, 2]
    assert good.count() == 2 and [r[0] for r in bad.collect()] == ["not json"] and bad.count() == 1
    (tmp_path / "x.csv").write_text("a,b\n1,x\nz,y\n3,\n")
    good, bad = adapt(spark, SourceSpec("csv", str(tmp_path / "x.csv"), {"header": "true"}, "a long, b string"))
    assert sorted(r.a for r in good.collect()) == [1, 3] and bad.count() == 1


def test_hot_payload_is_combined_before_the_shuffle(spark):
    from widefeat.operators.ingest import deduplicate

    df = spark.range(3000).selectExpr("if(id % 3 = 0, 'hot', md5(string(id))) as entity_id", "'b' as batch_name", "id as _key", "string(id) as text")
    out = deduplicate(df, "keep_first")
    assert out.count() == 2001 and out.where("entity_id = 'hot'").first()._key == 0
    assert re.search("partial_min_by", physical_plan(out))


def test_backfill_resume_and_failure(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", EngineConfig(max_retries=1, concurrency=1), features=False)
    seen = []

    def fault(task, attempt):
        seen.append((task.columns, attempt))
        if "quality" in task.columns:
            raise RuntimeError("model is gone")

    engine.executor.fail_units = fault
    report = engine.executor.run(BackfillRequest("web", (("src0", "math_hit"),), run_id="r"))
    assert report.failed == (("src0", "quality"),) and report.blocked == (("src0", "math_hit"),)
    assert [a for c, a in seen if "quality" in c] == [1, 2]
    engine.executor.fail_units = None
    assert engine.executor.run(BackfillRequest("web", (("src0", "math_hit"),), run_id="r")).ok
    status = engine.catalog.snapshot("web").status
    assert all(status["src0", c] == COMPUTED for c in ("processed", "char_len", "quality", "math_hit"))
    with pytest.raises(PlanningError):
        engine.backfill("web", [("src0", "nothing")])
    with pytest.raises(PlanningError):
        engine.backfill("web", [("nowhere", "char_len")])


def test_where_and_types_are_checked(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", features=False)
    with pytest.raises(Exception, match="cast|CAST|type"):
        engine.add_feature("web", FeatureSpec.sql("x", "date", "raw", ["raw"]))
    engine.add_feature("web", FeatureSpec.sql("y", "bigint", "raw.source_key", ["raw"], where="raw.source_key < 5"))
    engine.backfill("web", columns=["y"])
    assert engine.sql("select y from web where y is not null").count() == engine.sql("select 1 as x from web where raw.source_key < 5").count()


def test_layout_changes_keep_every_value(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web")
    before = rows(engine.table("web"))
    snap = engine.catalog.snapshot("web")
    core = {p.batch: p for p in snap.physical if p.group == "core"}
    g = engine.governor
    g.policy = Policy(max_rows=3)
    assert g.row_split("web", core["src0"].phys_id) == "COMMITTED"
    parts = [p for p in engine.catalog.snapshot("web").physical if p.batch == "src0" and p.group == "core"]
    assert len(parts) > 1 and sum(p.rows for p in parts) == core["src0"].rows and all(a.hi == b.lo for a, b in zip(parts, parts[1:]))
    some = engine.sql("select entity_id from web where batch_name = 'src0'").first().entity_id
    assert len([t for t in engine.plan(f"select raw from web where entity_id = '{some}' and batch_name = 'src0'")[0]["web"].tables]) == 1
    assert g.merge_batch_files("web", "core", "src0") == "COMMITTED"
    assert g.compact("web", core["src1"].phys_id) == "COMMITTED" and g.merge_shards("web", "src1") == "COMMITTED"
    g.policy = Policy(column_limit=8, headroom=1.0, max_shard=5)
    wide = next(p for p in engine.catalog.snapshot("web").physical if p.batch == "src2" and len(p.columns) > 8)
    assert g.column_split("web", wide.phys_id) == "COMMITTED"
    with pytest.raises(ColumnLimitError):
        g.merge_shards("web", "src2")
    assert rows(engine.table("web")) == before
    assert rows(engine.table("web", version=snap.version)) == before
    assert g.vacuum("web", 3600) == 0 and g.vacuum("web", 0) > 3
    assert rows(engine.table("web")) == before


def test_evolution_faults_and_locks(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", features=False)
    p = engine.catalog.snapshot("web").physical[0]

    def fault(stage):
        raise OSError(stage)

    assert engine.governor.compact("web", p.phys_id, fault=fault).startswith("ROLLED_BACK")
    engine.catalog.store.try_lock("web", "core", "writer")
    assert engine.governor.compact("web", p.phys_id) == "POSTPONED"
    engine.catalog.store.unlock("web", "core", "writer")
    other = engine.catalog.snapshot("web").physical[1]
    with pytest.raises(ValidationError):
        engine.governor.evolve("web", "core", [p], lambda staging: [other])
    assert p in engine.catalog.snapshot("web").physical
    assert engine.governor.compact("web", p.phys_id) == "COMMITTED"


def test_index_reads_only_what_it_must(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", features=False)
    engine.backfill("web", columns=["char_len"])
    engine.index.catch_up("web", ["src1", "src2"])
    assert 0 < engine.index.coverage("web") < 1
    ids = [r.entity_id for r in engine.table("web", []).select("entity_id").orderBy("entity_id").limit(30).collect()]
    assert rows(engine.lookup_many("web", [*ids, "absent"])) == rows(engine.lookup_many("web", ids, use_index=False))
    engine.index.catch_up("web")
    assert engine.index.coverage("web") == 1 and engine.index.catch_up("web") == 0
    _, batches, files = engine.index.narrowed("web", engine.catalog.snapshot("web"), ids[:1])
    assert files == 3 and len(batches) == 1  # raw, processed, char_len
    assert engine.lookup("web", "absent").count() == 0


def test_stream_batches_equal_batch_ingestion(spark, small_dir, tmp_path):
    from widefeat.streaming import flows

    engine = Engine(spark)
    schema = spark.read.parquet(f"{small_dir}/events.parquet").schema
    source = tmp_path / "in"
    spark.read.parquet(f"{small_dir}/events.parquet").repartition(4).write.parquet(str(source))
    mapping = {c.name: c.name for c in worlds.SIGNAL_COLUMNS if c.name != "k"} | {"source_key": "event_id"}
    args = dict(create=worlds.SIGNAL_COLUMNS, id_strategy=("key", ["event_id"]))
    for _ in range(2):
        stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(source))
        flows.ingest_stream(engine, stream, "signal", "ev", mapping, str(tmp_path / "ck"), **args).awaitTermination()
    assert len(engine.catalog.snapshot("signal").batches) == 4
    assert rows(engine.table("signal", ["event_id", "value"]).drop("batch_name")) == rows(worlds.world(spark, small_dir, "signal").table("signal", ["event_id", "value"]).drop("batch_name"))


def test_export_and_log(spark, small_dir, tmp_path):
    engine = worlds.fresh(spark, small_dir, "web", features=False)
    engine.backfill("web", columns=["char_len"])
    engine.export("select entity_id, char_len from web where char_len > 300", str(tmp_path / "out"), "json")
    assert spark.read.json(str(tmp_path / "out")).count() == engine.sql("select char_len from web where char_len > 300").count()
    assert engine.query_log("web").where(F.array_contains("columns", "char_len")).count() == 2
    assert engine.sql("select count(*) as n from sys_batches").first().n == len(engine.catalog.snapshot("web").batches)


def test_unknown_template_column():
    assert {f.name for f in library.web_features()} >= {"plain", "quality", "math_hit", "lang_guess"}
    assert Column("x", "int").kind == "stage"


def test_catch_up_after_commits(spark, small_dir):
    engine = worlds.fresh(spark, small_dir, "web", features=False)
    engine.backfill("web", columns=["char_len"])
    engine.index.catch_up("web")
    engine.materializer.sync("web", ["char_len"])
    engine.materializer.build_view("web", ["char_len", "raw"], view_id="v")
    at = engine.catalog.snapshot("web").version
    assert engine.catch_up("web", at) == {"events": 0, "indexed": 0, "synced": 0, "refreshed": 0}
    engine.refresh("web", [("src0", "char_len")])
    assert engine.catch_up("web", at) == {"events": 1, "indexed": 1, "synced": 1, "refreshed": 1}
    assert engine.index.coverage("web") == 1


def test_near_duplicate_groups(spark, small_dir):
    from widefeat.functions import sets

    engine = Engine(spark)
    text = " ".join(f"word{i}" for i in range(200))
    rows_in = [(1, "s", text), (2, "s", text + " more"), (3, "t", text.replace("word7 ", "other ")), (4, "t", " ".join(f"other{i}" for i in range(90))), (5, "t", ""), (6, "t", "two words")]
    frame = spark.createDataFrame(rows_in, "doc_id long, source string, text string").withColumn("lang", F.lit("en"))
    engine.ingest(SourceSpec("memory", frame=frame), "web", "source", worlds.WEB_MAPPING, create=worlds.WEB_COLUMNS, many=True)
    for f in (library.plain_feature(), sets.minhash_feature(), sets.near_dup_feature()):
        engine.add_feature("web", f)
    assert engine.backfill("web", columns=["near_dup_group"]).ok
    groups = {}
    for r in engine.sql("select raw.source_key as k, near_dup_group as g from web").collect():
        groups.setdefault(r.g, set()).add(r.k)
    assert sorted(map(sorted, groups.values())) == [[1, 2, 3], [4], [5], [6]]


def test_data_source(spark, small_dir, tmp_path):
    from widefeat.catalog import Catalog
    from widefeat.metastore import MetaStore
    from widefeat.sources.datasource import WideTableSource

    db = str(tmp_path / "catalog.db")
    engine = Engine(spark, catalog=Catalog(MetaStore(db)))
    worlds.build_signal(engine, small_dir)
    spark.dataSource.register(WideTableSource)
    got = spark.read.format("widefeat").option("table", "signal").load(db)
    assert got.count() == engine.table("signal").count() == 1000
    assert rows(got.select("entity_id", "value", "batch_name")) == rows(engine.table("signal", ["value"]).select("entity_id", "value", "batch_name"))


def test_empty_and_odd_sources(spark):
    engine = Engine(spark)
    frame = spark.createDataFrame([], "doc_id long, source string, text string, lang string, entity_id int")
    for many, batch in ((True, "source"), (False, "none")):
        engine.ingest(SourceSpec("memory", frame=frame), "web", batch, worlds.WEB_MAPPING, create=worlds.WEB_COLUMNS, many=many)
    for f in library.web_features():
        engine.add_feature("web", f)
    assert engine.backfill("web", columns=["math_hit"]).ok and engine.sql("select count(*) as n from web").first().n == 0
    odd = spark.createDataFrame([(1, None, "text", None, 5), (None, "a/b=c d", None, "en", 6), (3, "a/b=c d", "text", "en", 7), (4, "é", "", "en", 8)], frame.schema)
    engine.ingest(SourceSpec("memory", frame=odd), "web", "source", worlds.WEB_MAPPING, many=True)
    assert engine.backfill("web", columns=["math_hit", "char_len"]).ok
    got = {(r.batch_name, r.k, r.n) for r in engine.sql("select batch_name, raw.source_key as k, char_len as n from web").collect()}
    # null and empty payloads have one id, equal texts another; the null source key comes first
    assert got == {("unknown", 1, 4), ("a/b=c d", None, None)}
    engine.index.catch_up("web")
    some = engine.sql("select entity_id from web where batch_name = 'unknown'").first().entity_id
    assert engine.lookup("web", some).count() == 1
