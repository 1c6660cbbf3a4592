"""The measured experiments: each returns rows (workload, config, measure, value, unit, run).

Sizes are those of the given tables; what carries over from the reference is which configuration wins and how
measures move, not seconds.
"""

from __future__ import annotations

import random
import time
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import metrics, worlds
from .baselines import Legacy, failover_loop
from .engine import Engine
from .functions import library
from .metrics import Recorder
from .model import ColumnLimitError, EngineConfig, FeatureSpec, Output
from .operators import guard
from .operators.executor import BackfillRequest
from .operators.governance import Policy, storage_report
from .operators.storage import ship
from .plans.tuning import History
from .sources.adapters import SourceSpec

WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def workload(f):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return f(spark, sf_dir)

    WORKLOADS[f.__name__] = run
    return f


def noop(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def union(spark: SparkSession, *records: Recorder) -> DataFrame:
    return spark.createDataFrame([x for r in records for x in r.rows], metrics.MEASURES)


@workload
def w1_curation_end_to_end(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight sources, twelve features, one export: the engine against the earlier workflow."""
    full, legacy = Recorder("w1", "full"), Recorder("w1", "legacy")
    features = worlds.sft_features(worlds.safety_model(spark, sf_dir))  # both use the same weights, learned before either is timed
    engine = Engine(spark)
    with full.stage("ingest"):
        worlds.build_sft(engine, sf_dir)
    names = [o for f in features for o in f.output_names]
    with full.stage("backfill"):
        report = engine.backfill("sft", columns=names)
    with full.stage("export"):
        n = engine.sql("select entity_id, quality, safety from sft where quality >= 0.5 and safety < 0.5 and n_turns >= 2 and alternates").count()
    full.put("rows", n)
    full.put("jobs", 2 + len(report.tasks))
    full.put("manual_steps", len(engine.calls))
    full.put("logical_tables", 1)
    old = Legacy(spark)
    rows = engine.table("sft", ["raw"])
    with legacy.stage("ingest"):
        old.ingest({b.name: rows.where(F.col("batch_name") == b.name).select("entity_id", "raw") for b in engine.catalog.snapshot("sft").batches})
    with legacy.stage("backfill"):
        old.backfill(features, [f.name for f in features])
    with legacy.stage("export"):
        m = old.export(["quality", "safety", "n_turns", "alternates"], "quality >= 0.5 and safety < 0.5 and n_turns >= 2 and alternates").count()
    legacy.put("rows", m)
    legacy.put("jobs", old.jobs)
    legacy.put("manual_steps", old.manual_steps)
    legacy.put("physical_tables", old.physical_tables)
    return union(spark, full, legacy)


EXPORT = "select entity_id, batch_name, char_len, word_count, lang_guess, ngram_rep, url_ratio, digit_ratio, garbage_flag, content_md5, line_rep, pii_flag, quality, math_hit, raw.url as url from web where {} char_len between 100 and 100000 and word_count > 20 and lang_guess in ('en', 'de', 'fr') and ngram_rep < 0.9 and digit_ratio < 0.2 and garbage_flag = false and line_rep < 0.5 and quality > 0.3"


TRADE_EXPORT = "select orderkey, linenumber, quantity, price, discount, tax, returnflag, linestatus, shipdate, orderpriority from trade where batch_name in ({}) and quantity > 5 and discount <= 0.08"


@workload
def w2_volume_sweep(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (1, 5, 10, 20), legacy: int = 5) -> DataFrame:
    """Export of 15 columns under 8 predicates over growing batch combinations, and of trade by years.

    NoGov has a shard a feature and as many files as tasks wrote; Legacy, for up to `legacy` sources, a table a source and
    feature, joined by hand.
    """
    good, bad, old, trade = (Recorder("w2", c) for c in ("full", "nogov", "legacy", "trade"))
    tidy = worlds.fresh(spark, sf_dir, "web")
    loose = worlds.fresh(spark, sf_dir, "web", EngineConfig(governance=False, fuse="off", unit_batches=1000), features=False)
    loose.backfill("web", columns=[o for f in library.web_features() for o in f.output_names])
    names = [b.name for b in tidy.catalog.snapshot("web").batches]
    for b in names[:20]:
        tidy.governor.merge_shards("web", b)
    earlier = Legacy(spark)
    if legacy:
        rows = tidy.table("web", ["raw"])
        earlier.ingest({b: rows.where(F.col("batch_name") == b).select("entity_id", "raw") for b in names[:legacy]})
        earlier.backfill(library.web_features(), [f.name for f in library.web_features()])
    for n in sizes:
        wanted = names[:n]
        text = EXPORT.format(f"batch_name in ({', '.join(repr(b) for b in wanted)}) and")
        for rec, engine in ((good, tidy), (bad, loose)):
            s = metrics.measured_median(lambda e=engine, t=text: noop(e.sql(t, log=False)))
            a = engine.plan(text)[0]["web"]
            rec.put(f"seconds_{n}", s, "s")
            rec.put(f"throughput_{n}", metrics.throughput_tb_h(a.bytes, s), "TB/h")
            rec.put(f"joins_{n}", a.joins)
            rec.put(f"files_{n}", len(a.tables))
        if n <= legacy:
            columns = [c for c in library.TEXT_FEATURES if c not in ("secret_flag", "license_flag")] + ["quality", "math_hit"]
            part = Legacy(spark, earlier.root, {b: earlier.tables[b] for b in wanted}, earlier.results)
            s = metrics.measured_median(lambda p=part: noop(p.export(columns, EXPORT.partition("where")[2].format(""))), 1)
            old.put(f"seconds_{n}", s, "s")
            old.put(f"joins_{n}", len(columns) * n)
    years = worlds.fresh(spark, sf_dir, "trade")
    for n in range(1, 8):
        text = TRADE_EXPORT.format(", ".join(f"'y{1995 + i}'" for i in range(n)))
        s = metrics.measured_median(lambda t=text: noop(years.sql(t, log=False)))
        trade.put(f"seconds_{n}", s, "s")
        trade.put(f"throughput_{n}", metrics.throughput_tb_h(years.plan(text)[0]["trade"].bytes, s), "TB/h")
    for rec in (good, bad, *([old] if legacy else []), trade):
        rec.put("degradation", metrics.degradation([v for _, _, m, v, _, _ in rec.rows if m.startswith("seconds")]))
    return union(spark, good, bad, old, trade)


MAIN = ["char_len", "word_count", "lang_guess", "digit_ratio", "ngram_rep", "garbage_flag", "line_rep"]
TEN = "select entity_id, batch_name, char_len, word_count, lang_guess, round(digit_ratio, 6) as digit_ratio, round(ngram_rep, 6) as ngram_rep, garbage_flag, round(line_rep, 6) as line_rep from web where lang_guess = 'en' and char_len > 500 order by entity_id limit 1000"


def widened(spark: SparkSession, sf_dir: str, width: int, limit: int, governed: bool, many: bool = True) -> tuple[Engine, str]:
    """A web table with `width` cheap features; no physical table may hold more than `limit` columns (the catalog sees to that).

    Governed: tasks are cut below the limit, and the governor moves columns that no query uses out of tables that come near
    it. Without: one physical table a batch takes every new column, as a table with a schema of its own would. many: a batch
    a source, else one in all.
    """
    engine = Engine(spark, EngineConfig(governance=governed, column_limit=limit, max_fused=int(0.9 * limit) if governed else 100_000, unit_batches=1000))
    engine.ingest(worlds.documents(sf_dir), "web", "source" if many else "all", worlds.WEB_MAPPING, create=worlds.WEB_COLUMNS, many=many)
    for f in library.web_features():
        engine.add_feature("web", f)
    cheap = [f"wide_{i}" for i in range(max(0, width - len(MAIN)))]
    for i in range(0, len(cheap), 20):
        part = cheap[i : i + 20]
        engine.add_feature("web", FeatureSpec(f"pack_{i}", ("char_len",), tuple(Output(c, "bigint") for c in part), tuple(f"char_len + {int(c[5:])}" for c in part)))
    if governed:
        engine.backfill("web", columns=MAIN)
        engine.backfill("web", columns=cheap)
        for _ in range(5):
            engine.sql(TEN)
        engine.governor.policy = Policy(column_limit=limit, headroom=0.5, max_shard=int(0.45 * limit), max_files=10**6, small_ratio=2.0)
        engine.governor.cycle("web")
    else:
        engine.governor.policy = Policy(column_limit=limit)
        for i in range(0, width, 40):
            engine.backfill("web", columns=[*MAIN, *cheap][i : i + 40])
            for b in engine.catalog.snapshot("web").batches:
                engine.governor.merge_shards("web", b.name)
    return engine, TEN


@workload
def w3_width_sweep(spark: SparkSession, sf_dir: str, widths: tuple[int, ...] = (20, 50, 120), limit: int = 60) -> DataFrame:
    """Latency of a fixed ten-column query while the table widens past the column limit."""
    records = []
    for governed in (True, False):
        rec = Recorder("w3", "full" if governed else "nogov")
        for w in widths:
            try:
                engine, text = widened(spark, sf_dir, w, limit, governed, False)
            except ColumnLimitError:
                rec.put(f"success_{w}", 0.0)
                continue
            noop(engine.sql(text, log=False))
            times, failed = metrics.replay([lambda e=engine, t=text: noop(e.sql(t, log=False))] * 8, clients=8)
            rec.put(f"success_{w}", 1 - failed / 8)
            rec.put(f"p95_{w}", metrics.percentile(times, 0.95), "s")
            rec.put(f"joins_{w}", engine.plan(text)[0]["web"].joins)
            rec.put(f"widest_{w}", max(len(p.columns) + 2 for p in engine.catalog.snapshot("web").physical))
        records.append(rec)
    return union(spark, *records)


@workload
def w4_fusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight features on one text column, fused and not."""
    records = []
    for fuse in ("physical", "off"):
        rec = Recorder("w4", "on" if fuse != "off" else "off")
        engine = worlds.fresh(spark, sf_dir, "web", EngineConfig(fuse=fuse, concurrency=1), features=False)
        engine.backfill("web", columns=["processed"])
        with rec.stage("backfill"):
            report = engine.backfill("web", columns=library.FUSED_EIGHT)
        rec.put("scans", report.scans)
        rec.put("cpu_hours", metrics.cpu_hours(report.cpu_s), "h")
        rec.put("bytes_read", sum(r["bytes_in"] for r in engine.catalog.store.query("select bytes_in from runs where run_id = ?", report.run_id)), "B")
        records.append(rec)
    return union(spark, *records)


class Oversized(ValueError):
    """A text over the cap."""


class Garbled(ValueError):
    """A text with runs of symbols."""


@workload
def w5_failover(spark: SparkSession, sf_dir: str, cap: int = 15_000) -> DataFrame:
    """Texts over a cap and garbled ones are broken records: isolated, failing the task, or removed round by round; and the guard's cost."""
    docs = spark.read.parquet(worlds.path_of(sf_dir, "documents")).select("doc_id", "text")
    on, off, old = Recorder("w5", "on"), Recorder("w5", "off"), Recorder("w5", "legacy")
    count = lambda t: float(sum(c.isdigit() for c in t))

    def strict(t):
        if len(t) > cap:
            raise Oversized(len(t))
        if "###" in t:
            raise Garbled("###")
        return count(t)

    with on.stage("run"):
        r = guard.isolation_report(docs.select("doc_id", guard.guarded(strict, "double")("text").alias("r")), "r").first()
    on.put("success", r.rows_ok / r.rows)
    on.put("anomalies", r.rows_bad)
    on.put("anomaly_rate", r.anomaly_rate)
    on.put("rounds", 1)
    try:
        noop(docs.select(F.udf(strict, "double")("text").alias("v")))
        off.put("success", 1.0)
    except Exception:
        off.put("success", 0.0)
    with old.stage("run"):
        rounds, removed = failover_loop(docs, strict, "text", {"Oversized": f"length(text) > {cap}", "Garbled": "contains(text, '###')"})
    old.put("rounds", rounds)
    old.put("removed", removed)
    clean = docs.where(F.length("text") <= cap)
    many = lambda s: s.map(count).astype(float)
    bare = metrics.measured_median(lambda: noop(clean.select(F.pandas_udf(many, "double")("text"))))
    kept = metrics.measured_median(lambda: noop(clean.select(guard.guarded_arrow(many, count, "double")("text"))))
    on.put("guard_overhead", kept / bare - 1)
    return union(spark, on, off, old)


#: What the model feature `quality` reads.
STATISTICS = ("char_len", "word_count", "ngram_rep", "digit_ratio")


def repeated(spark: SparkSession, sf_dir: str, times: int, config: EngineConfig | None = None, columns: tuple[str, ...] = STATISTICS) -> Engine:
    """A web table with every document `times` times, each a row of its own, `columns` (the inputs of a model) computed."""
    engine = Engine(spark, config)
    copies = lambda d: d.crossJoin(spark.range(times).withColumnRenamed("id", "copy")).withColumn("doc_id", F.col("doc_id") * times + F.col("copy"))
    engine.ingest(SourceSpec("parquet", worlds.path_of(sf_dir, "documents"), transform=lambda d: copies(d.join(d.groupBy("text").agg(F.min("doc_id").alias("doc_id")), ["doc_id", "text"], "left_semi"))), "web", "source", worlds.WEB_MAPPING, create=worlds.WEB_COLUMNS, many=True, id_strategy=("key", ["doc_id"]))
    for f in library.web_features():
        engine.add_feature("web", f)
    engine.backfill("web", columns=columns)
    return engine


@workload
def w6_tuning(spark: SparkSession, sf_dir: str, scales: tuple[int, ...] = (1, 4, 16)) -> DataFrame:
    """A feature whose model takes 350 MB in each worker and 64 bytes a character, on growing inputs: it runs, and a worker
    that goes over the memory it was given fails. Which settings survive, at the first try or later, and what they cost
    beside an expert's (CPU hours, by Spark's stage metrics, times tries).

    A table a scale for all of them: each run makes the whole column again, in workers without the models and memory of the
    run before.
    """
    cost: dict[int, float] = {}
    records = {c: Recorder("w6", c) for c in ("warm-up", "expert", "default", "adaptive")}
    histories = {c: History() for c in records}
    for k in scales:
        engine = repeated(spark, sf_dir, k, EngineConfig(guard="task", unit_batches=1000, extra={"enforce_memory": True}), ("processed",))
        engine.add_feature("web", library.model_feature("embedding_norm", "double", ("processed",), "all", 350.0))
        for config, rec in records.items():
            if config == "warm-up" and k != scales[0]:
                continue
            engine.config = replace(engine.config, tuning=config.replace("warm-up", "expert"))
            engine.history = histories[config]
            report = engine.backfill("web", columns=["embedding_norm"], recompute=True)
            runs = engine.catalog.store.query("select attempt, ok, cpu_s, peak_mb, wall_s from runs where run_id = ? and feature = 'embedding_norm' order by attempt", report.run_id)
            rec.put(f"success_{k}", float(report.ok))
            rec.put(f"first_submit_{k}", float(bool(runs[0]["ok"])))
            if report.ok:
                hours = metrics.cpu_hours(runs[-1]["cpu_s"])
                if config in ("warm-up", "expert"):
                    cost[k] = hours
                if k in cost:  # an expert's run may fail too
                    rec.put(f"cost_{k}", metrics.task_cost(hours, len(runs) - 1, cost[k]))
                rec.put(f"peak_{k}", runs[-1]["peak_mb"], "MB")
                rec.put(f"wall_{k}", runs[-1]["wall_s"], "s")
    return union(spark, *(r for c, r in records.items() if c != "warm-up"))


def ids_for(engine: Engine, n: int) -> list[str]:
    rows = engine.table("web", []).select("entity_id").orderBy(F.md5("entity_id")).limit(n).collect()
    return [r.entity_id for r in rows]


@workload
def w7_point_lookup(spark: SparkSession, sf_dir: str, n: int = 200, absent: int = 10) -> DataFrame:
    """Latencies of single lookups with and without the index, absent ids among them, by twenty clients."""
    engine = worlds.fresh(spark, sf_dir, "web")
    engine.index.catch_up("web")
    ids = [*ids_for(engine, n), *(f"absent-{i}" for i in range(absent))]
    records = []
    for use in (True, False):
        rec = Recorder("w7", "index" if use else "scan")
        times, failed = metrics.replay([lambda i=i, u=use: engine.lookup("web", i, use_index=u).collect() for i in ids], clients=20)
        rec.put("p50", metrics.percentile(times, 0.5), "s")
        for share, seconds in [metrics.cdf(times)[int(len(times) * p / 10) - 1][::-1] for p in range(1, 11)] if times else []:
            rec.put(f"cdf_{share:.1f}", seconds, "s")
        rec.put("p99", metrics.percentile(times, 0.99), "s")
        rec.put("failed", failed)
        snap = engine.catalog.snapshot("web")
        if use:
            narrow, batches, files = engine.index.narrowed("web", snap, ids[:1])
            rec.put("files_read", files)
        else:
            rec.put("files_read", sum(p.files for p in snap.physical if p.purpose in ("core", "features")))
        records.append(rec)
    return union(spark, *records)


AGGREGATES = {
    "a1": "select count(lang_guess) as n from web", "a2": "select lang_guess, garbage_flag, count(*) as n from web group by 1, 2", "a3": "select count(*) as n from web where digit_ratio > 0.001 and lang_guess = 'en'",
    "a4": "select batch_name, count(*), avg(quality), min(char_len), max(word_count), sum(digit_ratio) from web group by 1",
}


TRADE_AGGREGATES = {
    "t1": "select count(discount) as n from trade", "t2": "select returnflag, linestatus, count(*) as n from trade group by 1, 2", "t3": "select count(*) as n from trade where shipdate >= timestamp '1996-01-01 00:00:00' and shipdate < timestamp '1997-01-01 00:00:00'",
    "t4": "select returnflag, linestatus, count(*), sum(quantity), avg(price), avg(discount) from trade group by 1, 2",
}


@workload
def w8_aggregates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four aggregate shapes on base tables and on the replica, of web and of trade."""
    web = worlds.fresh(spark, sf_dir, "web", EngineConfig(fuse="off", unit_batches=1000))
    web.materializer.sync("web", ["lang_guess", "garbage_flag", "digit_ratio", "char_len", "word_count", "quality"])
    trade = worlds.fresh(spark, sf_dir, "trade")
    trade.materializer.sync("trade", ["returnflag", "linestatus", "shipdate", "discount", "quantity", "price"])
    records = []
    for path in ("replica", "base"):
        rec = Recorder("w8", path)
        for table, engine, texts in (("web", web, AGGREGATES), ("trade", trade, TRADE_AGGREGATES)):
            for name, text in texts.items():
                rec.put(f"{name}_s", metrics.measured_median(lambda t=text, p=path, e=engine: e.sql(t, path=p, log=False).collect()), "s")
                a = engine.plan(text, path=path)[0][table]
                rec.put(f"{name}_joins", a.joins)
                rec.put(f"{name}_bytes", a.bytes, "B")
        records.append(rec)
    return union(spark, *records)


SHARDED = {
    "s1": "select entity_id, char_len, lang_guess, digit_ratio, quality from web where quality > 0.5",
    "s2": "select entity_id, batch_name, char_len, word_count, lang_guess, ngram_rep, digit_ratio, garbage_flag, quality, math_hit from web where quality > 0.5",
    "s3": EXPORT.format(""),
}


@workload
def w9_exports(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exports over two, three and four tables with views off, on and half stale."""
    engine = worlds.fresh(spark, sf_dir, "web")
    off, on, half = Recorder("w9", "mv_off"), Recorder("w9", "mv_on"), Recorder("w9", "mv_stale")
    base = {k: engine.plan(t)[0]["web"].joins for k, t in SHARDED.items()}
    for k, t in SHARDED.items():
        off.put(f"{k}_joins", base[k])
        off.put(f"{k}_s", metrics.measured_median(lambda t=t: noop(engine.sql(t, path="base", log=False))), "s")
    columns = {c for t in SHARDED.values() for c in engine.plan(t)[1]["web"].columns}
    engine.materializer.build_view("web", sorted(columns), view_id="all")
    for k, t in SHARDED.items():
        on.put(f"{k}_joins", engine.plan(t)[0]["web"].details["joins_after"])
        on.put(f"{k}_s", metrics.measured_median(lambda t=t: noop(engine.sql(t, log=False))), "s")
    on.put("storage_overhead", metrics.storage_overhead(engine.catalog.snapshot("web")))
    engine.refresh("web", [("src0", "quality"), ("src1", "quality")])
    half.put("compensated_batches", engine.plan(SHARDED["s1"])[0]["web"].details["compensated"])
    half.put("refreshed", len(engine.materializer.refresh("web", "all")))
    return union(spark, off, on, half)


@workload
def w10_export_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A log of 100 exports, 80 of them wide: what share of them a view serves before and after the governor."""
    engine = worlds.fresh(spark, sf_dir, "web")
    rnd = random.Random(9)
    wide = [n for n, _ in library.expressions("x").items()] + ["quality", "math_hit", "raw"]
    for i in range(100):
        columns = wide if i % 5 else rnd.sample(wide[:4], 2)
        engine.log_query("web", columns, shape="export", tables_joined=4 if i % 5 else 1)
    rec = Recorder("w10", "full")

    def served() -> float:
        """Share of the logged exports whose column set a view serves."""
        sets: dict[tuple, int] = {}
        for r in engine.query_log("web").collect():
            key = tuple(sorted(r.columns))
            sets[key] = sets.get(key, 0) + 1
        hits = sum(n for cs, n in sets.items() if engine.plan(f"select {', '.join(cs)} from web")[0]["web"].route == "view")
        return hits / sum(sets.values())

    rec.put("served_before", served())
    done = engine.governor.cycle("web", views=True)
    rec.put("views_built", sum(k == "build_view" for k, *_ in done))
    rec.put("served_after", served())
    return rec.frame(spark)


@workload
def w11_without_governance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ends of both sweeps with background work off, beside those with it on."""
    volume, width = w2_volume_sweep(spark, sf_dir, (1, 20), 0), w3_width_sweep(spark, sf_dir, (20, 120))
    return volume.where("measure in ('degradation', 'joins_20', 'files_20')").union(width.where("measure like 'success%'")).withColumn("workload", F.lit("w11"))


@workload
def catalog_latency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Milliseconds of metadata queries, and what the accelerators cover."""
    engine = worlds.fresh(spark, sf_dir, "web")
    rec = Recorder("catalog", "full")
    rec.put("snapshot_ms", metrics.catalog_latency_ms(engine, "web"), "ms")
    engine.index.catch_up("web")
    engine.materializer.sync("web", ["char_len", "quality"])
    for k, v in metrics.coverage(engine, "web", ["char_len", "quality"]).items():
        rec.put(f"coverage_{k}", v)
    return rec.frame(spark)


def recovered(spark: SparkSession, sf_dir: str, resume: bool, survive: int = 3) -> tuple[Engine, int, int, int]:
    """A backfill in the default configuration that dies after some units and is run again, resumed or from scratch.

    The engine, units done by the first run, units computed by the second, units in all.
    """
    engine = worlds.fresh(spark, sf_dir, "web", EngineConfig(max_retries=0, concurrency=1), features=False)
    pairs = tuple((b.name, c) for b in engine.catalog.snapshot("web").batches for c in ("char_len", "word_count"))
    ran: list[tuple] = []

    def dying(task, attempt):
        if len(ran) >= survive:
            raise RuntimeError("killed")
        ran.append((task.batches, task.columns))

    engine.executor.fail_units = dying
    engine.executor.run(BackfillRequest("web", pairs, run_id="r1"))
    before = len(ran)
    engine.executor.fail_units = lambda t, k: ran.append((t.batches, t.columns))
    if resume:
        engine.executor.run(BackfillRequest("web", pairs, run_id="r1"))
    else:
        engine.executor.run(BackfillRequest("web", (*pairs, *((b.name, "processed") for b in engine.catalog.snapshot("web").batches)), recompute=True, run_id="r2"))
    batches = len(engine.catalog.snapshot("web").batches)
    return engine, before, len(ran) - before, 2 * -(-batches // engine.config.unit_batches)


@workload
def w12_recovery(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A run that dies after some units: what is computed again with checkpoints and without."""
    records = []
    for resume in (True, False):
        rec = Recorder("w12", "resume" if resume else "restart")
        engine, done, again, total = recovered(spark, sf_dir, resume)
        rec.put("units", total)
        rec.put("units_done_before", done)
        rec.put("units_again", again)
        rec.put("complete", float(all(engine.catalog.snapshot("web").status.get((b.name, c)) == "COMPUTED" for b in engine.catalog.snapshot("web").batches for c in ("char_len", "word_count"))))
        records.append(rec)
    return union(spark, *records)


@workload
def w13_concurrent_replay(spark: SparkSession, sf_dir: str, clients: int = 20) -> DataFrame:
    """Twenty clients with a seeded mix of lookups, aggregates and exports, accelerators on and off."""
    engine = worlds.fresh(spark, sf_dir, "web")
    engine.index.catch_up("web")
    engine.materializer.sync("web", ["lang_guess", "garbage_flag", "digit_ratio", "char_len", "word_count", "quality"])
    ids, rnd = ids_for(engine, 5), random.Random(1)
    records = []
    for on in (True, False):
        rec = Recorder("w13", "on" if on else "off")
        path = None if on else "base"
        mix = []
        for _ in range(clients):
            kind = rnd.choice(["lookup", "aggregate", "export"])
            i, t, e = rnd.choice(ids), rnd.choice(list(AGGREGATES.values())), rnd.choice(list(SHARDED.values()))
            mix.append({"lookup": lambda i=i: engine.lookup("web", i, ["char_len"], use_index=on).collect(), "aggregate": lambda t=t: engine.sql(t, path=path, log=False).collect(), "export": lambda e=e: noop(engine.sql(e, path=path, log=False))}[kind])
        times, failed = metrics.replay(mix, clients)
        rec.put("p50", metrics.percentile(times, 0.5), "s")
        rec.put("p95", metrics.percentile(times, 0.95), "s")
        rec.put("failed", failed)
        records.append(rec)
    return union(spark, *records)


@workload
def w14_combined(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fusion, record guard and tuning, each on and off, over the instruction features."""
    records = []
    for fuse in ("physical", "off"):
        for mode in ("record", "task"):
            for tune in ("adaptive", "default"):
                rec = Recorder("w14", f"fuse={fuse},guard={mode},tuning={tune}")
                engine = worlds.fresh(spark, sf_dir, "sft", EngineConfig(fuse=fuse, guard=mode, tuning=tune))
                with rec.stage("backfill"):
                    report = engine.backfill("sft", columns=[o for f in worlds.sft_features() for o in f.output_names])
                rec.put("tasks", len(report.tasks))
                rec.put("cpu_hours", metrics.cpu_hours(report.cpu_s), "h")
                records.append(rec)
    return union(spark, *records)


@workload
def w15_complementary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Look one up, see the distribution, export: the routes that three steps take."""
    engine = worlds.fresh(spark, sf_dir, "web")
    engine.index.catch_up("web")
    engine.materializer.sync("web", ["lang_guess", "quality"])
    engine.materializer.build_view("web", ["char_len", "lang_guess", "digit_ratio", "quality"])
    rec = Recorder("w15", "all_on")
    steps = {"lookup": f"select * from web where entity_id = '{ids_for(engine, 1)[0]}'", "distribution": "select lang_guess, avg(quality) as q from web group by 1", "export": SHARDED["s1"]}
    for k, t in steps.items():
        with rec.stage(k):
            noop(engine.sql(t))
        rec.put(f"{k}_accelerated", float(engine.plan(t)[0]["web"].route in ("index", "replica", "view")))
    return rec.frame(spark)


def appended(spark: SparkSession, sf_dir: str, appends: int) -> tuple[Engine, int, int]:
    """Events in many small appends, then a governance cycle: the engine, files before and files after."""
    engine = Engine(spark, policy=Policy(min_batch_files=2, target_mb=64))
    path = worlds.path_of(sf_dir, "events")
    mapping = {c.name: c.name for c in worlds.SIGNAL_COLUMNS if c.name != "k"} | {"source_key": "event_id"}
    for i in range(appends):
        source = SourceSpec("parquet", path, transform=lambda d, i=i: d.where(F.col("event_id") % appends == i).repartition(4))
        engine.ingest(source, "signal", f"m{i:03d}", mapping, create=worlds.SIGNAL_COLUMNS, id_strategy=("key", ["event_id"]), mode="append", dedup=False)
    files = [storage_report(engine, "signal").agg(F.sum("files").alias("f")).first().f]
    engine.governor.cycle("signal")
    files.append(storage_report(engine, "signal").agg(F.sum("files").alias("f")).first().f)
    return engine, *files


@workload
def w16_small_files(spark: SparkSession, sf_dir: str, appends: int = 50) -> DataFrame:
    """Continuous small appends, what a governance cycle makes of them, and its share of the executors' time."""
    rec = Recorder("w16", "full")
    began = time.time()
    engine, before, after = appended(spark, sf_dir, appends)
    rec.put("run_s", time.time() - began, "s")
    rec.put("governance_s", engine.governor.seconds, "s")
    rec.put("governance_share", metrics.governance_share(spark))
    rec.put("files_before", before)
    rec.put("files_after", after)
    rec.put("rows_changed", abs(engine.table("signal").count() - spark.read.parquet(worlds.path_of(sf_dir, "events")).count()))
    return rec.frame(spark)


def routed_library() -> list:
    """All features that the library offers."""
    return [*library.web_features(), library.template("ppl"), library.template("safety"), *library.conversation_features(), *library.token_features()]


def routed_lanes() -> list[str]:
    """The lane of each under an idle cluster."""
    from .plans.routing import ClusterLoad, OperatorProfile, choose_lane

    return [choose_lane(f.mode, OperatorProfile.of(f), ClusterLoad()) for f in routed_library()]


@workload
def w17_routing_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lanes of the whole library under an idle cluster."""
    rec, lanes = Recorder("w17", "full"), routed_lanes()
    for lane in ("sql", "arrow", "gpu"):
        rec.put(f"share_{lane}", lanes.count(lane) / len(lanes))
    return rec.frame(spark)


def with_pages(spark: SparkSession, sf_dir: str, strategy: str) -> Engine:
    """Documents by source and pages by the end of their host, in one table."""
    engine = Engine(spark)
    engine.ingest(worlds.documents(sf_dir), "web", "source", worlds.WEB_MAPPING, create=worlds.WEB_COLUMNS, many=True, id_strategy=strategy)
    mapping = {"raw": "named_struct('body', html, 'url', url, 'source_key', page_id, 'declared_lang', cast(null as string))", "payload": "html", "source_key": "page_id"}
    engine.ingest(SourceSpec("parquet", worlds.path_of(sf_dir, "pages")), "web", "concat('pages-', regexp_extract(url, '[.]([a-z]+)(/|$|[?#:])', 1))", mapping, many=True, id_strategy=strategy)
    return engine


@workload
def w18_ingestion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ingesting all sources and pages with content and with random ids."""
    records = []
    given = sum(spark.read.parquet(worlds.path_of(sf_dir, n)).count() for n in ("documents", "pages"))
    for strategy in ("content", "uuid"):
        rec = Recorder("w18", strategy)
        with rec.stage("ingest"):
            engine = with_pages(spark, sf_dir, strategy)
        rows = sum(b.rows for b in engine.catalog.snapshot("web").batches)
        rec.put("rows", rows)
        rec.put("kept_share", rows / given)
        records.append(rec)
    return union(spark, *records)


def register() -> None:
    from .registry import QUERIES

    QUERIES.update(WORKLOADS)


register()
