"""Headline timings: prints one JSON line. BENCH_SF_DIR, BENCH_CPUS and BENCH_TIMES choose input, cores and row multiplication."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).resolve().parent))

from widefeat import metrics, workloads, worlds  # noqa: E402
from widefeat.engine import Engine  # noqa: E402
from widefeat.functions import library  # noqa: E402
from widefeat.model import EngineConfig  # noqa: E402
from widefeat.sources.adapters import SourceSpec  # noqa: E402

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: At the given size fixed costs rule; ratios are taken on this many copies of the documents, each text made different.
TIMES = int(os.environ.get("BENCH_TIMES", "12"))
HOT = ["lang_guess", "garbage_flag", "digit_ratio", "char_len", "word_count", "quality"]


def multiplied(spark: SparkSession, times: int, config: EngineConfig | None = None) -> Engine:
    """The web table over `times` copies of the documents, a word put before each copy's text."""
    engine = Engine(spark, config)

    def copies(d):
        many = d.repartition(4 * spark.sparkContext.defaultParallelism).withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
        return many.withColumn("text", F.concat(F.col("copy").cast("string"), F.lit(" "), F.col("text"))).withColumn("doc_id", F.col("doc_id") * times + F.col("copy"))

    engine.ingest(SourceSpec("parquet", worlds.path_of(SF, "documents"), transform=copies), "web", "source", worlds.WEB_MAPPING, create=worlds.WEB_COLUMNS, many=True)
    for f in library.web_features():
        engine.add_feature("web", f)
    return engine


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("widefeat-bench").config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.scheduler.mode", "FAIR").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}
    ratios: dict[str, float] = {}

    def timed(name: str, fn, runs: int = 1):
        began = time.perf_counter()
        out = fn()
        spent = [time.perf_counter() - began]
        for _ in range(runs - 1):
            began = time.perf_counter()
            fn()
            spent.append(time.perf_counter() - began)
        times[name] = round(sorted(spent)[len(spent) // 2], 3)
        return out

    def ratio(name: str, slow: str, fast: str) -> None:
        ratios[name] = round(times[slow] / times[fast], 2)

    spark.range(1000).selectExpr("sum(id)").collect()
    web = timed("ingest_web", lambda: worlds.fresh(spark, SF, "web", features=False))
    report = timed("backfill_web_15_features", lambda: web.backfill("web", columns=[o for f in library.web_features() for o in f.output_names]))
    ratios["backfill_cpu_hours"] = round(metrics.cpu_hours(report.cpu_s), 5)
    timed("sft_end_to_end", lambda: worlds.fresh(spark, SF, "sft").backfill("sft", columns=[o for f in worlds.sft_features() for o in f.output_names]))
    trade = timed("ingest_trade", lambda: worlds.fresh(spark, SF, "trade"))
    timed("trade_pricing_summary", lambda: trade.sql("select returnflag, linestatus, count(*), sum(quantity), avg(discount) from trade group by 1, 2", log=False).collect(), 3)
    timed("trade_year_filter", lambda: workloads.noop(trade.sql("select * from trade where batch_name = 'y1996' and quantity > 30", log=False)), 3)

    # ratios, on more rows
    cpu = {}
    for fuse in ("off", "physical"):
        engine = multiplied(spark, TIMES, EngineConfig(fuse=fuse, concurrency=1, unit_batches=1000))
        engine.backfill("web", columns=["processed"])
        report = timed(f"fusion_eight_{'on' if fuse != 'off' else 'off'}", lambda e=engine: e.backfill("web", columns=library.FUSED_EIGHT))
        ratios[f"scans_{fuse}"], cpu[fuse] = report.scans, report.cpu_s
        ratios[f"cpu_hours_{fuse}"] = round(metrics.cpu_hours(report.cpu_s), 5)
    ratio("fusion_speedup", "fusion_eight_off", "fusion_eight_on")
    ratios["fusion_cpu_saved"] = round(1 - cpu["physical"] / cpu["off"], 3)
    wide = engine
    wide.backfill("web", columns=[o for f in library.web_features() for o in f.output_names])
    text = workloads.EXPORT.format("")
    timed("export_s3_views_off", lambda: workloads.noop(wide.sql(text, path="base", log=False)), 3)
    ratios["joins_views_off"] = wide.plan(text, path="base")[0]["web"].joins
    timed("view_build", lambda: wide.materializer.build_view("web", wide.plan(text, path="base")[1]["web"].columns))
    timed("export_s3_views_on", lambda: workloads.noop(wide.sql(text, log=False)), 3)
    ratios["joins_views_on"] = wide.plan(text)[0]["web"].details["joins_after"]
    ratio("export_speedup", "export_s3_views_off", "export_s3_views_on")
    timed("index_build", lambda: wide.index.catch_up("web"))
    one = workloads.ids_for(wide, 1)[0]
    timed("lookup_index", lambda: wide.lookup("web", one).collect(), 5)
    timed("lookup_scan", lambda: wide.lookup("web", one, use_index=False).collect(), 5)
    ratio("lookup_speedup", "lookup_scan", "lookup_index")
    wide.materializer.sync("web", HOT)
    for name, q in workloads.AGGREGATES.items():
        timed(f"aggregate_{name}_base", lambda q=q: wide.sql(q, path="base", log=False).collect(), 3)
        timed(f"aggregate_{name}_replica", lambda q=q: wide.sql(q, path="replica", log=False).collect(), 3)
        ratio(f"aggregate_{name}_speedup", f"aggregate_{name}_base", f"aggregate_{name}_replica")
    snap = wide.catalog.snapshot("web")
    size = sum(p.bytes for p in snap.physical if p.purpose in ("core", "features"))
    ratios["export_tb_h"] = round(metrics.throughput_tb_h(size, times["export_s3_views_on"]), 6)
    ratios["rows"] = sum(b.rows for b in snap.batches)
    print(json.dumps({"metric": "total_headline_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "ratios": ratios, "sf": SF.rstrip("/").rpartition("sf")[2]}))
    spark.stop()


if __name__ == "__main__":
    main()
