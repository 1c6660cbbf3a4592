"""Answers of the experiments W1 to W18: what each workload's queries return in its configurations, with flat-SQL twins.

Times and counts of work are in `workloads`; here only results are looked at, in whatever layout, path or recovery a
workload leads to, so that each can be compared row by row with another engine.
"""

from __future__ import annotations

import json
import random
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import workloads, worlds
from .functions import library
from .model import EngineConfig
from .registry import LIMIT, S1, S2, S3, WIDE, broken, copied, curated, query, ungoverned


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def collected(spark, frames: list[tuple[str, DataFrame]]) -> DataFrame:
    """(config, columns) of aggregates of one row each, by a job of its own each."""
    rows = [(name, *frame.first()) for name, frame in frames]
    return spark.createDataFrame(rows, ", ".join(["config string", *(f"{f.name} {f.dataType.simpleString()}" for f in frames[0][1].schema)]))


WHERE = "char_len between 100 and 100000 and word_count > 20 and lang_guess in ('en', 'de', 'fr') and ngram_rep < 0.9 and digit_ratio < 0.2 and garbage_flag = false and line_rep < 0.5 and quality > 0.3"
SUMMED = "count(*) as n, cast(coalesce(sum(char_len), 0) as bigint) as chars, round(coalesce(sum(quality), 0), 4) as q"
VOLUME = f"select {SUMMED} from web where {WHERE} and batch_name in ({{}})"
SOURCES = {k: ", ".join(f"'src{i}'" for i in range(k)) for k in (1, 5, 10, 20)}
YEARS = {k: ", ".join(f"'y{1995 + i}'" for i in range(k)) for k in range(1, 8)}
TRADE_VOLUME = "select count(*) as n, cast(sum(cast(quantity as decimal(18,2))) as double) as quantity from trade where quantity > 5 and discount <= 0.08 and batch_name in ({})"


@query("w1_answer", "select entity_id, cast(n_turns as bigint) as n_turns, char_len from sft where n_turns >= 2 and alternates and 1 / (1 + exp(-(-1.0 + 0.002 * least(n_turns, 1000) + 2.0 * 1.5 * (case when char_len > 300 then 1 else 0 end) - 8.0 * digit_ratio))) >= 0.5")
def _(spark, sf_dir):
    return curated(spark, sf_dir).sql("select entity_id, cast(n_turns as bigint) as n_turns, char_len from sft where n_turns >= 2 and alternates and quality >= 0.5")


@query("w2_answer", " union all ".join(f"select '{c}-{k}' as config, * from ({VOLUME.format(names)})" for c in ("full", "nogov") for k, names in SOURCES.items()))
def _(spark, sf_dir):
    engines = {"full": worlds.world(spark, sf_dir, "web"), "nogov": ungoverned(spark, sf_dir)}
    return collected(spark, [(f"{c}-{k}", e.sql(VOLUME.format(names), log=False)) for c, e in engines.items() for k, names in SOURCES.items()])


@query("w2_trade_answer", " union all ".join(f"select '{k}' as config, * from ({TRADE_VOLUME.format(names)})" for k, names in YEARS.items()))
def _(spark, sf_dir):
    engine = worlds.world(spark, sf_dir, "trade")
    return collected(spark, [(str(k), engine.sql(TRADE_VOLUME.format(names), log=False)) for k, names in YEARS.items()])


@query("w3_answer", WIDE.replace(", round(quality, 6) as quality", ""))
def _(spark, sf_dir):
    """The fixed query after the table has grown past the limit of columns and the governor has split it by use."""
    engine, text = workloads.widened(spark, sf_dir, 120, 60, True)
    if max(len(p.columns) for p in engine.catalog.snapshot("web").physical) + 2 > 60 or engine.plan(text)[0]["web"].joins > 1:
        raise AssertionError("the layout isn't what the governor promises")
    return engine.sql(text, log=False)


EIGHT = "count(*) as n, cast(sum(char_len) as bigint) as chars, cast(sum(word_count) as bigint) as words, count(distinct content_md5) as texts, round(sum(ngram_rep), 4) as rep, round(sum(digit_ratio), 4) as digits, round(sum(url_ratio), 4) as urls, count(case when garbage_flag then 1 end) as garbage, count(distinct lang_guess) as langs"


@query("w4_answer", f"select m as config, t.* from (select {EIGHT} from web) t cross join (values ('physical'), ('off')) c(m)")
def _(spark, sf_dir):
    out = []
    for mode in ("physical", "off"):
        engine = worlds.fresh(spark, sf_dir, "web", EngineConfig(fuse=mode, unit_batches=1000), features=False)
        engine.backfill("web", columns=library.FUSED_EIGHT)
        out.append((mode, engine.sql(f"select {EIGHT} from web", log=False)))
    return collected(spark, out)


@query("w5_answer", f"select batch_name, count(*) as n, count(case when char_len <= {LIMIT} and math_hit is not null then 1 end) as computed from web group by batch_name")
def _(spark, sf_dir):
    return broken(spark, sf_dir).sql("select batch_name, count(*) as n, count(math_hit) as computed from web group by batch_name", log=False)


@query("w6_answer", "select k::bigint as scale, count(*) as n, round(sum(quality), 3) as q from web cross join (values (1), (2), (4)) t(k), range(0, 4) r(i) where i < k group by k")
def _(spark, sf_dir):
    """A model feature over the documents one, two and four times, its splits and batches set by rules, then history."""
    out, history = [], None
    for k in (1, 2, 4):
        engine = workloads.repeated(spark, sf_dir, k, EngineConfig(tuning="adaptive"))
        engine.history = history or engine.history
        history = engine.history
        engine.backfill("web", columns=["quality"])
        out.append(engine.sql(f"select cast({k} as bigint) as scale, count(*) as n, round(sum(quality), 3) as q from web", log=False))
    return union([spark.createDataFrame(o.collect(), o.schema) for o in out])


FEW = "select entity_id, batch_name, char_len, lang_guess, raw.source_key as source_key from web"


@query("w7_answer", f"{FEW} where entity_id in (select entity_id from (select distinct md5(text) as entity_id from documents) d order by md5(entity_id) limit 200)")
def _(spark, sf_dir):
    """Two hundred ids and ten that are absent, each looked up by itself through the index by twenty clients."""
    engine = worlds.world(spark, sf_dir, "web")
    engine.index.catch_up("web")
    ids = [*workloads.ids_for(engine, 200), *(f"absent-{i}" for i in range(10))]
    columns = ["char_len", "lang_guess", "raw"]
    with ThreadPoolExecutor(20) as pool:
        found = [r for rows in pool.map(lambda i: engine.lookup("web", i, columns).select("entity_id", "batch_name", "char_len", "lang_guess", F.col("raw.source_key").alias("source_key")).collect(), ids) for r in rows]
    return spark.createDataFrame(found, "entity_id string, batch_name string, char_len bigint, lang_guess string, source_key bigint")


A_WEB = {
    "a1": "select 'a1' as q, 'all' as k, count(lang_guess) as n, cast(0 as double) as x from web", "a2": "select 'a2' as q, concat(lang_guess, '-', cast(garbage_flag as varchar(5))) as k, count(*) as n, cast(0 as double) as x from web group by 2",
    "a3": "select 'a3' as q, 'all' as k, count(*) as n, cast(0 as double) as x from web where digit_ratio > 0.001 and lang_guess = 'en'", "a4": "select 'a4' as q, batch_name as k, max(word_count) as n, round(avg(quality), 6) as x from web group by batch_name",
}
A_TRADE = {
    "t1": "select 't1' as q, 'all' as k, count(discount) as n, cast(0 as double) as x from trade", "t2": "select 't2' as q, concat(returnflag, linestatus) as k, count(*) as n, cast(0 as double) as x from trade group by 2",
    "t3": "select 't3' as q, 'all' as k, count(*) as n, cast(0 as double) as x from trade where shipdate >= timestamp '1996-01-01 00:00:00' and shipdate < timestamp '1997-01-01 00:00:00'", "t4": "select 't4' as q, returnflag as k, count(*) as n, round(avg(discount), 6) as x from trade group by returnflag",
}


@query("w8_answer", " union all ".join(f"({t})" for t in A_WEB.values()))
def _(spark, sf_dir):
    engine = copied(spark, sf_dir)
    for t in A_WEB.values():
        if engine.plan(t)[0]["web"].route != "replica":
            raise AssertionError(t)
    return union([spark.createDataFrame(engine.sql(t, log=False).collect(), "q string, k string, n bigint, x double") for t in A_WEB.values()])


@query("w8_trade_answer", " union all ".join(f"({t})" for t in A_TRADE.values()))
def _(spark, sf_dir):
    engine = worlds.fresh(spark, sf_dir, "trade")
    engine.materializer.sync("trade", ["returnflag", "linestatus", "shipdate", "discount"])
    for t in A_TRADE.values():
        if engine.plan(t)[0]["trade"].route != "replica":
            raise AssertionError(t)
    return union([spark.createDataFrame(engine.sql(t, log=False).collect(), "q string, k string, n bigint, x double") for t in A_TRADE.values()])


COUNTED = "select count(*) as n, count(distinct entity_id) as ids, round(sum(quality), 4) as q from ({})"


@query("w9_answer", " union all ".join(f"select '{k}' as config, * from ({COUNTED.format(t)})" for k, t in (("s1", S1), ("s2", S2), ("s3", S3))))
def _(spark, sf_dir):
    engine = copied(spark, sf_dir)
    for t in (S1, S2, S3):
        if engine.plan(t, path="view")[0]["web"].route != "view":
            raise AssertionError(t)
    sums = (F.count("*").alias("n"), F.countDistinct("entity_id").alias("ids"), F.round(F.sum("quality"), 4).alias("q"))
    return collected(spark, [(k, engine.sql(t, path="view", log=False).agg(*sums)) for k, t in (("s1", S1), ("s2", S2), ("s3", S3))])


MIX = "select entity_id, char_len, round(quality, 6) as quality, math_hit, garbage_flag, raw.source_key as source_key from web"


@query("w10_answer", MIX)
def _(spark, sf_dir):
    """A wide export of the logged mix, served by the view that the governor made of the log."""
    engine = worlds.fresh(spark, sf_dir, "web")
    for i in range(100):
        engine.log_query("web", ["char_len", "quality", "math_hit", "garbage_flag", "raw"] if i % 5 else ["char_len"], tables_joined=4 if i % 5 else 1)
    engine.governor.cycle("web", views=True)
    if engine.plan(MIX)[0]["web"].route != "view":
        raise AssertionError("no view was made")
    return engine.sql(MIX, log=False)


@query("w11_answer", S2)
def _(spark, sf_dir):
    return ungoverned(spark, sf_dir).sql(S2, log=False)


@query("w12_answer", "select batch_name, count(*) as n, cast(sum(char_len) as bigint) as chars, cast(sum(word_count) as bigint) as words from web group by batch_name")
def _(spark, sf_dir):
    """Values after a run that died and was resumed, in the default configuration."""
    engine, _, again, total = workloads.recovered(spark, sf_dir, True)
    if again >= total:
        raise AssertionError("everything was computed again")
    return engine.sql("select batch_name, count(*) as n, sum(char_len) as chars, sum(word_count) as words from web group by batch_name", log=False)


def seeded_mix(clients: int = 20) -> list[tuple[str, str]]:
    rnd = random.Random(1)
    kinds = {"aggregate": list(A_WEB.values()), "export": [COUNTED.format(t) for t in (S1, S2, S3)]}
    return [(f"{i:02d}", json.dumps([kind, n])) for i in range(clients) for kind in [rnd.choice(sorted(kinds))] for n in [rnd.randrange(len(kinds[kind]))]]


def mix_text(key: str) -> str:
    kind, n = json.loads(key)
    if kind == "export":
        return f"select n, q as x from ({COUNTED.format((S1, S2, S3)[n])})"
    return f"select cast(sum(n) as bigint) as n, round(sum(x), 4) as x from ({list(A_WEB.values())[n]})"


@query("w13_answer", " union all ".join(f"select '{i}' as config, * from ({mix_text(k)})" for i, k in seeded_mix()))
def _(spark, sf_dir):
    engine = copied(spark, sf_dir)
    with ThreadPoolExecutor(20) as pool:
        found = list(pool.map(lambda ik: (ik[0], *engine.sql(mix_text(ik[1]), log=False).first()), seeded_mix()))
    return spark.createDataFrame(found, "config string, n bigint, x double")


SFT_SUMS = "select count(*) as n, cast(sum(char_len) as bigint) as chars, round(sum(digit_ratio), 5) as digits, count(case when pii_flag then 1 end) as pii, count(case when alternates then 1 end) as alternating from sft"


@query("w14_answer", f"select concat(f, '-', g, '-', t) as config, s.* from ({SFT_SUMS}) s cross join (values ('physical'), ('off')) a(f) cross join (values ('record'), ('task')) b(g) cross join (values ('adaptive'), ('default')) c(t)")
def _(spark, sf_dir):
    out = []
    for fuse in ("physical", "off"):
        for guard in ("record", "task"):
            for tuning in ("adaptive", "default"):
                engine = worlds.fresh(spark, sf_dir, "sft", EngineConfig(fuse=fuse, guard=guard, tuning=tuning, unit_batches=1000))
                if not engine.backfill("sft", columns=["char_len", "digit_ratio", "pii_flag", "alternates"]).ok:
                    raise AssertionError((fuse, guard, tuning))
                out.append((f"{fuse}-{guard}-{tuning}", engine.sql(SFT_SUMS, log=False)))
    return collected(spark, out)


STEPS = {"distribution": "select count(*) as n, round(sum(quality), 4) as q from web where lang_guess = 'en'"}


@query("w15_answer", " union all ".join(f"select '{k}' as config, * from ({t})" for k, t in STEPS.items()) + f" union all select 'export', n, q from ({COUNTED.format(S2)}) union all select 'lookup', count(*), round(sum(quality), 4) from web where entity_id = (select min(md5(text)) from documents)")
def _(spark, sf_dir):
    engine = copied(spark, sf_dir)
    engine.index.catch_up("web")
    one = engine.table("web", []).agg(F.min("entity_id")).first()[0]
    steps = STEPS | {"lookup": f"select count(*) as n, round(sum(quality), 4) as q from web where entity_id = '{one}'"}
    routes = {k: engine.plan(t)[0]["web"].route for k, t in (steps | {"export": S2}).items()}
    if routes != {"distribution": "replica", "export": "view", "lookup": "index"}:
        raise AssertionError(routes)
    export = engine.sql(S2, log=False).agg(F.count("*").alias("n"), F.round(F.sum("quality"), 4).alias("q"))
    return collected(spark, [("export", export), *((k, engine.sql(t, log=False)) for k, t in steps.items())])


@query("w16_answer", "select event_type, count(*) as n, cast(sum(event_id) as bigint) as ids from events group by event_type")
def _(spark, sf_dir):
    """Rows after many micro-appends and the governor's cycle."""
    engine, before, after = workloads.appended(spark, sf_dir, 20)
    if after >= before:
        raise AssertionError((before, after))
    return engine.sql("select event_type, count(*) as n, sum(event_id) as ids from signal group by event_type", log=False)


@query("w17_answer", "select lane, count(*) as features from (values " + ", ".join(f"('{'sql' if f.fn is None else 'gpu' if f.mode == 'gpu_only' else 'arrow'}')" for f in workloads.routed_library()) + ") t(lane) group by lane")
def _(spark, sf_dir):
    """Lanes of the whole library under an idle cluster: models of 'all' stay on CPU while they fit there."""
    return spark.createDataFrame([(x,) for x in workloads.routed_lanes()], "lane string").groupBy("lane").agg(F.count("*").alias("features"))


@query("w18_answer", "select batch_name, count(*) as n from web group by 1 union all select 'pages-' || regexp_extract(url, '[.]([a-z]+)(/|$|[?#:])', 1), count(distinct html) from pages group by 1")
def _(spark, sf_dir):
    return workloads.with_pages(spark, sf_dir, "content").sql("select batch_name, count(*) as n from web group by batch_name", log=False)

