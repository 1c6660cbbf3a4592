"""The logical tables of the experiments, built once per application and input folder.

Each has a twin in flat SQL over the raw tables, for checks by another engine.
"""

from __future__ import annotations

import threading

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .engine import Engine
from .functions import library
from .model import Column, EngineConfig
from .sources.adapters import SourceSpec

_built: dict[tuple[str, str, str], Engine | str] = {}
_lock = threading.RLock()

WEB_COLUMNS = [Column("raw", "struct<body:string,url:string,source_key:bigint,declared_lang:string>")]
WEB_MAPPING = {"raw": "named_struct('body', text, 'url', cast(null as string), 'source_key', doc_id, 'declared_lang', lang)", "payload": "text", "source_key": "doc_id"}
TRADE_COLUMNS = [Column(n, t) for n, t in (("orderkey", "bigint"), ("partkey", "bigint"), ("suppkey", "bigint"), ("linenumber", "int"), ("quantity", "double"), ("price", "double"), ("discount", "double"), ("tax", "double"), ("returnflag", "string"), ("linestatus", "string"), ("shipdate", "timestamp_ntz"), ("custkey", "bigint"), ("orderpriority", "string"), ("orderdate", "timestamp_ntz"))]
SIGNAL_COLUMNS = [Column(n, t) for n, t in (("event_id", "bigint"), ("ts", "timestamp_ntz"), ("user_id", "bigint"), ("event_type", "string"), ("value", "double"), ("k", "int"))]
SFT_COLUMNS = [Column("raw", "struct<conv_id:bigint,turns:array<struct<turn:bigint,role:string,text:string>>>")]
VEC_COLUMNS = [Column("raw", "struct<vec_id:bigint,label:int,embedding:array<float>>")]


def path_of(sf_dir: str, name: str) -> str:
    return f"{sf_dir.rstrip('/')}/{name}.parquet"


def documents(sf_dir: str) -> SourceSpec:
    return SourceSpec("parquet", path_of(sf_dir, "documents"))


def build_web(engine: Engine, sf_dir: str, features: bool = True) -> None:
    engine.ingest(documents(sf_dir), "web", "source", WEB_MAPPING, create=WEB_COLUMNS, many=True)
    for f in library.web_features():
        engine.add_feature("web", f)
    if features:
        engine.backfill("web", columns=[o for f in library.web_features() for o in f.output_names])


def build_trade(engine: Engine, sf_dir: str) -> None:
    spark = engine.spark
    lines, orders = (spark.read.parquet(path_of(sf_dir, n)) for n in ("lineitem", "orders"))
    source = SourceSpec("memory", frame=lines.join(orders, lines.l_orderkey == orders.o_orderkey, "left"))
    names = {"custkey": "o_custkey", "orderpriority": "o_orderpriority", "orderdate": "o_orderdate", "price": "l_extendedprice"}
    mapping = {c.name: names.get(c.name, f"l_{c.name}") for c in TRADE_COLUMNS} | {"source_key": "l_orderkey"}
    engine.ingest(source, "trade", "concat('y', year(l_shipdate))", mapping, create=TRADE_COLUMNS, many=True, id_strategy=("key", lines.columns), dedup=False)


def build_signal(engine: Engine, sf_dir: str) -> None:
    mapping = {c.name: c.name for c in SIGNAL_COLUMNS} | {"k": "cast(get_json_object(props, '$.k') as int)", "source_key": "event_id"}
    engine.ingest(SourceSpec("parquet", path_of(sf_dir, "events")), "signal", "concat('d', date_format(ts, 'yyyy-MM-dd'))", mapping, create=SIGNAL_COLUMNS, many=True, id_strategy=("key", ["event_id"]))


def fold(rows: DataFrame) -> DataFrame:
    """One row a conversation, turns in order."""
    turns = F.array_sort(F.collect_list(F.struct("turn", "role", "text")))
    return rows.groupBy("conv_id").agg(turns.alias("turns"))


def build_sft(engine: Engine, sf_dir: str) -> None:
    mapping = {"raw": "named_struct('conv_id', conv_id, 'turns', turns)", "source_key": "conv_id"}
    source = SourceSpec("parquet", path_of(sf_dir, "conversations"), transform=fold)
    engine.ingest(source, "sft", "concat('sft-', conv_id % 8)", mapping, create=SFT_COLUMNS, many=True, id_strategy=("key", ["conv_id"]))
    for f in sft_features(safety_model(engine.spark, sf_dir)):
        engine.add_feature("sft", f)


def safety_model(spark: SparkSession, sf_dir: str) -> str:
    """Weights of the safety score, learned from labelled documents (doc_id not divisible by 5, at most SAFETY_ROWS of them)."""
    from .functions.models import SAFETY_ROWS, train_safety

    key = (spark.sparkContext.applicationId, sf_dir, "safety")
    with _lock:
        if key not in _built:
            labels = spark.read.parquet(path_of(sf_dir, "labels")).where("toxic is not null and doc_id % 5 <> 0").orderBy(F.xxhash64("doc_id"), "doc_id").limit(SAFETY_ROWS)
            rows = spark.read.parquet(path_of(sf_dir, "documents")).select("doc_id", "text").join(F.broadcast(labels), "doc_id").orderBy("doc_id").collect()
            _built[key] = train_safety([r.text for r in rows], [r.toxic for r in rows])
        return _built[key]


def sft_features(weights: str = "") -> list:
    """Twelve features of conversations; weights are those of the safety score."""
    joined = "array_join(transform(raw.turns, t -> coalesce(t.text, '')), '\\n')"
    gpu = [
        library.safety_feature(weights, ("raw",), (joined,)), library.model_feature("domain_model", "string", ("raw",), "gpu_only", 7000.0, (joined,)),
        library.model_feature("quality", "double", ("raw", "char_len", "digit_ratio"), "gpu_only", 350.0, ("char_len", "cast(size(raw.turns) as bigint)", "0D", "digit_ratio")),
    ]
    return library.conversation_features() + gpu


def build_vec(engine: Engine, sf_dir: str) -> None:
    mapping = {"raw": "named_struct('vec_id', vec_id, 'label', label, 'embedding', embedding)", "source_key": "vec_id"}
    engine.ingest(SourceSpec("parquet", path_of(sf_dir, "embeddings")), "vec", "concat('label-', label)", mapping, create=VEC_COLUMNS, many=True, id_strategy=("key", ["vec_id"]))


BUILDERS = {"web": build_web, "trade": build_trade, "signal": build_signal, "sft": build_sft, "vec": build_vec}


def fresh(spark: SparkSession, sf_dir: str, table: str, config: EngineConfig | None = None, **options) -> Engine:
    """An engine of its own with one logical table."""
    engine = Engine(spark, config)
    BUILDERS[table](engine, sf_dir, **options)
    return engine


def world(spark: SparkSession, sf_dir: str, table: str) -> Engine:
    """The shared engine of a logical table; queries on it don't change its layout."""
    key = (spark.sparkContext.applicationId, sf_dir, table)
    with _lock:
        if key not in _built:
            _built[key] = fresh(spark, sf_dir, table)
        return _built[key]


# ---- the same tables in flat SQL


def web_sql(text: str) -> str:
    """Only the features that the query names are computed."""
    import re

    from .functions.models import MATH, MATH_SIGNS, QUALITY

    named = set(re.findall(r"\w+", text))
    if "math_hit" in named:
        named.add("quality")
    if "quality" in named:
        named |= {"char_len", "word_count", "ngram_rep", "digit_ratio"}
    f = {n: x for n, x in library.expressions("plain", spark=False, words="_w").items() if n in named}
    plain = f"case when text like '<%' then {library._plain_html('text', False)} else text end"
    b, w1, w2, w3, w4 = map(repr, QUALITY)
    cast = {"bigint": "bigint", "double": "double", "string": "varchar", "boolean": "boolean"}
    cols = "".join(f", cast({e} as {cast[t]}) as {n}" for n, (t, e) in f.items())
    q = f", 1 / (1 + exp(-({b} + {w1} * least(word_count, 1000) + {w2} * (case when char_len > 300 then 1 else 0 end) + {w3} * ngram_rep + {w4} * digit_ratio))) as quality" if "quality" in named else ""
    noise, bonus, scale, bias = map(repr, MATH)
    grams = "list_concat(_m, list_transform(range(1, len(_m)), lambda i: _m[i] || ' ' || _m[i + 1]))"
    weight = f"((('0x' || substr(md5(g), 1, 4))::int) / 65536.0::double - 0.5) * {noise} + (case when regexp_matches(g, '{MATH_SIGNS.pattern}') then {bonus} else 0 end)"
    words = r"list_filter(regexp_split_to_array(lower(plain), '[ \t\n\r\f]+'), lambda w: w <> '')"
    math = f", (1 / (1 + exp(-({scale} * coalesce(list_avg(list_transform({grams}, lambda g: {weight})), 0) + ({bias}))))) * quality > 0.3 as math_hit" if "math_hit" in named else ""
    cols += f", {words} as _m" if math else ""
    return (
        "web as (with a as materialized (select md5(text) as entity_id, source as batch_name, {'body': text, 'source_key': doc_id, 'declared_lang': lang} as raw, "
        f"{plain} as plain, {library._duck_words(plain)} as _w, row_number() over (partition by md5(text) order by doc_id, source) as n from documents), "
        f"b as materialized (select *{cols} from a where n = 1), c as materialized (select *{q} from b) select *{math} from c)"
    )


def trade_sql() -> str:
    return (
        "trade as (select concat('y', year(l_shipdate)) as batch_name, l_orderkey as orderkey, l_partkey as partkey, l_suppkey as suppkey, l_linenumber as linenumber, l_quantity as quantity, "
        "l_extendedprice as price, l_discount as discount, l_tax as tax, l_returnflag as returnflag, l_linestatus as linestatus, l_shipdate as shipdate, o_custkey as custkey, o_orderpriority as orderpriority, "
        "o_orderdate as orderdate from lineitem left join orders on l_orderkey = o_orderkey)"
    )


def signal_sql() -> str:
    return "signal as (select md5(cast(event_id as varchar)) as entity_id, concat('d', strftime(ts, '%Y-%m-%d')) as batch_name, event_id, ts, user_id, event_type, value, cast(json_extract(props, '$.k') as integer) as k from events)"


def sft_sql() -> str:
    f = library.expressions("joined", spark=False)
    return (
        "sft as (with a as (select conv_id, concat('sft-', conv_id % 8) as batch_name, md5(cast(conv_id as varchar)) as entity_id, count(*) as n_turns, avg(case when role = 'user' then 1.0 else 0.0 end) as user_share, "
        "bool_or(role = 'system') as has_system, avg(case when role = 'assistant' then length(text) end) as avg_reply_len, string_agg(coalesce(text, ''), chr(10) order by turn) as joined, list(role order by turn) as roles from conversations group by conv_id), "
        f"b as (select *, {f['char_len'][1]} as char_len, {f['lang_guess'][1]} as lang_guess, cast({f['digit_ratio'][1]} as double) as digit_ratio, {f['pii_flag'][1]} as pii_flag, "
        "len(list_filter(range(2, len(roles) + 1), lambda i: roles[i] = roles[i - 1])) = 0 as alternates from a) select * from b)"
    )


def vec_sql() -> str:
    return "vec as (select md5(cast(vec_id as varchar)) as entity_id, concat('label-', label) as batch_name, {'vec_id': vec_id, 'label': label, 'embedding': embedding} as raw from embeddings)"


TWINS = {"web": web_sql, "trade": trade_sql, "signal": signal_sql, "sft": sft_sql, "vec": vec_sql}


def twin(text: str) -> str:
    """A query on logical tables as flat SQL on raw tables."""
    import re

    ctes = ", ".join(make(text) if n == "web" else make() for n, make in TWINS.items() if re.search(rf"\b{n}\b", text))
    if not ctes:
        return text
    rest = text.strip()
    if rest.lower().startswith("with recursive "):
        return f"with recursive {ctes}, {rest[15:]}"
    return f"with {ctes}, {rest[5:]}" if rest.lower().startswith("with ") else f"with {ctes} {rest}"
