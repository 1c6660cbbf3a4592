"""The registered queries of this package: thin digests over its operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import language_id, quality_rules, toxicity
from .ann import nearest
from .common import held_out, read_table
from .html_render import extract_text
from .packing import pack
from .sharding import shard_by_bytes
from .simhash import near_duplicates
from .token_files import token_digest
from .transducer import codec_digest


def op1_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_digest(read_table(spark, sf_dir, "documents"), end_id=2)


def op2_transducer_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return codec_digest(read_table(spark, sf_dir, "documents"))


def op3_minimum_slack_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(read_table(spark, sf_dir, "documents"), end_id=1)


def op4_ftrl_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    scores = toxicity.score(docs, toxicity.fit(docs, read_table(spark, sf_dir, "labels")))
    return scores.select("doc_id", held_out("doc_id").alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op5_decision_list_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    judged = quality_rules.judge(docs, quality_rules.fit(docs, read_table(spark, sf_dir, "labels")))
    return judged.select("doc_id", *quality_rules.COUNTS, "base_failed", "kept")


def op7_language_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    found = language_id.identify(docs, language_id.fit(docs))
    return found.select("doc_id", held_out("doc_id").alias("held_out"), "lang_pred", "score")


def op6_layout_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_text(read_table(spark, sf_dir, "pages"))


def op8_byte_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_by_bytes(read_table(spark, sf_dir, "documents"), shards=8)


def op9_anisotropic_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(read_table(spark, sf_dir, "embeddings"), k=5)


def op10_pigeonring_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(read_table(spark, sf_dir, "documents"), shingle=3, most_bits=2)
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_token_files, op2_transducer_codec, op3_minimum_slack_packing, op4_ftrl_toxicity, op5_decision_list_quality, op6_layout_text, op7_language_mixture, op8_byte_shards, op9_anisotropic_search, op10_pigeonring_simhash)}


def oracle_sql() -> dict[str, str]:
    return {}
