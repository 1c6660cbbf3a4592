"""A corpus pipeline of four stages; each works on all that the one before kept.

Quality rules, language identification, near-duplicates by shingles, packing. Filtering stages return the columns of
`documents`, whatever these are: what is rejected goes, and one document of each near-duplicate group (the smallest
doc_id) stays. The language stage keeps a document if half of it or more is in the languages learned from the corpus.

Edge cases: null and empty texts fail the quality rules; null doc_ids, repeated rows and equal ids are judged row by
row, and of rows equal in id and text one stays; empty tables pass through every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from widefeat.llm import language_id, quality_rules, similar
from widefeat.llm.common import read_table, staged
from widefeat.llm.packing import pack

def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rules and the learned decision list."""
    rules = quality_rules.fit(docs, read_table(spark, sf_dir, "labels"))
    return quality_rules.keep(docs, rules, docs.columns)


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose mixture of languages is half or more in languages that the corpus has labels of."""
    return language_id.keep(docs, language_id.fit(docs))


def copies_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of texts that share 0.8 or more of their five-word shingles."""
    return similar.one_of_each(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in sequences of at most 2048 tokens."""
    return pack(docs, end_id=1)


STAGES = [("quality_rules", quality_stage), ("language", language_stage), ("near_duplicates", copies_stage), ("packing", packing_stage)]

#: Learned rules and mixtures, similar texts and packing have no SQL form; tests compare each stage with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`; between two stages the documents are written and read again."""
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
