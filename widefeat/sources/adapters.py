"""Sources: what a batch is read from, checked and with broken rows set aside."""

from __future__ import annotations

import json
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

CORRUPT = "_corrupt_record"
TEXT_FORMATS = ("json", "csv")


@dataclass(frozen=True)
class SourceSpec:
    """format: parquet, orc, json, csv, text, binaryFile, table or memory (then `frame`)."""

    format: str
    path: str | list[str] | None = None
    options: dict[str, str] = field(default_factory=dict)
    schema: str | T.StructType | None = None
    frame: DataFrame | None = None
    transform: Callable[[DataFrame], DataFrame] | None = None

    def describe(self) -> str:
        return json.dumps({"format": self.format, "path": self.path, "options": self.options})


def adapt(spark: SparkSession, source: SourceSpec) -> tuple[DataFrame, DataFrame | None]:
    """Rows of the source, and the rows that couldn't be parsed (text formats with a schema)."""
    if source.format == "memory":
        rows, bad = source.frame, None
    elif source.format == "table":
        rows, bad = spark.table(source.path), None
    elif source.format in TEXT_FORMATS and source.schema is not None:
        rows, bad = parsed_lines(spark, source)
    else:
        reader = spark.read.options(**source.options)
        rows, bad = (reader.schema(source.schema) if source.schema is not None else reader).format(source.format).load(source.path), None
    return (source.transform(rows) if source.transform else rows), bad


def parsed_lines(spark: SparkSession, source: SourceSpec) -> tuple[DataFrame, DataFrame]:
    """Lines parsed one by one, so that broken ones can be counted and kept as they are. A header line is left out."""
    schema = T.StructType.fromDDL(source.schema) if isinstance(source.schema, str) else source.schema
    marked = T.StructType([*schema.fields, T.StructField(CORRUPT, T.StringType())])
    options = {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": CORRUPT} | {k: v for k, v in source.options.items() if k != "header"}
    lines = spark.read.text(source.path).where(F.trim("value") != "")
    if source.options.get("header", "false").lower() == "true" and (first := lines.first()):
        lines = lines.where(F.col("value") != first.value)
    parse = F.from_json if source.format == "json" else F.from_csv
    kind = marked if source.format == "json" else ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in marked)
    rows = lines.select("value", parse("value", kind, options).alias("r"))
    broken = F.col("r").isNull() | F.col(f"r.{CORRUPT}").isNotNull()
    return rows.where(~broken).select("r.*").drop(CORRUPT), rows.where(broken).select(F.col("value").alias(CORRUPT))
