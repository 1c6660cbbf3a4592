"""The earlier workflow, for comparison: a table a source, a job a feature and table, joins written by hand."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.models import model_of
from .model import FeatureSpec
from .operators.storage import new_id, shared_base


@dataclass
class Legacy:
    """Independent tables; every step is a job of its own. Counts jobs, tables and manual steps."""

    spark: SparkSession
    root: str = ""
    tables: dict[str, str] = field(default_factory=dict)
    results: dict[tuple[str, str], str] = field(default_factory=dict)
    jobs: int = 0
    manual_steps: int = 0

    def __post_init__(self) -> None:
        self.root = self.root or f"{shared_base(self.spark)}/{new_id('legacy')}"

    def ingest(self, sources: dict[str, DataFrame]) -> None:
        """One physical table a source: (id, payload)."""
        for name, rows in sources.items():
            path = f"{self.root}/{new_id('src')}"
            rows.write.parquet(path)
            self.tables[name], self.jobs, self.manual_steps = path, self.jobs + 1, self.manual_steps + 2

    def backfill(self, features: Sequence[FeatureSpec], order: Sequence[str]) -> None:
        """A job for each feature and table: joins what it needs, writes one result table."""
        specs = {f.name: f for f in features}
        for name in self.tables:
            for f in (specs[n] for n in order):
                rows = self.relation(name, [i for i in f.inputs if i in {o for s in specs.values() for o in s.output_names}])
                for let, expr in f.lets:
                    rows = rows.withColumn(let, F.expr(expr))
                if f.fn is None:
                    out = [F.expr(e).cast(o.type).alias(o.name) for o, e in zip(f.outputs, f.exprs, strict=True)]
                else:
                    udf = F.pandas_udf(model_of(f).many, f.outputs[0].type)
                    out = [udf(*(F.expr(a) for a in f.exprs)).alias(f.outputs[0].name)]
                path = f"{self.root}/{new_id('feat')}"
                rows.select("entity_id", *out).write.parquet(path)
                for o in f.output_names:
                    self.results[name, o] = path
                self.jobs, self.manual_steps = self.jobs + 1, self.manual_steps + 1

    def relation(self, name: str, columns: Sequence[str]) -> DataFrame:
        """A source's table with one join for each result column."""
        rows = self.spark.read.parquet(self.tables[name])
        for c in dict.fromkeys(columns):
            rows = rows.join(self.spark.read.parquet(self.results[name, c]).select("entity_id", c), "entity_id", "left")
        return rows

    def export(self, columns: Sequence[str], where: str) -> DataFrame:
        """Hand-written joins a source, then a union over sources."""
        self.manual_steps += len(self.tables)
        parts = [self.relation(n, [c for c in columns if (n, c) in self.results]).select("entity_id", F.lit(n).alias("batch_name"), *columns).where(where) for n in self.tables]
        return reduce(DataFrame.unionByName, parts)

    @property
    def physical_tables(self) -> int:
        return len(self.tables) + len(set(self.results.values()))


def failover_loop(rows: DataFrame, fn: Callable, column: str, kinds: dict[str, str], most_rounds: int = 10) -> tuple[int, int]:
    """Find, remove, resubmit: (rounds, records removed).

    A round runs everything; the error that it dies of names one kind of broken record, whose rows (a predicate each, as
    an engineer would write it) are removed before the next round.
    """
    bad, rounds = "false", 0
    while rounds < most_rounds:
        rounds += 1
        left = rows.where(f"not ({bad})")
        try:
            left.select(F.udf(fn, "double")(F.col(column)).alias("v")).write.format("noop").mode("overwrite").save()
            break
        except Exception as e:
            found = next((k for k in kinds if k in str(e)), None)
            if found is None:
                raise
            bad = f"{bad} or ({kinds[found]})"
    return rounds, rows.where(bad).count()
