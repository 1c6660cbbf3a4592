"""The engine: one logical table to its users, everything else behind it."""

from __future__ import annotations

import json
import time
from collections.abc import Iterable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .catalog import Catalog, CatalogSnapshot
from .model import ID, Column, EngineConfig, FeatureSpec, PlanningError
from .operators import ingest as ingestion
from .operators.executor import ERRORS, BackfillReport, BackfillRequest, Executor
from .operators.governance import Governor, Policy
from .operators.idindex import IdIndex
from .operators.materialize import Materializer
from .operators.storage import new_id, shared_base, ship
from .plans import translate
from .plans.routing import ClusterLoad
from .plans.tuning import History
from .sources.adapters import SourceSpec


#: Up to so many files the rows of a few ids are put together by one task.
FEW_FILES = 64


class Engine:
    """Ingestion, features, exploration and governance over one catalog and one folder."""

    def __init__(self, spark: SparkSession, config: EngineConfig | None = None, root: str | None = None, catalog: Catalog | None = None, policy: Policy | None = None):
        ship(spark)
        self.spark, self.config = spark, config or EngineConfig()
        self.root = root or f"{shared_base(spark)}/{new_id('wide')}"
        self.catalog = catalog or Catalog(column_limit=self.config.column_limit)
        self.load, self.history = ClusterLoad(), History()
        self.executor, self.index, self.materializer = Executor(self), IdIndex(self), Materializer(self)
        self.governor = Governor(self, policy)
        self.calls: list[str] = []

    # ---- rows

    def ingest(self, source: SourceSpec, table: str, batch: str, mapping: dict[str, str], **options):
        """Submit a batch (or, with many=True, one a value of the expression `batch`)."""
        self.calls.append(f"ingest {table}")
        return ingestion.ingest(self.spark, self.catalog, self.root, source, table, batch, mapping, known_ids=lambda s: self.known_ids(table), **({"target_mb": self.config.write_mb} | options))

    def known_ids(self, table: str) -> DataFrame:
        """The ids of all committed batches: from the core tables, two narrow columns."""
        snap = self.catalog.snapshot(table)
        return translate.assemble(self.spark, snap, ()).relation.select(ID)

    # ---- features

    def add_feature(self, table: str, spec: FeatureSpec, bump: bool = False) -> FeatureSpec:
        self.calls.append(f"add_feature {spec.name}")
        return self.catalog.add_feature(table, spec, translate.stub(self.spark, self.catalog.snapshot(table)), bump)

    def backfill(self, table: str, pairs: Iterable[tuple[str, str]] | None = None, columns: Sequence[str] = (), batches: Sequence[str] | None = None, **options) -> BackfillReport:
        """Fill pairs, or the columns of all (or some) batches."""
        self.calls.append(f"backfill {table}")
        if pairs is None:
            names = [b.name for b in self.catalog.snapshot(table).batches]
            pairs = [(b, c) for b in (batches or names) for c in columns]
        return self.executor.run(BackfillRequest(table, tuple(pairs), **options))

    def refresh(self, table: str, pairs: Iterable[tuple[str, str]]) -> BackfillReport:
        """Compute pairs again; what depends on them becomes stale."""
        return self.backfill(table, pairs, recompute=True)

    def explain_backfill(self, table: str, pairs: Iterable[tuple[str, str]]) -> DataFrame:
        """The tasks that a backfill would run."""
        tasks = self.executor.plan(BackfillRequest(table, tuple(pairs)))
        rows = [(t.number, list(t.batches), t.level, t.lane, list(t.columns), list(t.inputs), list(t.after)) for t in tasks]
        return self.spark.createDataFrame(rows, "task int, batches array<string>, level int, lane string, columns array<string>, inputs array<string>, after array<int>")

    # ---- queries

    def _choose(self, name: str, need: translate.Requirement, version: int | None, path: str | None) -> translate.Assembly:
        """point: index; aggregate on synced columns: replica; fewer joins by a view: view; else base tables."""
        snap = self.catalog.snapshot(name, version)
        batches = translate.prune_batches(self.spark, snap, need.batch_predicates)
        path = path or self.config.forced_path
        current = version is None
        if need.ids and self.config.use_index and current and path in (None, "index") and self.index.covered(name):
            narrow, with_rows, files = self.index.narrowed(name, snap, need.ids)
            files += 0 if self.index.coverage(name) == 1 else FEW_FILES  # what isn't indexed is scanned by many tasks
            out = translate.assemble(self.spark, narrow, need.columns, [b for b in with_rows if b in set(batches)], need.ids, few_files=files <= FEW_FILES)
            out.route, out.reason = "index", f"id equality, {len(out.tables)} files"
            return out
        if self.config.use_replica and current and path in (None, "replica"):
            ok, why = self.materializer.eligible(need, snap, batches, self.config.max_lag)
            if ok:
                return self.materializer.replica_relation(need, snap, batches)
        else:
            why = "replica off"
        if self.config.use_views and current and path in (None, "view") and (found := self.materializer.match(need, snap, batches)):
            return found
        out = translate.assemble(self.spark, snap, need.columns, batches, need.ids)
        out.reason = f"base tables ({why})"
        return out

    def snapshots(self, text: str, version: int | dict[str, int] | None) -> dict[str, CatalogSnapshot]:
        """Snapshots of the logical tables that the text names: the current ones, or at a version (by table if there are several)."""
        names = translate.named_in(text, [r["path"] for r in self.catalog.store.query("select path from tables")])
        if isinstance(version, int):
            if len(names) > 1:
                raise PlanningError(f"{names}: with several tables, version is a dict by table")
            version = {n: version for n in names}
        return {n: self.catalog.snapshot(n, (version or {}).get(n)) for n in names}

    def plan(self, text: str, version: int | dict[str, int] | None = None, path: str | None = None, views: dict[str, DataFrame] | None = None) -> tuple[dict[str, translate.Assembly], dict[str, translate.Requirement]]:
        """Requirements and relations of the logical tables that the text names."""
        return self._plan(text, self.snapshots(text, version), version, path, views)

    def _plan(self, text, tables, version, path, views):
        session = self.spark.newSession()
        for name, snap in tables.items():
            translate.in_session(session, translate.stub(self.spark, snap)).createOrReplaceTempView(name)
        for name, view in (views or {}).items():
            translate.in_session(session, view).createOrReplaceTempView(name)
        if "sys_" in text:
            for name in self._sys_tables(list(tables)):
                self.catalog.register_views(session, name)
        needs = translate.required(session.sql(text), tables)
        at = version if isinstance(version, dict) else dict.fromkeys(tables, version)
        return {n: self._choose(n, need, at.get(n), path) for n, need in needs.items()}, needs

    def _sys_tables(self, named: list[str]) -> list[str]:
        """The logical table that sys_* views of a query are about: the one it names, else the first."""
        return named[:1] or [r["path"] for r in self.catalog.store.query("select path from tables order by rowid limit 1")]

    def sql(self, text: str, version: int | dict[str, int] | None = None, path: str | None = None, log: bool = True, views: dict[str, DataFrame] | None = None) -> DataFrame:
        """Plain SQL on logical tables, on sys_* views and on other DataFrames given by name."""
        began = time.time()
        tables = self.snapshots(text, version)
        assemblies, needs = self._plan(text, tables, version, path, views)
        # a table that the optimizer drops from the plan is bound whole all the same, never to an empty stand-in
        relations = {n: translate.padded(assemblies[n].relation, snap) if n in assemblies else translate.assemble(self.spark, snap, [c.name for c in snap.columns]).relation for n, snap in tables.items()} | (views or {})
        register = (lambda s: [self.catalog.register_views(s, n) for n in self._sys_tables(list(tables))]) if "sys_" in text else None
        out = translate.bind(self.spark, relations, text, register)
        out.logged = []
        if log:
            for n, need in needs.items():
                out.logged.append(self.log_query(n, need.columns, need.predicates, need.shape, assemblies[n].route, assemblies[n].joins + 1, assemblies[n].bytes, 1000 * (time.time() - began)))
        return out

    def timed(self, text: str, **options) -> list:
        """The rows of a query; its log entry, which has the time of planning until then, gets the whole time."""
        began = time.time()
        out = self.sql(text, **options)
        found = out.collect()
        for query_id in out.logged:
            self.catalog.store.execute("update query_log set ms = ? where query_id = ?", 1000 * (time.time() - began), query_id)
        return found

    def log_query(self, table: str, columns: Sequence[str], predicates: Sequence[str] = (), shape: str = "export", route: str = "base", tables_joined: int = 1, size: int = 0, ms: float = 0.0, at: float | None = None) -> int:
        """Add a query to the log; its id."""
        with self.catalog.store.transaction():
            self.catalog.store.execute(
                "insert into query_log (path, at, columns, predicates, shape, route, tables_joined, bytes, ms, snapshot_version) values (?, ?, ?, ?, ?, ?, ?, ?, ?, ?)",
                table, at or time.time(), json.dumps(list(columns)), json.dumps(list(predicates)), shape, route, tables_joined, size, ms, self.catalog.store.version(table),
            )
            return self.catalog.store.query("select last_insert_rowid() as i")[0]["i"]

    def query_log(self, table: str) -> DataFrame:
        rows = [(r["query_id"], json.loads(r["columns"])) for r in self.catalog.store.query("select query_id, columns from query_log where path = ?", table)]
        return self.spark.createDataFrame(rows, "query_id long, columns array<string>")

    def explain_sql(self, text: str) -> DataFrame:
        """Route, reason, joins and tables of each logical table in the text."""
        assemblies, needs = self.plan(text)
        rows = [(n, a.route, a.reason, a.joins, len(a.tables), list(a.batches), list(needs[n].columns), a.bytes) for n, a in assemblies.items()]
        return self.spark.createDataFrame(rows, "table_name string, route string, reason string, joins int, files_sets int, batches array<string>, columns array<string>, bytes long")

    def table(self, name: str, columns: Sequence[str] | None = None, version: int | None = None, as_of: float | None = None) -> DataFrame:
        """The logical table, or some columns of it, as a DataFrame."""
        snap = self.catalog.snapshot(name, version, as_of)
        return translate.assemble(self.spark, snap, columns or [c.name for c in snap.columns]).relation

    def lookup(self, table: str, entity_id: str, columns: Sequence[str] | None = None, use_index: bool = True) -> DataFrame:
        """One entity with all its stages and features."""
        return self.lookup_many(table, [entity_id], columns, use_index)

    def lookup_many(self, table: str, ids: Sequence[str], columns: Sequence[str] | None = None, use_index: bool = True) -> DataFrame:
        """Rows of a list of ids; what the index doesn't cover is scanned."""
        snap = self.catalog.snapshot(table)
        columns = list(columns or [c.name for c in snap.columns])
        if use_index and self.config.use_index:
            narrow, batches, files = self.index.narrowed(table, snap, ids)
            whole = self.index.coverage(table) == 1
            return translate.assemble(self.spark, narrow, columns, batches, ids, few_files=whole and files <= FEW_FILES).relation
        return translate.assemble(self.spark, snap, columns, None, ids).relation

    def lookup_frame(self, table: str, ids: DataFrame, columns: Sequence[str]) -> DataFrame:
        """Rows of many ids (a DataFrame with entity_id): a semi-join, so the list may be of any size."""
        return self.table(table, columns).join(ids.select(ID).distinct(), ID, "left_semi")

    def export(self, text: str, path: str, format: str = "parquet", max_records: int | None = None, partition_by: Sequence[str] = ()) -> str:
        """Write a query's rows to files; a finished folder carries _SUCCESS."""
        self.calls.append("export")
        writer = self.sql(text).write.mode("errorifexists")
        if max_records:
            writer = writer.option("maxRecordsPerFile", max_records)
        writer.partitionBy(*partition_by).format(format).save(path)
        return path

    def errors(self, table: str) -> DataFrame:
        """All isolated records."""
        paths = [r["location"] for r in self.catalog.store.query("select location from errors where path = ?", table)]
        return self.spark.read.schema(ERRORS).parquet(*paths) if paths else self.spark.createDataFrame([], ERRORS)

    def catch_up(self, table: str, since: int = 0) -> dict[str, int]:
        """What follows commits: index, replica and views take up the changes after a version; counts of what was done."""
        events = self.catalog.changes_since(table, since)
        done = {"events": len(events), "indexed": 0, "synced": 0, "refreshed": 0}
        if any(kind in ("batch", "backfill", "layout") for _, kind, _ in events):
            snap = self.catalog.snapshot(table)
            done["indexed"] = self.index.catch_up(table) if self.index.covered(table) else 0
            if self.materializer.replica(snap):
                done["synced"] = len(self.materializer.sync(table))
            for view_id in self.materializer.views(snap):
                done["refreshed"] += len(self.materializer.refresh(table, view_id))
        return done

    def stub(self, table: str) -> DataFrame:
        return translate.stub(self.spark, self.catalog.snapshot(table))

    def stage_columns(self, *columns: tuple[str, str]) -> list[Column]:
        return [Column(n, t) for n, t in columns]

    def features_by_lane(self, table: str) -> DataFrame:
        """How many registered features run in each lane."""
        from .plans.routing import OperatorProfile, choose_lane

        rows = [(choose_lane(f.mode, OperatorProfile.of(f), self.load),) for f in self.catalog.snapshot(table).features]
        return self.spark.createDataFrame(rows, "lane string").groupBy("lane").agg(F.count("*").alias("features"))
