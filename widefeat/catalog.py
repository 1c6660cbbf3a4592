"""The catalog: logical tables, columns, features, batches and where their files are.

A snapshot is an immutable picture of one version; queries and backfills work on it while others commit.
"""

from __future__ import annotations

import hashlib
import json
import time
from collections.abc import Iterable, Sequence
from dataclasses import dataclass, replace
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .metastore import FOREVER, MetaStore
from .model import ABSENT, BATCH, COMPUTED, ID, KEYS, BatchEntry, Column, ColumnLimitError, FeatureSpec, LineageRecord, Physical, PlanningError
from .plans.dag import FeatureGraph



def logical_name(entry: str) -> str:
    """A physical table lists columns by name, or as `stored as logical`."""
    return entry.rpartition(" as ")[2]


def stored_name(entry: str) -> str:
    return entry.partition(" as ")[0]


SYS = {
    "tables": "select path, version as current_version, props from tables where path = ?",
    "columns": "select name, type, kind, feature, version as column_version, comment, analysis_type, valid_from, valid_to from columns where path = ?",
    "groups": "select group_id, purpose, lock_owner, lock_until from groups where path = ?",
    "physical_tables": "select phys_id, group_id, location, batch, purpose, rows, bytes, files, lo, hi, sorted_by, valid_from, valid_to from physical where path = ?",
    "batches": "select name as batch_name, rows, duplicates as duplicates_dropped, source, mapping, id_strategy, ingested_at, valid_from as version from batches where path = ?",
    "features": "select name as feature_id, version, spec, expr_hash, registered_at, active from features where path = ?",
    "status": "select batch as batch_name, column_name, version as column_version, state, run_id from status where path = ?",
    "lineage": "select run_id, batch as batch_name, column_name, feature as feature_id, feature_version, lane, input_versions, finished_at, rows_ok, rows_bad, error_ref, parents, table_version from lineage where path = ?",
    "runs": "select run_id, feature, batch as batch_name, attempt, ok, cpu_s, peak_mb, bytes_in, bytes_out, rows, params, wall_s, lane from runs where path = ?",
    "checkpoints": "select c.run_id, c.unit, c.location, c.done_at from checkpoints c where c.run_id in (select run_id from lineage where path = ?)",
    "query_log": "select query_id, at, columns, predicates, shape, route, tables_joined, bytes, ms, snapshot_version from query_log where path = ?",
    "views": "select view_id, columns, freq, state, last_used from views where path = ?",
    "index_coverage": "select phys_id, rows, version from index_segments where path = ?",
    "changes": "select version, kind, payload, at from changes where path = ?",
}
SYS_TYPES = {"version": "long", "current_version": "long", "column_version": "long", "feature_version": "long", "table_version": "long", "snapshot_version": "long", "valid_from": "long", "valid_to": "long", "rows": "long", "bytes": "long", "files": "long", "lo": "long", "hi": "long", "duplicates_dropped": "long", "rows_ok": "long", "rows_bad": "long", "attempt": "long", "ok": "long", "bytes_in": "long", "bytes_out": "long", "active": "long", "query_id": "long", "tables_joined": "long", "freq": "long", "created_at": "double", "lock_until": "double", "ingested_at": "double", "registered_at": "double", "finished_at": "double", "cpu_s": "double", "peak_mb": "double", "wall_s": "double", "done_at": "double", "at": "double", "ms": "double", "last_used": "double"}


@dataclass(frozen=True)
class CatalogSnapshot:
    """One version of a logical table."""

    path: str
    version: int
    columns: tuple[Column, ...]
    batches: tuple[BatchEntry, ...]
    physical: tuple[Physical, ...]
    features: tuple[FeatureSpec, ...]
    status: dict[tuple[str, str], str]

    @cached_property
    def schema(self) -> T.StructType:
        return T.StructType([T.StructField(c.name, T.StructType.fromDDL(f"x {c.type}")[0].dataType, c.kind not in ("id", "batch")) for c in self.columns])

    @cached_property
    def graph(self) -> FeatureGraph:
        return FeatureGraph.from_specs(self.features)

    @cached_property
    def by_place(self) -> dict[tuple[str, str], list[Physical]]:
        """(batch, column) to the base tables that hold it (several if split by id range)."""
        out: dict[tuple[str, str], list[Physical]] = {}
        for p in self.physical:
            if p.purpose in ("core", "features"):
                for c in p.columns:
                    out.setdefault((p.batch, logical_name(c)), []).append(p)
        return out

    def column(self, name: str) -> Column:
        for c in self.columns:
            if c.name == name:
                return c
        raise PlanningError(f"{self.path} has no column {name}")

    def resolve(self, batch: str, column: str) -> list[Physical]:
        """Where a column of a batch lies; empty: it is NULL there."""
        return self.by_place.get((batch, column), [])

    def batches_matching(self, spark: SparkSession, predicate: str) -> list[str]:
        """Batches that satisfy a predicate on batch_name, decided without a job."""
        if not self.batches:
            return []
        values = ", ".join("('" + b.name.replace("\\", "\\\\").replace("'", "\\'") + "')" for b in self.batches)
        return [r[0] for r in spark.sql(f"select {BATCH} from values {values} as t({BATCH}) where {predicate}").collect()]


class Catalog:
    """Metadata operations; all changes are transactions on one table's version."""

    def __init__(self, store: MetaStore | None = None, column_limit: int = 1200):
        self.store, self.column_limit = store or MetaStore(), column_limit

    # ---- tables and columns

    def create_table(self, path: str, columns: Sequence[Column] = (), props: dict | None = None) -> None:
        fixed = [Column(ID, "string", "id"), Column(BATCH, "string", "batch")]
        with self.store.transaction():
            if self.store.query("select 1 from tables where path = ?", path):
                raise PlanningError(f"{path} exists")
            self.store.execute("insert into tables values (?, 1, ?, ?)", path, time.time(), json.dumps(props or {}))
            for c in [*fixed, *columns]:
                self._put_column(path, c, 1)

    def exists(self, path: str) -> bool:
        return bool(self.store.query("select 1 from tables where path = ?", path))

    def _put_column(self, path: str, c: Column, version: int) -> None:
        self.store.execute("update columns set valid_to = ? where path = ? and name = ? and valid_to = ?", version, path, c.name, FOREVER)
        self.store.execute("insert into columns values (?, ?, ?, ?, ?, ?, ?, ?, ?, ?)", path, c.name, c.type, c.kind, c.feature, c.version, c.comment, c.analysis_type, version, FOREVER)

    def add_columns(self, path: str, columns: Iterable[Column]) -> int:
        columns = list(columns)
        return self.store.commit(path, None, "columns", [c.name for c in columns], lambda v: [self._put_column(path, c, v) for c in columns])

    # ---- features

    def add_feature(self, path: str, spec: FeatureSpec, stub: DataFrame | None = None, bump: bool = False) -> FeatureSpec:
        """Register a feature: inputs exist, outputs are new, no cycle, and expressions have the declared types."""
        snap = self.snapshot(path)
        names = {c.name: c for c in snap.columns}
        if missing := [c for c in spec.inputs if c not in names]:
            raise PlanningError(f"{spec.name}: unknown inputs {missing}")
        old = {f.name: f for f in snap.features}.get(spec.name)
        if old and not bump:
            raise PlanningError(f"{spec.name} is registered; bump=True makes a new version")
        if taken := [o.name for o in spec.outputs if o.name in names and names[o.name].feature != spec.name]:
            raise PlanningError(f"{spec.name}: outputs {taken} exist")
        spec = replace(spec, version=old.version + 1 if old else 1, table=path)
        FeatureGraph.from_specs([f for f in snap.features if f.name != spec.name] + [spec]).check_acyclic()
        if stub is not None and spec.fn is None:
            for name, expr in spec.lets:
                stub = stub.withColumn(name, F.expr(expr))
            if len(spec.outputs) != len(spec.exprs):
                raise PlanningError(f"{spec.name}: {len(spec.outputs)} outputs, {len(spec.exprs)} expressions")
            stub.selectExpr(*(f"cast({expr} as {out.type}) as `{out.name}`" for out, expr in zip(spec.outputs, spec.exprs, strict=True)))  # fails if it can't be analysed

        def work(v: int) -> None:
            self.store.execute("update features set active = 0 where path = ? and name = ?", path, spec.name)
            digest = hashlib.md5("|".join([*spec.exprs, spec.fn or ""]).encode()).hexdigest()
            self.store.execute("insert into features values (?, ?, ?, ?, ?, ?, 1, ?)", path, spec.name, spec.version, spec.to_json(), digest, time.time(), v)
            for o in spec.outputs:
                self._put_column(path, Column(o.name, o.type, "feature", spec.name, spec.version, o.comment, o.analysis_type), v)
                if old:
                    self._keep_old(path, o.name, old.version, v)

        self.store.commit(path, None, "feature", {"feature": spec.name, "version": spec.version}, work)
        return spec

    def _keep_old(self, path: str, column: str, version: int, v: int) -> None:
        """Values of the version before stay readable as column@vN; the column itself is to be computed again."""
        kept = f"{column}@v{version}"
        c = self.store.query("select * from columns where path = ? and name = ? order by valid_from desc limit 1", path, column)[0]
        self._put_column(path, Column(kept, c["type"], "feature", None, version, f"version {version} of {column}"), v)
        for r in self.store.query("select rowid, columns from physical where path = ? and valid_to = ?", path, FOREVER):
            names = json.loads(r["columns"])
            if column in names:
                names[names.index(column)] = f"{column} as {kept}"
                self.store.execute("update physical set columns = ? where rowid = ?", json.dumps(names), r["rowid"])
        for r in self.store.query("select batch, state, run_id from status where path = ? and column_name = ?", path, column):
            self.store.execute("insert or replace into status values (?, ?, ?, ?, ?, ?)", path, r["batch"], kept, version, r["state"], r["run_id"])
        self.store.execute("delete from status where path = ? and column_name = ?", path, column)

    # ---- snapshots

    def snapshot(self, path: str, version: int | None = None, as_of: float | None = None) -> CatalogSnapshot:
        """The table now, at a version, or at a time."""
        s = self.store
        with s.mutex:
            now = s.version(path)
            if as_of is not None:
                found = s.query("select max(version) as v from changes where path = ? and at <= ?", path, as_of)
                version = found[0]["v"] or 1
            v = now if version is None else version
            columns = tuple(Column(r["name"], r["type"], r["kind"], r["feature"], r["version"], r["comment"], r["analysis_type"]) for r in s.query("select * from columns where path = ? and valid_from <= ? and valid_to > ? order by rowid", path, v, v))
            batches = tuple(BatchEntry(r["name"], r["rows"], r["duplicates"], r["source"], r["mapping"], r["id_strategy"], r["ingested_at"]) for r in s.query("select * from batches where path = ? and valid_from <= ? order by valid_from, rowid", path, v))
            physical = tuple(self._physical(r) for r in s.query("select * from physical where path = ? and valid_from <= ? and valid_to > ? order by rowid", path, v, v))
            features: dict[str, FeatureSpec] = {}
            for r in s.query("select spec from features where path = ? and valid_from <= ? order by version", path, v):
                f = FeatureSpec.from_json(r["spec"])
                features[f.name] = f
            status = {(r["batch"], r["column_name"]): r["state"] for r in s.query("select * from status where path = ?", path)}
        return CatalogSnapshot(path, v, columns, batches, physical, tuple(features.values()), status)

    @staticmethod
    def _physical(r) -> Physical:
        return Physical(r["phys_id"], r["group_id"], r["location"], r["batch"], tuple(json.loads(r["columns"])), r["purpose"], r["rows"], r["bytes"], r["files"], r["lo"], r["hi"], r["sorted_by"], tuple(json.loads(r["versions"])))

    # ---- mapping

    def put_physical(self, path: str, p: Physical, v: int) -> None:
        """Map a physical table; one with more columns than the limit (keys and all) is refused."""
        if len(p.columns) + len(KEYS) > self.column_limit:
            raise ColumnLimitError(f"{len(p.columns) + len(KEYS)} columns in {p.group} of {p.batch}, the limit is {self.column_limit}")
        self.store.execute("insert or ignore into groups values (?, ?, ?, null, 0)", path, p.group, p.purpose)
        self.store.execute("insert into physical values (?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?)", path, p.phys_id, p.group, p.path, p.batch, json.dumps(p.columns), p.purpose, p.rows, p.bytes, p.files, p.lo, p.hi, p.sorted_by, json.dumps(p.versions), v, FOREVER, time.time())

    def swap_mapping(self, path: str, remove: Iterable[str], add: Iterable[Physical], kind: str = "layout", expected: int | None = None) -> int:
        """Replace physical tables by others: pointers only, the logical schema stays."""
        remove, add = list(remove), list(add)

        def work(v: int) -> None:
            for phys_id in remove:
                self.store.execute("update physical set valid_to = ?, changed_at = ? where path = ? and phys_id = ? and valid_to = ?", v, time.time(), path, phys_id, FOREVER)
            for p in add:
                self.put_physical(path, p, v)

        return self.store.commit(path, expected, kind, {"remove": remove, "add": [p.phys_id for p in add]}, work)

    def dropped_physical(self, path: str, min_age_s: float = 0) -> list[Physical]:
        """Tables that no current version maps, replaced at least that long ago."""
        rows = self.store.query("select * from physical where path = ? and valid_to < ? and changed_at <= ?", path, FOREVER, time.time() - min_age_s)
        live = {p.path for p in self.snapshot(path).physical}
        return [p for p in map(self._physical, rows) if p.path not in live]

    # ---- batches

    def register_batches(self, path: str, entries: Sequence[tuple[BatchEntry, Sequence[Physical], Sequence[str], Sequence[str]]], expected: int | None = None) -> int:
        """Make batches visible: (entry, files, columns that are filled, columns that are absent) of each, all at once."""

        def work(v: int) -> None:
            for b, files, filled, absent in entries:
                if self.store.query("select 1 from batches where path = ? and name = ?", path, b.name):
                    raise PlanningError(f"batch {b.name} exists")
                self.store.execute("insert into batches values (?, ?, ?, ?, ?, ?, ?, ?, ?)", path, b.name, b.rows, b.duplicates_dropped, b.source, b.mapping, b.id_strategy, b.ingested_at or time.time(), v)
                for p in files:
                    self.put_physical(path, p, v)
                for names, state in ((filled, COMPUTED), (absent, ABSENT)):
                    for c in names:
                        self.store.execute("insert or replace into status values (?, ?, ?, 1, ?, '')", path, b.name, c, state)

        return self.store.commit(path, expected, "batch", [b.name for b, *_ in entries], work)

    def has_batch(self, path: str, name: str) -> bool:
        return bool(self.store.query("select 1 from batches where path = ? and name = ?", path, name))

    def pending_pairs(self, path: str) -> list[tuple[str, str]]:
        """(batch, feature column) pairs that are not computed."""
        snap = self.snapshot(path)
        wanted = [c for f in snap.features for c in f.output_names]
        return [(b.name, c) for b in snap.batches for c in wanted if snap.status.get((b.name, c)) != COMPUTED]

    # ---- status, lineage, runs

    def set_status(self, path: str, pairs: Iterable[tuple[str, str]], state: str, run_id: str = "", version: int = 1) -> None:
        with self.store.transaction():
            for batch, column in pairs:
                self.store.execute("insert or replace into status values (?, ?, ?, ?, ?, ?)", path, batch, column, version, state, run_id)

    def commit_pairs(self, path: str, records: Sequence[LineageRecord], add: Sequence[Physical], remove: Sequence[str] = (), trimmed: Sequence[tuple[str, Physical]] = ()) -> int:
        """Status, mapping and lineage of computed pairs, atomically."""

        def work(v: int) -> None:
            for phys_id in [*remove, *(old for old, _ in trimmed)]:
                self.store.execute("update physical set valid_to = ?, changed_at = ? where path = ? and phys_id = ? and valid_to = ?", v, time.time(), path, phys_id, FOREVER)
            for p in [*add, *(new for _, new in trimmed)]:
                self.put_physical(path, p, v)
            for r in records:
                self.store.execute("insert or replace into status values (?, ?, ?, ?, ?, ?)", path, r.batch, r.column, r.feature_version, COMPUTED, r.run_id)
                self.store.execute("insert into lineage values (?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?, ?)", path, r.run_id, r.batch, r.column, r.feature, r.feature_version, r.lane, r.input_versions, r.finished_at, r.rows_ok, r.rows_bad, r.error_ref, json.dumps(r.parents), v)

        return self.store.commit(path, None, "backfill", sorted({(r.batch, r.column) for r in records}), work)

    def column_versions(self, path: str) -> dict[tuple[str, str], int]:
        """The table version at which each (batch, column) pair was last written."""
        out = {}
        for r in self.store.query("select name, valid_from from batches where path = ?", path):
            out[r["name"], ""] = r["valid_from"]
        for r in self.store.query("select batch, column_name, max(table_version) as v from lineage where path = ? group by 1, 2", path):
            out[r["batch"], r["column_name"]] = r["v"]
        return out

    def changes_since(self, path: str, version: int) -> list[tuple[int, str, object]]:
        return [(r["version"], r["kind"], json.loads(r["payload"])) for r in self.store.query("select * from changes where path = ? and version > ? order by version", path, version)]

    def stale_pairs(self, path: str) -> list[tuple[str, str]]:
        """Computed pairs with an ancestor that was written later, or of which a newer version is registered than they were computed with.

        A pair computed by an older version of its own feature is stale too; where its column was renamed it is pending instead.
        """
        snap, at = self.snapshot(path), self.column_versions(path)
        newest = {o: f.version for f in snap.features for o in f.output_names}
        made = {(r["batch"], r["column_name"]): r["v"] for r in self.store.query("select batch, column_name, max(feature_version) as v from lineage where path = ? group by 1, 2", path)}
        old = {pair for pair, v in made.items() if v < newest.get(pair[1], v)}
        out = []
        for (batch, column), state in sorted(snap.status.items()):
            if state != COMPUTED or (batch, column) not in at:
                continue
            above = snap.graph.ancestors(column)
            if (batch, column) in old or any(at.get((batch, k), 0) > at[batch, column] or (batch, k) in old for k in above):
                out.append((batch, column))
        return out

    # ---- system views

    def sys(self, spark: SparkSession, name: str, path: str) -> DataFrame:
        """A system table as a DataFrame."""
        if name == "edges":
            return self.snapshot(path).graph.edges_df(spark)
        if name == "physical_columns":
            rows = [(p.phys_id, stored_name(c), logical_name(c)) for p in self.snapshot(path).physical for c in p.columns]
            return spark.createDataFrame(rows, "phys_id string, phys_name string, logical_name string")
        with self.store.mutex:
            cursor = self.store.connection.execute(SYS[name], (path,))
            fields = [d[0] for d in cursor.description]
            rows = [tuple(r) for r in cursor.fetchall()]
        kinds = [SYS_TYPES.get(f, "string") for f in fields]
        rows = [tuple(None if x is None else float(x) if k == "double" else x for x, k in zip(r, kinds, strict=True)) for r in rows]
        return spark.createDataFrame(rows, ", ".join(f"`{f}` {k}" for f, k in zip(fields, kinds, strict=True)))

    def register_views(self, spark: SparkSession, path: str) -> None:
        """sys_<name> temporary views in the session."""
        for name in [*SYS, "edges", "physical_columns"]:
            self.sys(spark, name, path).createOrReplaceTempView(f"sys_{name}")
