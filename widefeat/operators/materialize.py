"""Materialised column sets: the columnar replica of hot columns, and pre-joined views.

Both are copies of some columns of a batch with the versions they were made from. A copy serves a query only while
those versions are current (or within the allowed lag); batches whose copy is stale are read from the base tables in
the same query, so answers never depend on which copies exist.
"""

from __future__ import annotations

import json
import time
from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..catalog import CatalogSnapshot
from ..model import BATCH, ID, KEYS, Physical
from ..plans import translate
from .ingest import escaped
from .storage import measured, new_id, write_by_batch


class Materializer:
    """Replica and views of one engine."""

    def __init__(self, engine):
        self.engine = engine

    # ---- what both share

    def _fresh(self, table: str, copies: Sequence[Physical], columns: Sequence[str] | None = None, max_lag: int = 0) -> dict[str, Physical]:
        """By batch the copies whose (wanted) columns are up to date."""
        at = self.engine.catalog.column_versions(table)
        out = {}
        for p in copies:
            made = dict(zip(p.columns, p.versions, strict=True))
            wanted = p.columns if columns is None else [c for c in columns if c in made]
            if all(at.get((p.batch, c), at.get((p.batch, ""), 0)) - made[c] <= max_lag for c in wanted):
                out[p.batch] = p
        return out

    def _build(self, table: str, group: str, purpose: str, columns: Sequence[str], batches: Sequence[str], sort: Sequence[str] = (), options: dict[str, str] | None = None) -> list[Physical]:
        """Copy columns of batches in one job and swap them in for older copies of the same group."""
        engine, spark = self.engine, self.engine.spark
        snap, at = engine.catalog.snapshot(table), engine.catalog.column_versions(table)
        if not batches:
            return []
        columns = [c for c in dict.fromkeys(columns) if c not in KEYS]
        spark.sparkContext.setLocalProperty("spark.scheduler.pool", "governance")
        source = translate.assemble(spark, snap, columns, batches)
        path = f"{engine.root}/{table}/{purpose}/{new_id('m')}"
        try:
            write_by_batch(source.relation, path, [*sort, ID], engine.config.write_mb, options=options)
        finally:
            spark.sparkContext.setLocalProperty("spark.scheduler.pool", None)
        rows = {b.name: b.rows for b in snap.batches}
        add = [measured(spark, Physical(new_id(purpose), group, f"{path}/_b={escaped(spark, b)}", b, tuple(columns), purpose, rows[b], sorted_by=",".join(sort), versions=tuple(at.get((b, c), at.get((b, ""), 0)) for c in columns))) for b in batches if rows[b]]
        old = [p.phys_id for p in snap.physical if p.group == group and p.batch in set(batches)]
        engine.catalog.swap_mapping(table, old, add, purpose)
        return add

    # ---- replica

    def select_hot(self, table: str, k: int = 30) -> list[str]:
        """The columns that aggregate queries use most (ties by name)."""
        log = [json.loads(r["columns"]) for r in self.engine.catalog.store.query("select columns from query_log where path = ? and shape = 'aggregate'", table)]
        counts: dict[str, int] = {}
        for columns in log:
            for c in set(columns) - set(KEYS):
                counts[c] = counts.get(c, 0) + 1
        return [c for c, _ in sorted(counts.items(), key=lambda x: (-x[1], x[0]))[:k]]

    def replica(self, snap: CatalogSnapshot) -> list[Physical]:
        return [p for p in snap.physical if p.purpose == "replica"]

    def sync(self, table: str, columns: Sequence[str] | None = None, batches: Sequence[str] | None = None) -> list[str]:
        """Copy hot columns of batches that have no fresh copy; the batches copied."""
        snap = self.engine.catalog.snapshot(table)
        columns = list(columns or dict.fromkeys(c for p in self.replica(snap) for c in p.columns) or self.select_hot(table))
        fresh = {b for b, p in self._fresh(table, self.replica(snap)).items() if set(columns) <= set(p.columns)}
        todo = [b.name for b in snap.batches if b.name not in fresh and (batches is None or b.name in batches)]
        options = {"parquet.block.size": str(16 << 20)}
        for c in columns[:1]:
            options |= {f"parquet.bloom.filter.enabled#{c}": "true"}
        self._build(table, "replica", "replica", columns, todo, columns[:1] if columns and "struct" not in snap.column(columns[0]).type else (), options)
        return todo

    def eligible(self, need: translate.Requirement, snap: CatalogSnapshot, batches: Sequence[str], max_lag: int = 0) -> tuple[bool, str]:
        """Whether the replica can answer: aggregate shape, all columns there, every batch fresh."""
        if need.shape != "aggregate":
            return False, "not an aggregate"
        wanted = [c for c in need.columns if c not in KEYS]
        fresh = self._fresh(snap.path, self.replica(snap), wanted, max_lag)
        for b in batches:
            if b not in fresh:
                return False, f"{b} is not in sync"
            if missing := set(wanted) - set(fresh[b].columns):
                return False, f"{sorted(missing)} not synced"
        return bool(batches), "all columns synced" if batches else "no batch"

    def replica_relation(self, need: translate.Requirement, snap: CatalogSnapshot, batches: Sequence[str]) -> translate.Assembly:
        copies = [p for p in self.replica(snap) if p.batch in set(batches)]
        out = translate.assemble(self.engine.spark, snap, need.columns, batches, extra=copies)
        out.route, out.reason = "replica", "aggregate on synced columns"
        return out

    def rollup(self, table: str, dims: Sequence[str], measures: Sequence[str]) -> DataFrame:
        """Counts, sums, minima and maxima of measures by dimensions, for further aggregation."""
        snap = self.engine.catalog.snapshot(table)
        rows = translate.assemble(self.engine.spark, snap, [*dims, *measures]).relation
        parts = [f(m).alias(f"{n}_{m}") for m in measures for n, f in (("sum", F.sum), ("min", F.min), ("max", F.max), ("n", F.count))]
        return rows.groupBy(*dims).agg(F.count("*").alias("rows"), *parts)

    # ---- views

    def build_view(self, table: str, columns: Sequence[str], batches: Sequence[str] | None = None, view_id: str | None = None, freq: int = 0) -> str:
        """Pre-join columns and register the view with what it covers."""
        snap = self.engine.catalog.snapshot(table)
        view_id = view_id or new_id("view")
        self._build(table, view_id, "view", columns, [b.name for b in snap.batches if batches is None or b.name in batches])
        self.engine.catalog.store.execute("insert or replace into views values (?, ?, ?, ?, 'FRESH', ?)", table, view_id, json.dumps(sorted(columns)), freq, time.time())
        return view_id

    def views(self, snap: CatalogSnapshot) -> dict[str, list[Physical]]:
        out: dict[str, list[Physical]] = {}
        for p in snap.physical:
            if p.purpose == "view":
                out.setdefault(p.group, []).append(p)
        return out

    def match(self, need: translate.Requirement, snap: CatalogSnapshot, batches: Sequence[str]) -> translate.Assembly | None:
        """The relation with the view that leaves the fewest joins (then bytes), if that is fewer than without one."""
        base = translate.assemble(self.engine.spark, snap, need.columns, batches)
        best, best_id = None, ""
        wanted = {c for c in need.columns if c not in KEYS}
        for view_id, copies in sorted(self.views(snap).items()):
            if not wanted & set(copies[0].columns):
                continue
            fresh = self._fresh(snap.path, copies, [c for c in copies[0].columns if c in wanted])
            usable = [p for b, p in fresh.items() if b in set(batches)]
            if not usable:
                continue
            with_view = translate.assemble(self.engine.spark, snap, need.columns, batches, extra=usable)
            on_view = translate.assemble(self.engine.spark, snap, need.columns, [p.batch for p in usable], extra=usable)
            if on_view.joins >= base.joins:
                continue
            with_view.route = "view"
            kind = "full" if wanted <= set(copies[0].columns) else "partial"
            stale = len(set(batches)) - len(usable)
            with_view.reason = f"{kind} match of {view_id}, joins {base.joins} to {on_view.joins}" + (f", {stale} batches from base" if stale else "")
            with_view.details |= {"view": view_id, "kind": kind, "joins_before": base.joins, "joins_after": on_view.joins, "compensated": stale}
            rank = (on_view.joins, on_view.bytes)
            if best is None or rank < best[0]:
                best, best_id = (rank, with_view), view_id
        if best is None:
            return None
        self.engine.catalog.store.execute("update views set last_used = ? where path = ? and view_id = ?", time.time(), snap.path, best_id)
        return best[1]

    def refresh(self, table: str, view_id: str) -> list[str]:
        """Copy again the batches of a view that are new or stale."""
        snap = self.engine.catalog.snapshot(table)
        copies = self.views(snap).get(view_id, [])
        if not copies:
            return []
        fresh = self._fresh(table, copies)
        todo = [b.name for b in snap.batches if b.name not in fresh]
        self._build(table, view_id, "view", copies[0].columns, todo)
        return todo

    def drop_view(self, table: str, view_id: str) -> None:
        snap = self.engine.catalog.snapshot(table)
        self.engine.catalog.swap_mapping(table, [p.phys_id for p in self.views(snap).get(view_id, [])], [], "view")
        self.engine.catalog.store.execute("update views set state = 'DROPPED' where path = ? and view_id = ?", table, view_id)


def cooccurrence(log: DataFrame) -> DataFrame:
    """How often two columns occur in one query: (col_a < col_b, freq). log: query_id, columns array<string>."""
    own = F.array_sort(F.array_distinct("columns"))
    pairs = F.flatten(F.transform(own, lambda a: F.transform(F.filter(own, lambda b: b > a), lambda b: F.struct(a.alias("col_a"), b.alias("col_b")))))
    return log.select(F.inline(pairs)).groupBy("col_a", "col_b").agg(F.count("*").alias("freq"))


def candidates(log: DataFrame, homes: dict[str, str], min_freq: int, min_tables: int = 2) -> list[tuple[tuple[str, ...], int]]:
    """Column sets asked for often that span several physical tables; a set inside a larger one adds to it.

    homes: physical table by column. The log is grouped by its column sets before anything comes to the driver.
    """
    own = F.array_sort(F.array_distinct(F.filter("columns", lambda c: ~c.isin(*KEYS))))
    sets = [(tuple(r.columns), r.freq) for r in log.select(own.alias("columns")).groupBy("columns").agg(F.count("*").alias("freq")).collect()]
    merged: list[tuple[tuple[str, ...], int]] = []
    for columns, freq in sorted(sets, key=lambda x: (-len(x[0]), x[0])):
        for i, (larger, n) in enumerate(merged):
            if set(columns) <= set(larger):
                merged[i] = (larger, n + freq)
                break
        else:
            merged.append((columns, freq))
    out = [(c, n) for c, n in merged if n >= min_freq and len({homes[x] for x in c if x in homes}) >= min_tables]
    return sorted(out, key=lambda x: (-x[1], x[0]))
