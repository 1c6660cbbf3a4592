"""Transactional metadata: versions, compare-and-set, locks and a change log.

Everything here is of the size of batches times column groups, never of rows. SQLite keeps it on the driver; any
relational store with the same statements can stand in. Mapping entries carry the interval of versions in which they
hold, so an old layout can be read again.
"""

from __future__ import annotations

import json
import sqlite3
import threading
import time
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from typing import Any

from .model import ConflictError

FOREVER = 1 << 60
SCHEMA = """
create table if not exists tables (path text primary key, version integer, created_at real, props text);
create table if not exists columns (path text, name text, type text, kind text, feature text, version integer, comment text, analysis_type text, valid_from integer, valid_to integer);
create table if not exists groups (path text, group_id text, purpose text, lock_owner text, lock_until real, primary key (path, group_id));
create table if not exists physical (path text, phys_id text, group_id text, location text, batch text, columns text, purpose text, rows integer, bytes integer, files integer, lo integer, hi integer, sorted_by text, versions text, valid_from integer, valid_to integer, changed_at real);
create table if not exists batches (path text, name text, rows integer, duplicates integer, source text, mapping text, id_strategy text, ingested_at real, valid_from integer, primary key (path, name));
create table if not exists features (path text, name text, version integer, spec text, expr_hash text, registered_at real, active integer, valid_from integer);
create table if not exists status (path text, batch text, column_name text, version integer, state text, run_id text, primary key (path, batch, column_name));
create table if not exists lineage (path text, run_id text, batch text, column_name text, feature text, feature_version integer, lane text, input_versions text, finished_at real, rows_ok integer, rows_bad integer, error_ref text, parents text, table_version integer);
create table if not exists runs (run_id text, path text, feature text, batch text, attempt integer, ok integer, cpu_s real, peak_mb real, bytes_in integer, bytes_out integer, rows integer, params text, wall_s real, lane text);
create table if not exists checkpoints (run_id text, unit text, location text, errors_at text, done_at real, primary key (run_id, unit));
create table if not exists writers (path text, group_id text, owner text, until real, primary key (path, group_id, owner));
create table if not exists upkeep (path text, level text, at real, primary key (path, level));
create table if not exists errors (path text, run_id text, location text);
create table if not exists query_log (query_id integer primary key autoincrement, path text, at real, columns text, predicates text, shape text, route text, tables_joined integer, bytes integer, ms real, snapshot_version integer);
create table if not exists views (path text, view_id text, columns text, freq integer, state text, last_used real, primary key (path, view_id));
create table if not exists index_segments (path text, phys_id text, location text, rows integer, version integer);
create table if not exists changes (path text, version integer, kind text, payload text, at real);
"""


class MetaStore:
    """SQLite behind a lock; `db` is a file or :memory:."""

    def __init__(self, db: str = ":memory:"):
        self.connection = sqlite3.connect(db, check_same_thread=False, isolation_level=None, timeout=30)
        self.connection.row_factory = sqlite3.Row
        self.mutex = threading.RLock()
        self.connection.executescript(SCHEMA)

    def query(self, sql: str, *args: Any) -> list[sqlite3.Row]:
        with self.mutex:
            return self.connection.execute(sql, args).fetchall()

    def execute(self, sql: str, *args: Any) -> int:
        with self.mutex:
            return self.connection.execute(sql, args).rowcount

    @contextmanager
    def transaction(self) -> Iterator[None]:
        """All statements inside take effect together or not at all."""
        with self.mutex:
            self.connection.execute("begin immediate")
            try:
                yield
            except BaseException:
                self.connection.execute("rollback")
                raise
            self.connection.execute("commit")

    def version(self, path: str) -> int:
        rows = self.query("select version from tables where path = ?", path)
        if not rows:
            raise KeyError(f"no logical table {path}")
        return rows[0]["version"]

    def commit(self, path: str, expected: int | None, kind: str, payload: Any, work: Callable[[int], None]) -> int:
        """Run `work(new_version)` if the table still has the expected version (None: any), else raise ConflictError."""
        with self.transaction():
            now = self.version(path)
            if expected is not None and now != expected:
                raise ConflictError(f"{path} is at version {now}, not {expected}")
            self.execute("update tables set version = ? where path = ?", now + 1, path)
            work(now + 1)
            self.execute("insert into changes values (?, ?, ?, ?, ?)", path, now + 1, kind, json.dumps(payload), time.time())
        return now + 1

    def try_lock(self, path: str, group: str, owner: str, lease_s: float = 3600) -> bool:
        """Take a group's exclusive lock, if no writer is at work in the group; an expired lease is free again."""
        now = time.time()
        with self.transaction():
            self.execute("delete from writers where until < ?", now)
            if self.query("select 1 from writers where path = ? and group_id = ? and owner <> ?", path, group, owner):
                return False
            self.execute("insert or ignore into groups values (?, ?, '', null, 0)", path, group)
            return self.execute("update groups set lock_owner = ?, lock_until = ? where path = ? and group_id = ? and (lock_owner is null or lock_owner = ? or lock_until < ?)", owner, now + lease_s, path, group, owner, now) == 1

    def unlock(self, path: str, group: str, owner: str) -> None:
        self.execute("update groups set lock_owner = null, lock_until = 0 where path = ? and group_id = ? and lock_owner = ?", path, group, owner)

    @contextmanager
    def writing(self, path: str, group: str, owner: str, lease_s: float = 3600, patience_s: float = 600) -> Iterator[None]:
        """Hold a writer's share of a group: many writers may, the exclusive lock and they exclude each other.

        A writer waits while a layout change is on; a layout change is postponed while writers are at work.
        """
        give_up = time.time() + patience_s
        while True:
            with self.transaction():
                now = time.time()
                if not self.query("select 1 from groups where path = ? and group_id = ? and lock_owner is not null and lock_owner <> ? and lock_until >= ?", path, group, owner, now):
                    self.execute("insert or replace into writers values (?, ?, ?, ?)", path, group, owner, now + lease_s)
                    break
            if now > give_up:
                raise ConflictError(f"{path}/{group} is locked by a layout change")
            time.sleep(0.05)
        try:
            yield
        finally:
            self.execute("delete from writers where path = ? and group_id = ? and owner = ?", path, group, owner)
