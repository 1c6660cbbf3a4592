"""Background care of layout: observe, decide, evolve under lock, validate, switch.

Every action rewrites into new files, compares row count and an order-free checksum, and swaps pointers in one
transaction; a running query keeps its snapshot's files until vacuum. Nothing here changes an answer.
"""

from __future__ import annotations

import json
import math
import time
from collections.abc import Callable, Iterable, Sequence
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..catalog import CatalogSnapshot, logical_name
from ..metrics import governance_share
from ..model import ID, KEYS, ColumnLimitError, Physical, WideTableError
from ..plans import translate
from .storage import data_files, delete, measured, new_id, range_of, read_physical, write_by_batch

MB = 1 << 20


# ---- rules (no Spark)


def compaction_due(files: int, small_files: int, max_files: int = 1000, small_ratio: float = 0.5) -> bool:
    """Over max_files, or more than half of the files small."""
    return files > max_files or (files > 0 and small_files / files > small_ratio)


def tier(last_access_s: float, now_s: float, last_light_s: float = 0, last_deep_s: float = 0, hot_days: float = 7) -> str | None:
    """light: daily, for what was used lately; deep: weekly, for the rest."""
    day = 86_400
    if now_s - last_access_s <= hot_days * day:
        return "light" if now_s - last_light_s >= day else None
    return "deep" if now_s - last_deep_s >= 7 * day else None


def split_ranges(rows: int, size: int, max_rows: int = 500_000_000, max_bytes: int = 500 * 10**9, lo: int = 0, hi: int = 1 << 32) -> list[tuple[int, int]]:
    """Equal id ranges, a power of two of them, so that none is over a limit if ids are even."""
    need = max(rows / max_rows, size / max_bytes, 1)
    n = 1 << max(0, math.ceil(math.log2(need)))
    return [(lo + (hi - lo) * i // n, lo + (hi - lo) * (i + 1) // n) for i in range(n)]


def access_frequency(log: Iterable[tuple[float, Sequence[str]]], now_s: float, half_life_days: float = 30) -> dict[str, float]:
    """Uses by column, older ones counting less."""
    out: dict[str, float] = {}
    for at, columns in log:
        for c in set(columns):
            out[c] = out.get(c, 0.0) + 0.5 ** ((now_s - at) / 86_400 / half_life_days)
    return out


def assign_shards(columns: Sequence[str], core: Sequence[str], frequency: dict[str, float], limit: int = 1200, headroom: float = 0.9, max_shard: int = 300) -> list[list[str]]:
    """The main table's columns first (core, then hot ones), then shards of the coldest; one list if all fit."""
    target = int(limit * headroom)
    movable = sorted((c for c in columns if c not in set(core)), key=lambda c: (-frequency.get(c, 0.0), c))
    if len(columns) <= target:
        return [[*core, *movable]]
    main = min(max_shard, target) - len(core)
    out = [[*core, *movable[: max(0, main)]]]
    rest = movable[max(0, main) :]
    return out + [rest[i : i + max_shard] for i in range(0, len(rest), max_shard)]


# ---- observing


def storage_report(engine, table: str, small_mb: float = 64) -> DataFrame:
    """A row a physical table: files, small ones, bytes, skew (largest to median file); folders are listed by 32 threads."""

    def one(p: Physical) -> tuple:
        sizes = sorted(n for _, n in data_files(engine.spark, p.path))
        median = sizes[len(sizes) // 2] if sizes else 0
        return p.phys_id, p.group, p.batch, len(p.columns), p.rows, len(sizes), sum(n < small_mb * MB for n in sizes), sum(sizes), float(sizes[-1] / median) if median else 0.0

    with ThreadPoolExecutor(32) as pool:
        rows = list(pool.map(one, engine.catalog.snapshot(table).physical))
    return engine.spark.createDataFrame(rows, "phys_id string, group_id string, batch_name string, columns long, rows long, files long, small_files long, bytes long, skew double")


def query_report(engine, table: str) -> DataFrame:
    """Uses by column."""
    rows = [(r["query_id"], json.loads(r["columns"]), r["tables_joined"]) for r in engine.catalog.store.query("select * from query_log where path = ?", table)]
    log = engine.spark.createDataFrame(rows, "query_id long, columns array<string>, tables_joined long")
    return log.select(F.explode("columns").alias("column_name")).groupBy("column_name").agg(F.count("*").alias("uses"))


@dataclass(frozen=True)
class Action:
    kind: str
    target: str
    detail: str = ""
    benefit: float = 0.0


@dataclass(frozen=True)
class Policy:
    max_files: int = 1000
    small_mb: float = 64
    small_ratio: float = 0.5
    target_mb: int = 512
    max_rows: int = 500_000_000
    max_bytes: int = 500 * 10**9
    column_limit: int = 1200
    headroom: float = 0.9
    max_shard: int = 300
    view_min_freq: float = 0.05
    min_batch_files: int = 2
    merge_below: float = 0.25
    view_idle_days: float = 30


def decide(snap: CatalogSnapshot, storage: Sequence, policy: Policy, views: Sequence[tuple[tuple[str, ...], int]] = (), stale_views: Sequence[str] = (), stale_replica: bool = False, idle_views: Sequence[str] = ()) -> list[Action]:
    """Ordered actions from observations."""
    out = []
    for s in storage:
        if s.rows > policy.max_rows or s.bytes > policy.max_bytes:
            out.append(Action("row_split", s.phys_id, "", float(s.rows)))
        elif s.files >= policy.min_batch_files and compaction_due(s.files, s.small_files, policy.max_files, policy.small_ratio):
            out.append(Action("compact", s.phys_id, "", float(s.files)))
        if s.columns + len(KEYS) > policy.column_limit * policy.headroom:
            out.append(Action("column_split", s.phys_id, "", float(s.columns)))
    small: dict[str, list] = {}
    for s in storage:
        if s.group_id == "features":
            small.setdefault(s.batch_name, []).append(s)
    out += [Action("merge_shards", b, "", float(len(ss))) for b, ss in sorted(small.items()) if 2 <= len(ss) and sum(x.columns for x in ss) <= policy.max_shard]
    ranges: dict[tuple, list[Physical]] = {}
    for p in snap.physical:
        if p.purpose in ("core", "features"):
            ranges.setdefault((p.group, p.batch, p.columns), []).append(p)
    for (group, batch, _), parts in sorted(ranges.items(), key=lambda x: x[0][:2]):
        # id ranges that have become small together are put back, well below the limits so that they aren't split again
        if len(parts) > 1 and sum(p.rows for p in parts) <= policy.merge_below * policy.max_rows and sum(p.bytes for p in parts) <= policy.merge_below * policy.max_bytes:
            out.append(Action("merge_ranges", batch, group, float(len(parts))))
    out += [Action("drop_view", v, "", 1.0) for v in idle_views]
    out += [Action("build_view", ",".join(c), "", float(n)) for c, n in views]
    out += [Action("refresh_view", v, "", 1.0) for v in stale_views if v not in set(idle_views)]
    out += [Action("sync_replica", snap.path, "", 1.0)] if stale_replica else []
    order = {"row_split": 0, "merge_ranges": 1, "column_split": 2, "merge_shards": 3, "compact": 4, "drop_view": 5, "refresh_view": 6, "sync_replica": 7, "build_view": 8}
    return sorted(out, key=lambda a: (order[a.kind], -a.benefit, a.target))


# ---- evolving


class ValidationError(WideTableError):
    """Rewritten files don't hold what the old ones held."""


class Governor:
    """Layout changes of one engine."""

    def __init__(self, engine, policy: Policy | None = None):
        self.engine, self.policy = engine, policy or Policy()
        self.seconds = 0.0

    def evolve(self, table: str, group: str, old: Sequence[Physical], work: Callable[[str], list[Physical]], owner: str | None = None, fault: Callable[[str], None] | None = None, compare: Sequence[str] | None = None) -> str:
        """prepare (lock), execute (rewrite to staging), validate, commit. COMMITTED, POSTPONED or ROLLED_BACK."""
        engine, store = self.engine, self.engine.catalog.store
        owner, began = owner or new_id("governor"), time.time()
        if not store.try_lock(table, group, owner):
            return "POSTPONED"
        staging = f"{engine.root}/{table}/{group}/{new_id('g')}"
        try:
            snap = engine.catalog.snapshot(table)
            engine.spark.sparkContext.setLocalProperty("spark.scheduler.pool", "governance")
            new = work(staging)
            if fault:
                fault("executed")
            columns = list(compare) if compare is not None else list(dict.fromkeys(logical_name(c) for p in old for c in p.columns))
            self.validate(snap, old, new, columns)
            if fault:
                fault("validated")
            engine.catalog.swap_mapping(table, [p.phys_id for p in old], new, "layout", None)
            return "COMMITTED"
        except Exception as e:
            delete(engine.spark, staging)
            if isinstance(e, (ColumnLimitError, ValidationError)):
                raise
            return f"ROLLED_BACK: {type(e).__name__}: {e}"[:300]
        finally:
            engine.spark.sparkContext.setLocalProperty("spark.scheduler.pool", None)
            store.unlock(table, group, owner)
            self.seconds += time.time() - began

    def validate(self, snap: CatalogSnapshot, old: Sequence[Physical], new: Sequence[Physical], columns: Sequence[str]) -> None:
        """Rows and order-free checksum of every column with the keys, before and after."""
        before, after = (self.checksums(snap, tables, columns) for tables in (old, new))
        for c in before:
            if before[c] != after[c]:
                raise ValidationError(f"{c or 'keys'}: rows and checksum {before[c]} became {after[c]}")

    def checksums(self, snap: CatalogSnapshot, tables: Sequence[Physical], columns: Sequence[str]) -> dict[str, tuple[int, int]]:
        """By column the rows and the sum of hashes; one scan a column set, 200 columns at a time."""
        types, out = {c.name: c.type for c in snap.columns}, {c: (0, 0) for c in columns}
        layouts: dict[tuple, list[Physical]] = {}
        for p in tables:
            layouts.setdefault(p.columns, []).append(p)
        for stored, ps in layouts.items():
            have = [c for c in map(logical_name, stored) if c in out]
            for i in range(0, len(have), 200):
                part = have[i : i + 200]
                sums = [F.sum(F.xxhash64(*KEYS, F.to_json(F.struct(c)) if "map<" in types[c] else F.col(c)).cast("decimal(38,0)")).alias(f"s{k}") for k, c in enumerate(part)]
                r = read_physical(self.engine.spark, ps, types, part).agg(F.count("*").alias("n"), *sums).first()
                for k, c in enumerate(part):
                    out[c] = (out[c][0] + r.n, out[c][1] + int(r[f"s{k}"] or 0))
        return out

    def _read(self, snap: CatalogSnapshot, p: Physical) -> DataFrame:
        types = {c.name: c.type for c in snap.columns}
        return read_physical(self.engine.spark, [p], types, [logical_name(c) for c in p.columns])

    def compact(self, table: str, phys_id: str, level: str = "deep", **options) -> str:
        """deep: all rows sorted by id into files of the target size; light: small files put together as they are."""
        snap = self.engine.catalog.snapshot(table)
        p = next(x for x in snap.physical if x.phys_id == phys_id)
        n = max(1, round(p.bytes / (self.policy.target_mb * MB)))

        def work(staging: str) -> list[Physical]:
            rows = self._read(snap, p)
            if level == "deep":
                rows = rows.repartitionByRange(n, ID).sortWithinPartitions(ID)
            else:
                rows = rows.coalesce(n)
            rows.write.option("compression", "zstd").parquet(staging)
            return [measured(self.engine.spark, replace(p, phys_id=new_id("c"), path=staging, columns=tuple(map(logical_name, p.columns)), sorted_by=ID if level == "deep" else ""))]

        return self.evolve(table, p.group, [p], work, **options)

    def level(self, table: str, now: float | None = None) -> str | None:
        """light, daily, for a table read or written within a week; deep, weekly, for one at rest; None if it isn't its turn."""
        store = self.engine.catalog.store
        seen = store.query("select max(at) as q, (select max(ingested_at) from batches where path = ?) as b from query_log where path = ?", table, table)[0]
        last = {r["level"]: r["at"] for r in store.query("select level, at from upkeep where path = ?", table)}
        return tier(max(seen["q"] or 0, seen["b"] or 0), now or time.time(), last.get("light", 0), last.get("deep", 0))

    def row_split(self, table: str, phys_id: str, **options) -> str:
        """Deal a table's rows into id ranges, so that each is under the limits."""
        snap = self.engine.catalog.snapshot(table)
        p = next(x for x in snap.physical if x.phys_id == phys_id)
        ranges = split_ranges(p.rows, p.bytes, self.policy.max_rows, self.policy.max_bytes, p.lo, p.hi)

        def work(staging: str) -> list[Physical]:
            rows = self._read(snap, p).withColumn("_at", range_of())
            width = (p.hi - p.lo) // len(ranges)
            part = F.least(((F.col("_at") - p.lo) / width).cast("int"), F.lit(len(ranges) - 1))
            write_by_batch(rows.withColumn("_r", part).drop("_at"), staging, [ID], self.policy.target_mb, "_r", "_r")
            counts = {r._r: r.n for r in self.engine.spark.read.parquet(staging).groupBy("_r").agg(F.count("*").alias("n")).collect()}
            return [measured(self.engine.spark, replace(p, phys_id=new_id("r"), path=f"{staging}/_r={i}", columns=tuple(map(logical_name, p.columns)), lo=lo, hi=hi, rows=counts[i], sorted_by=ID)) for i, (lo, hi) in enumerate(ranges) if i in counts]

        return self.evolve(table, p.group, [p], work, **options)

    def merge_shards(self, table: str, batch: str, limit: int | None = None, **options) -> str:
        """Put a batch's feature shards of whole range side by side into one."""
        snap = self.engine.catalog.snapshot(table)
        old = [p for p in snap.physical if p.batch == batch and p.purpose == "features" and (p.lo, p.hi) == (0, 1 << 32)]
        columns = [logical_name(c) for p in old for c in p.columns]
        if len(columns) + len(KEYS) > (limit or self.policy.column_limit):
            raise ColumnLimitError(f"{len(columns)} columns in one table")

        def work(staging: str) -> list[Physical]:
            rows = translate.assemble(self.engine.spark, snap, columns, [batch]).relation
            rows.sortWithinPartitions(ID).write.option("compression", "zstd").parquet(staging)
            return [measured(self.engine.spark, Physical(new_id("features"), "features", staging, batch, tuple(columns), "features", old[0].rows, sorted_by=ID))]

        return self.evolve(table, "features", old, work, **options) if len(old) > 1 else "NOTHING"

    def column_split(self, table: str, phys_id: str, **options) -> str:
        """Move the columns used least into shards of their own; hot ones stay together."""
        snap, engine = self.engine.catalog.snapshot(table), self.engine
        p = next(x for x in snap.physical if x.phys_id == phys_id)
        log = [(r["at"], json.loads(r["columns"])) for r in engine.catalog.store.query("select at, columns from query_log where path = ?", table)]
        columns = [logical_name(c) for c in p.columns]
        core = [c for c in columns if snap.column(c).kind == "stage"]
        shards = assign_shards(columns, core, access_frequency(log, time.time()), self.policy.column_limit, self.policy.headroom, self.policy.max_shard)

        def work(staging: str) -> list[Physical]:
            out = []
            # one column-pruned scan a shard: Parquet reads each column chunk once in all
            for i, cs in enumerate(shards):
                self._read(snap, p).select(*KEYS, *cs).write.option("compression", "zstd").parquet(f"{staging}/{i}")
                out.append(measured(engine.spark, replace(p, phys_id=new_id("k"), path=f"{staging}/{i}", columns=tuple(cs), group=p.group if i == 0 else "features", purpose=p.purpose if i == 0 else "features")))
            return out

        return self.evolve(table, p.group, [p], work, **options) if len(shards) > 1 else "NOTHING"

    def merge_batch_files(self, table: str, group: str, batch: str, **options) -> str:
        """Put small id-range parts of one batch and column set together again."""
        snap = self.engine.catalog.snapshot(table)
        old = [p for p in snap.physical if p.batch == batch and p.group == group]
        if len(old) < 2 or len({p.columns for p in old}) > 1:
            return "NOTHING"
        types = {c.name: c.type for c in snap.columns}

        def work(staging: str) -> list[Physical]:
            rows = read_physical(self.engine.spark, old, types, [logical_name(c) for c in old[0].columns])
            rows.repartitionByRange(max(1, round(sum(p.bytes for p in old) / (self.policy.target_mb * MB))), ID).sortWithinPartitions(ID).write.option("compression", "zstd").parquet(staging)
            return [measured(self.engine.spark, replace(old[0], phys_id=new_id("m"), path=staging, lo=min(p.lo for p in old), hi=max(p.hi for p in old), rows=sum(p.rows for p in old), sorted_by=ID))]

        return self.evolve(table, group, old, work, **options)

    def vacuum(self, table: str, min_age_s: float = 3600) -> int:
        """Delete files that only snapshots older than min_age_s can need."""
        gone = self.engine.catalog.dropped_physical(table, min_age_s)
        for path in {p.path for p in gone}:
            delete(self.engine.spark, path)
        return len(gone)

    def accelerators(self, table: str, snap: CatalogSnapshot, now: float) -> tuple[list[str], bool, list[str]]:
        """Views with a batch that is missing or stale, whether the replica has one, and views that nobody has used for long."""
        m, batches = self.engine.materializer, {b.name for b in snap.batches if b.rows}
        views = m.views(snap)
        stale = sorted(v for v, copies in views.items() if batches - set(m._fresh(table, copies)))
        replica = m.replica(snap)
        used = {r["view_id"]: r["last_used"] for r in self.engine.catalog.store.query("select view_id, last_used from views where path = ?", table)}
        idle = sorted(v for v in views if now - (used.get(v) or 0) > self.policy.view_idle_days * 86_400)
        return stale, bool(replica) and bool(batches - set(m._fresh(table, replica))), idle

    def cycle(self, table: str, budget_s: float | None = None, views: bool = False, share: float | None = None, now: float | None = None) -> list[tuple[str, str, str]]:
        """One round of observing, deciding and acting: (kind, target, outcome).

        budget_s: seconds for this round; share: the most of all executors' run time that governance may have had so far.
        What is over a budget is deferred. Compaction keeps to its tier's turn, which is remembered.
        """
        if not self.engine.config.governance:
            return []
        began, now, done = time.time(), now or time.time(), []
        store, snap = self.engine.catalog.store, self.engine.catalog.snapshot(table)
        wanted = []
        if views:
            from .materialize import candidates

            log = self.engine.query_log(table)
            n = log.count()
            homes = {logical_name(c): p.group if p.purpose == "core" else p.phys_id for p in snap.physical if p.purpose in ("core", "features") and p.batch == (snap.batches[0].name if snap.batches else "") for c in p.columns}
            have = {frozenset(p.columns) for p in snap.physical if p.purpose == "view"}
            wanted = [x for x in candidates(log, homes, max(1, math.ceil(self.policy.view_min_freq * n))) if frozenset(x[0]) not in have]
        stale, replica, idle = self.accelerators(table, snap, now)
        level = self.level(table, now)
        m = self.engine.materializer
        act = {
            "compact": lambda a: self.compact(table, a.target, level), "row_split": lambda a: self.row_split(table, a.target), "column_split": lambda a: self.column_split(table, a.target),
            "merge_shards": lambda a: self.merge_shards(table, a.target), "merge_ranges": lambda a: self.merge_batch_files(table, a.detail, a.target), "build_view": lambda a: m.build_view(table, a.target.split(",")),
            "refresh_view": lambda a: ",".join(m.refresh(table, a.target)), "sync_replica": lambda a: ",".join(m.sync(table)), "drop_view": lambda a: m.drop_view(table, a.target) or "DROPPED",
        }
        compacted = False
        for a in decide(snap, storage_report(self.engine, table, self.policy.small_mb).collect(), self.policy, wanted, stale, replica, idle):
            if budget_s is not None and time.time() - began > budget_s or share is not None and governance_share(self.engine.spark) > share:
                done.append((a.kind, a.target, "DEFERRED"))
                continue
            if a.kind == "compact" and level is None:
                done.append((a.kind, a.target, "NOT_DUE"))
                continue
            live = {p.phys_id for p in self.engine.catalog.snapshot(table).physical}
            out = act[a.kind](a) if a.kind not in ("compact", "row_split", "column_split") or a.target in live else "SUPERSEDED"
            compacted |= a.kind == "compact" and out == "COMMITTED"
            done.append((a.kind, a.target, out))
        if compacted:
            store.execute("insert or replace into upkeep values (?, ?, ?)", table, level, now)
        return done
