"""From SQL on the logical table to a relation over the fewest physical tables.

The user's text is analysed against a stub with the logical schema. Which columns it needs, which batches and ids it
can touch and what shape it has are read from the optimised plan; a relation is then assembled from that and takes
the stub's place. All rewriting happens before Catalyst sees the real relation.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator, Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..catalog import CatalogSnapshot, logical_name
from ..model import BATCH, ID, KEYS, Physical
from ..operators.storage import read_physical

HASH_SPACE = 1 << 32
MARK = "wide_table"


@dataclass(frozen=True)
class Requirement:
    """What a query needs of one logical table. ids: None, or the only ids it can return."""

    columns: tuple[str, ...]
    batch_predicates: tuple[str, ...] = ()
    ids: tuple[str, ...] | None = None
    shape: str = "export"
    predicates: tuple[str, ...] = ()


@dataclass
class Assembly:
    """A relation and what it costs."""

    relation: DataFrame
    route: str
    reason: str
    joins: int = 0
    tables: tuple[str, ...] = ()
    bytes: int = 0
    batches: tuple[str, ...] = ()
    details: dict = field(default_factory=dict)


def stub(spark: SparkSession, snap: CatalogSnapshot) -> DataFrame:
    """An empty relation of the logical schema that the optimizer can't fold away; its columns say of which table they are."""
    marked = T.StructType([T.StructField(f.name, f.dataType, f.nullable, {MARK: snap.path}) for f in snap.schema])
    return spark.createDataFrame(spark.sparkContext.emptyRDD(), marked)


def named_in(text: str, paths: Iterable[str]) -> list[str]:
    """The logical tables whose names stand in the text as words of their own."""
    return [p for p in paths if re.search(rf"(?<![\w.]){re.escape(p)}(?!\w)", text)]


def _seq(x) -> Iterator:
    for i in range(x.size()):
        yield x.apply(i)


def _nodes(plan) -> Iterator:
    """All nodes of a plan, those of subqueries too."""
    yield plan
    for c in _seq(plan.children()):
        yield from _nodes(c)
    for s in _seq(plan.subqueries()):
        yield from _nodes(s)


def _conjuncts(expr) -> Iterator:
    if expr.nodeName() == "And":
        yield from _conjuncts(expr.left())
        yield from _conjuncts(expr.right())
    else:
        yield expr


def _straight_leaf(plan):
    """The stub leaf that only projections and filters part from a filter: what it rejects there can't matter above."""
    while plan.nodeName() in ("Project", "Filter"):
        plan = plan.children().apply(0)
    return plan if plan.nodeName() == "LogicalRDD" else None


ID_EQUALS = re.compile(rf"^\(?(?:\w+\.)*`?{ID}`? = '([^']*)'\)?$")
ID_IN = re.compile(rf"^\(?(?:\w+\.)*`?{ID}`? IN \((.*)\)\)?$")


def required(query: DataFrame, tables: dict[str, CatalogSnapshot]) -> dict[str, Requirement]:
    """Requirements by table name. Leaves are told apart by the mark of their columns; several uses of a table are united."""
    plan = query._jdf.queryExecution().optimizedPlan()
    nodes = list(_nodes(plan))
    leaves = {id(n): n for n in nodes if n.nodeName() == "LogicalRDD"}
    used: set[int] = {a.exprId().id() for a in _seq(plan.output())}
    for n in nodes:
        if n.nodeName() != "LogicalRDD":
            used |= {a.exprId().id() for a in _seq(n.references().toSeq())}
    shape = "aggregate" if any(n.nodeName() == "Aggregate" for n in nodes) else "export"
    out: dict[str, Requirement] = {}
    filters: dict[int, list[tuple[str, set[str]]]] = {}
    for n in nodes:
        if n.nodeName() == "Filter":
            leaf = _straight_leaf(n.child())
            below = [] if leaf is None else [leaf]
            for c in _conjuncts(n.condition()):
                at = {a.exprId().id(): a.name() for a in _seq(c.references().toSeq())}
                for leaf in below:
                    own = {a.exprId().id() for a in _seq(leaf.output())}
                    if set(at) <= own and "subquery" not in c.sql().lower():
                        filters.setdefault(min(own), []).append((c.sql(), set(at.values())))
    for leaf in leaves.values():
        attributes = {a.exprId().id(): a.name() for a in _seq(leaf.output())}
        table = next((a.metadata().getString(MARK) for a in _seq(leaf.output()) if a.metadata().contains(MARK)), None)
        if table not in tables:
            continue
        columns = {name for i, name in attributes.items() if i in used}
        own = list(dict.fromkeys((sql, tuple(sorted(cols))) for sql, cols in filters.get(min(attributes), [])))
        batch = tuple(unqualified(sql) for sql, cols in own if cols == (BATCH,))
        ids: tuple[str, ...] | None = None
        for sql, cols in own:
            if cols == (ID,):
                if m := ID_EQUALS.match(sql):
                    ids = (m[1],)
                elif m := ID_IN.match(sql):
                    ids = tuple(re.findall(r"'([^']*)'", m[1]))
        predicates = tuple(unqualified(sql) for sql, _ in own)
        new = Requirement(tuple(sorted(columns)), batch, ids, "point" if ids else shape, predicates)
        if table in out:
            old = out[table]
            both = tuple(p for p in old.batch_predicates if p in new.batch_predicates)
            either = tuple(sorted({*old.ids, *new.ids})) if old.ids and new.ids else None
            new = Requirement(tuple(sorted({*old.columns, *new.columns})), both, either, "point" if either else shape, tuple(p for p in old.predicates if p in new.predicates))
        out[table] = new
    return out


def unqualified(sql: str) -> str:
    return re.sub(r"\b\w+\.(?=[\w`])", "", sql) if not re.search(r"'[^']*\.[^']*'", sql) else sql


def prune_batches(spark: SparkSession, snap: CatalogSnapshot, predicates: Iterable[str]) -> tuple[str, ...]:
    names = [b.name for b in snap.batches]
    for p in predicates:
        kept = set(snap.batches_matching(spark, p))
        names = [n for n in names if n in kept]
    return tuple(names)


def hash_place(entity_id: str) -> int:
    import hashlib

    return int(hashlib.md5(entity_id.encode()).hexdigest()[:8], 16)


def prune_ranges(tables: Sequence[Physical], ids: Sequence[str] | None) -> list[Physical]:
    """Of id-range parts only those that can hold the ids."""
    if ids is None:
        return list(tables)
    places = [hash_place(i) for i in ids]
    return [t for t in tables if any(t.lo <= x < t.hi for x in places)]


def assemble(spark: SparkSession, snap: CatalogSnapshot, columns: Sequence[str], batches: Sequence[str] | None = None, ids: Sequence[str] | None = None, extra: Sequence[Physical] = (), few_files: bool = False) -> Assembly:
    """The logical rows of some columns: per layout one multi-path scan a shard and left joins, then a union of layouts.

    Shards without a wanted column aren't read; batches of one layout share scans, so the plan grows with layouts, not
    batches. extra: other tables (views) that may serve columns instead of base shards, by batch. few_files: the index has
    narrowed everything to the files of a few ids; their shards are then read by one task and folded by key, without joins.
    """
    types = {c.name: c.type for c in snap.columns}
    wanted = [c.name for c in snap.columns if c.name in set(columns) and c.name not in KEYS]
    batches = [b.name for b in snap.batches] if batches is None else list(batches)
    core = {b: [p for p in snap.physical if p.batch == b and p.purpose == "core" and p.group == "core"] for b in batches}
    views = {p.batch: p for p in extra}
    layouts: dict[tuple, list[tuple[str, list[list[Physical]]]]] = {}
    for b in batches:
        shards: list[tuple[tuple[str, ...], list[Physical]]] = []
        left = set(wanted)
        main = core[b]
        if b in views:
            view = views[b]
            shards.append((tuple(c for c in wanted if c in set(map(logical_name, view.columns))), [view]))
            left -= set(shards[0][0])
        else:
            have = {logical_name(c) for c in main[0].columns} if main else set()
            shards.append((tuple(c for c in wanted if c in have), main))
            left -= have
        groups: dict[tuple, list[str]] = {}
        for c in wanted:
            if c in left and (found := snap.resolve(b, c)):
                groups.setdefault(tuple((p.phys_id, p.path) for p in found), []).append(c)
        by_place = {(p.phys_id, p.path): p for p in snap.physical}  # the index leaves a table once for each of its files
        for places, cs in sorted(groups.items(), key=lambda x: x[1]):
            shards.append((tuple(cs), [by_place[i] for i in places]))
        parts = [prune_ranges(tables, ids) for _, tables in shards]
        if not parts[0]:
            continue
        key = (b in views, *((cs, tuple(stored_layout(t[0], cs)) if t else ()) for (cs, _), t in zip(shards, parts, strict=True)))
        layouts.setdefault(key, []).append((b, parts))
    branches, joins, used = [], 0, []
    if few_files and any(len(key) > 2 for key in layouts):
        parts, used = [], []
        for key, members in layouts.items():
            for k, (cs, _) in enumerate(key[1:]):
                if tables := [p for _, of_batch in members for p in of_batch[k]]:
                    used += tables
                    scan = read_physical(spark, tables, types, cs).where(F.col(ID).isin(list(ids or ())))
                    parts.append(scan.selectExpr(*KEYS, f"{k == 0} as _row".lower(), *(f"`{c}`" if c in cs else f"cast(null as {types[c]}) as `{c}`" for c in wanted)))
        first = ", ".join([f"first(`{c}`, true) as `{c}`" for c in wanted])
        folded = reduce(DataFrame.union, parts).coalesce(1).groupBy(*KEYS).agg(F.expr(f"struct({first or 'null as _none'}) as _all"), F.expr("max(_row) as _row")).where("_row")
        folded = folded.selectExpr(*KEYS, *(f"_all.`{c}` as `{c}`" for c in wanted))
        return Assembly(folded, "base", "files of a few ids", 0, tuple(p.phys_id for p in used), sum(p.bytes for p in used), tuple(batches), {"layouts": len(layouts), "joins_total": 0})
    for key, members in layouts.items():
        relation = None
        for k, (cs, _) in enumerate(key[1:]):
            tables = [p for _, parts in members for p in parts[k]]
            if not tables:
                continue
            used += tables
            scan = read_physical(spark, tables, types, cs)
            if ids is not None:
                scan = scan.where(F.col(ID).isin(list(ids)))
            if relation is None:
                relation = scan
            else:
                relation = relation.join(scan, list(KEYS), "left")
                joins += 1
        present = set(relation.columns)
        branches.append(relation.select(*KEYS, *(F.col(c) if c in present else F.lit(None).cast(types[c]).alias(c) for c in wanted)))
    if not branches:
        relation = spark.createDataFrame([], ", ".join([f"{k} string" for k in KEYS] + [f"`{c}` {types[c]}" for c in wanted]))
    else:
        relation = branches[0]
        for b in branches[1:]:
            relation = relation.unionByName(b)
    return Assembly(relation, "base", "base tables", max([len(k) - 2 for k in layouts], default=0), tuple(p.phys_id for p in used), sum(p.bytes for p in used), tuple(batches), {"layouts": len(layouts), "joins_total": joins})


def padded(relation: DataFrame, snap: CatalogSnapshot) -> DataFrame:
    """`relation` with all logical columns; those that the optimised query has no use for, but its text may name, are NULL."""
    types, have = {c.name: c.type for c in snap.columns}, set(relation.columns)
    return relation.select(*(F.col(f"`{c}`") if c in have else F.lit(None).cast(t).alias(c) for c, t in types.items()))


def stored_layout(p: Physical, columns: Sequence[str]) -> Iterator[str]:
    stored = {logical_name(c): c for c in p.columns}
    return (stored[c] for c in columns)


SESSION_KEYS = ("spark.sql.shuffle.partitions", "spark.sql.session.timeZone", "spark.sql.adaptive.enabled", "spark.sql.sources.partitionOverwriteMode")


def own_session(spark: SparkSession, settings: dict[str, str] | None = None) -> SparkSession:
    """A session with the settings that matter to plans, and some of its own."""
    session = spark.newSession()
    for key in SESSION_KEYS:
        session.conf.set(key, spark.conf.get(key))
    for key, value in (settings or {}).items():
        session.conf.set(key, value)
    return session


def bind(spark: SparkSession, relations: dict[str, DataFrame], text: str, register=None) -> DataFrame:
    """Run the text with the relations under the logical names, in a session of its own."""
    session = own_session(spark)
    for name, relation in relations.items():
        in_session(session, relation).createOrReplaceTempView(name)
    if register:
        register(session)
    return session.sql(text)


def in_session(session: SparkSession, df: DataFrame) -> DataFrame:
    """The same logical plan as a DataFrame of another session."""
    jvm = session.sparkContext._jvm
    moved = jvm.org.apache.spark.sql.classic.Dataset.ofRows(session._jsparkSession, df._jdf.logicalPlan())
    return DataFrame(moved, session)
