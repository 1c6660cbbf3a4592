"""Plain values that catalog, planner and operators exchange."""

from __future__ import annotations

import json
from collections.abc import Sequence
from dataclasses import asdict, dataclass, field

ID, BATCH = "entity_id", "batch_name"
KEYS = (ID, BATCH)
ABSENT, PENDING, RUNNING, COMPUTED, FAILED, BLOCKED = "ABSENT", "PENDING", "RUNNING", "COMPUTED", "FAILED", "BLOCKED"


class WideTableError(Exception):
    """Base of the engine's errors."""


class ConflictError(WideTableError):
    """Another writer committed first."""


class PlanningError(WideTableError):
    """A request that can't be planned: unknown column, cycle, parent without producer."""


class ColumnLimitError(WideTableError):
    """A physical table would hold more columns than the limit."""


@dataclass(frozen=True)
class Column:
    """A logical column. kind: id, batch, stage or feature."""

    name: str
    type: str
    kind: str = "stage"
    feature: str | None = None
    version: int = 1
    comment: str = ""
    analysis_type: str = ""


@dataclass(frozen=True)
class Output:
    name: str
    type: str
    analysis_type: str = ""
    comment: str = ""


@dataclass(frozen=True)
class FeatureSpec:
    """A registered feature: inputs, outputs, an expression (or a named Python function) and hints.

    mode: cpu_only, gpu_only or all. fn names a function of functions.models for the arrow and gpu lanes; exprs are then
    its arguments.
    lets: (name, expression) pairs that the expressions refer to and that fused features share.
    scope: row, or table for features that need all rows of their inputs.
    """

    name: str
    inputs: tuple[str, ...]
    outputs: tuple[Output, ...]
    exprs: tuple[str, ...] = ()
    mode: str = "cpu_only"
    fn: str | None = None
    table: str | None = None
    model_mb: float = 0.0
    hints: tuple[tuple[str, str], ...] = ()
    parallelism: int | None = None
    where: str | None = None
    lets: tuple[tuple[str, str], ...] = ()
    scope: str = "row"
    version: int = 1

    @classmethod
    def sql(cls, name: str, type: str, expr: str, inputs: Sequence[str], **options) -> FeatureSpec:
        """A feature of one output, written in SQL."""
        return cls(name, tuple(inputs), (Output(name, type),), (expr,), **options)

    @property
    def output_names(self) -> tuple[str, ...]:
        return tuple(o.name for o in self.outputs)

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @classmethod
    def from_json(cls, text: str) -> FeatureSpec:
        d = json.loads(text)
        d |= {"inputs": tuple(d["inputs"]), "exprs": tuple(d["exprs"]), "outputs": tuple(Output(**o) for o in d["outputs"]), "hints": tuple(map(tuple, d["hints"])), "lets": tuple(map(tuple, d["lets"]))}
        return cls(**d)


@dataclass(frozen=True)
class Physical:
    """Files that hold some columns of some id range of one batch. purpose: core, features, view or replica."""

    phys_id: str
    group: str
    path: str
    batch: str
    columns: tuple[str, ...]
    purpose: str = "core"
    rows: int = 0
    bytes: int = 0
    files: int = 0
    lo: int = 0
    hi: int = 1 << 32
    sorted_by: str = ""
    versions: tuple[int, ...] = ()


@dataclass(frozen=True)
class BatchEntry:
    name: str
    rows: int
    duplicates_dropped: int = 0
    source: str = "{}"
    mapping: str = "{}"
    id_strategy: str = "content"
    ingested_at: float = 0.0


@dataclass(frozen=True)
class LineageRecord:
    run_id: str
    batch: str
    column: str
    feature: str
    feature_version: int
    lane: str
    input_versions: str
    finished_at: float
    rows_ok: int
    rows_bad: int
    error_ref: str = ""
    parents: tuple[str, ...] = ()


@dataclass
class EngineConfig:
    """Switches of the engine; each ablation turns one off."""

    governance: bool = True
    fuse: str = "physical"
    guard: str = "record"
    use_index: bool = True
    use_replica: bool = True
    use_views: bool = True
    tuning: str = "adaptive"
    column_limit: int = 1200
    max_shard_columns: int = 300
    headroom: float = 0.9
    max_fused: int = 50
    max_retries: int = 2
    concurrency: int = 4
    max_lag: int = 0
    unit_batches: int = 10
    unit_bytes: int = 1 << 40
    guard_mb: float = 512.0
    write_mb: int = 128
    forced_path: str | None = None
    extra: dict = field(default_factory=dict)
