"""From a backfill request to fused tasks: closure, levels, lanes, fusion."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

from ..catalog import CatalogSnapshot
from ..model import ABSENT, COMPUTED, FeatureSpec, PlanningError
from .dag import FeatureGraph
from .routing import ClusterLoad, OperatorProfile, choose_lane

Pair = tuple[str, str]


@dataclass(frozen=True)
class FusedTask:
    """Features of one lane and level that read the same, for one batch or several of one shape; `after`: tasks that must be done before."""

    number: int
    batches: tuple[str, ...]
    lane: str
    level: int
    features: tuple[FeatureSpec, ...]
    columns: tuple[str, ...]
    after: tuple[int, ...]

    @property
    def inputs(self) -> tuple[str, ...]:
        """Columns to read: inputs that the task doesn't compute itself."""
        made = {o for f in self.features for o in f.output_names}
        return tuple(dict.fromkeys(i for f in self.features for i in f.inputs if i not in made))


def minimum_closure(graph: FeatureGraph, status: dict[Pair, str], pairs: Iterable[Pair], recompute: bool = False) -> set[Pair]:
    """Targets and ancestors that aren't computed; with recompute the targets themselves in any case."""
    out: set[Pair] = set()
    for batch, column in pairs:
        for c in graph.ancestors(column) | {column}:
            if c not in graph.producers:
                if status.get((batch, c)) == ABSENT and c == column:
                    raise PlanningError(f"{column} of {batch} has no producer")
                if status.get((batch, c)) == ABSENT and column in graph.producers:
                    raise PlanningError(f"{c} of {batch} is absent and has no producer; {column} needs it")
            elif status.get((batch, c)) != COMPUTED or (recompute and c == column):
                out.add((batch, c))
    return out


def plan_tasks(snap: CatalogSnapshot, work: set[Pair], fuse: str = "physical", load: ClusterLoad = ClusterLoad(), max_fused: int = 50) -> list[FusedTask]:
    """Tasks in an order that respects dependencies.

    fuse: off (one feature a task), inputs (same input columns), physical (same physical tables), chain (also dependent
    SQL features of one batch, stacked in one scan).
    """
    graph, groups, lanes = snap.graph, {}, {}
    by_batch: dict[str, set[str]] = {}
    for batch, column in work:
        by_batch.setdefault(batch, set()).add(column)
    for batch in sorted(by_batch):
        columns = by_batch[batch]
        # a feature with several outputs is computed once: all of them belong to it
        columns |= {o for c in columns for o in graph.producers[c].output_names if snap.status.get((batch, o)) != COMPUTED}
        wave: dict[str, int] = {}
        for level, names in enumerate(graph.levels(columns)):
            for spec in dict.fromkeys(graph.producers[c] for c in names):
                lane = "table" if spec.scope == "table" else choose_lane(spec.mode, OperatorProfile.of(spec), load)
                if fuse == "chain":  # dependent SQL features stay in one wave; another lane begins a new one
                    above = [(wave[i], lanes[i]) for i in spec.inputs if i in wave]
                    step = max((w + (not lane == from_lane == "sql") for w, from_lane in above), default=0)
                else:
                    step = level
                for o in spec.output_names:
                    wave[o], lanes[o] = step, lane
                reads = tuple(sorted({p.phys_id for i in spec.inputs for p in snap.resolve(batch, i)} | {f"new:{i}" for i in spec.inputs if (batch, i) in work}))
                reads = (spec.name,) if spec.scope == "table" else reads  # a set feature is a task of its own
                key = (spec.name,) if spec.scope == "table" else {"off": (spec.name,), "inputs": tuple(sorted(spec.inputs)), "physical": reads, "chain": () if lane == "sql" else reads}[fuse]
                groups.setdefault((batch, step, lane, key), []).append(spec)
    tasks: list[FusedTask] = []
    made: dict[Pair, int] = {}
    for (batch, step, lane, _), specs in sorted(groups.items(), key=lambda x: (x[0][0], x[0][1])):
        for i in range(0, len(specs), max_fused):
            part = tuple(specs[i : i + max_fused])
            own = {o for f in part for o in f.output_names}
            after = {made[batch, c] for f in part for c in f.inputs if (batch, c) in made and c not in own}
            task = FusedTask(len(tasks), (batch,), lane, step, part, tuple(sorted(own)), tuple(sorted(after)))
            made |= {(batch, c): task.number for c in own}
            tasks.append(task)
    return tasks


def span_batches(tasks: list[FusedTask]) -> list[FusedTask]:
    """One task for all batches that need the same features in the same lane and step: as many jobs as steps, not batches."""
    groups: dict[tuple, list[FusedTask]] = {}
    for t in tasks:
        groups.setdefault((t.level, t.lane, t.features), []).append(t)
    ordered = sorted(groups.items(), key=lambda x: x[0][0])
    place = {t.number: k for k, (_, ts) in enumerate(ordered) for t in ts}
    return [FusedTask(k, tuple(b for t in ts for b in t.batches), lane, level, features, ts[0].columns, tuple(sorted({place[a] for t in ts for a in t.after}))) for k, ((level, lane, features), ts) in enumerate(ordered)]
