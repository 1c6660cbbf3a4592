"""Resources of a task: rules at first, history once there are two similar runs."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

MB = 1 << 20


@dataclass(frozen=True)
class InputStats:
    partitions: int
    rows: int
    bytes: int
    p99_record: float = 0.0

    @property
    def mean_record(self) -> float:
        return self.bytes / max(1, self.rows)


@dataclass(frozen=True)
class ResourceParams:
    split_mb: float
    worker_mb: float
    batch_rows: int
    parallelism: int
    source: str = "rules"


@dataclass(frozen=True)
class Run:
    feature: str
    bytes: int
    rows: int
    cpu_s: float
    peak_mb: float
    ok: bool = True
    attempt: int = 1
    memory: bool = False


def cold_start(stats: InputStats, model_mb: float = 0.0) -> ResourceParams:
    """128 MB a task, half for each doubling of the mean record above 64 KB; more when there are very many partitions."""
    doublings = max(0, math.ceil(math.log2(max(1.0, stats.mean_record / 65536))))
    split = max(4.0, 128.0 / 2**doublings)
    if stats.partitions > 10_000:
        split = min(512.0, split * math.ceil(stats.partitions / 10_000))
    p99 = max(stats.p99_record, stats.mean_record, 1.0)
    batch = int(min(10_000, max(16, 64 * MB // p99)))
    memory = 384 + 2.5 * model_mb + batch * p99 * 3 / MB
    return ResourceParams(split, memory, batch, max(1, math.ceil(stats.bytes / (split * MB))))


@dataclass
class History:
    """Past runs by feature; similar: the same feature within 16 times the size."""

    runs: list[Run] = field(default_factory=list)
    margin: float = 1.1

    def record(self, run: Run) -> None:
        self.runs.append(run)

    def similar(self, feature: str, size: int) -> list[Run]:
        return [r for r in self.runs if r.feature == feature and 1 / 16 <= r.bytes / max(1, size) <= 16]

    def interpolate(self, feature: str, size: int, what: str) -> float | None:
        """Log-linear between the two nearest sizes, along the nearest slope outside them."""
        points: dict[int, list[float]] = {}
        for r in self.similar(feature, size):
            if r.ok:
                points.setdefault(r.bytes, []).append(getattr(r, what))
        known = sorted((b, sum(v) / len(v)) for b, v in points.items())
        if len(known) < 2:
            return None
        at = next((i for i in range(len(known) - 1) if known[i + 1][0] >= size), len(known) - 2)
        (x0, y0), (x1, y1) = known[at], known[at + 1]
        slope = math.log(max(y1, 1e-9) / max(y0, 1e-9)) / math.log(x1 / x0)
        return max(y0, 1e-9) * (size / x0) ** slope

    def short_of_memory(self, feature: str, size: int) -> bool:
        """Whether the last run of about this size failed for lack of memory."""
        runs = self.similar(feature, size)
        return bool(runs) and not runs[-1].ok and runs[-1].memory

    def floor_mb(self, feature: str, size: int) -> float:
        """Failed runs of no larger size need half as much again."""
        return max([1.5 * r.peak_mb for r in self.similar(feature, size) if not r.ok and r.bytes <= size], default=0.0)


def adapt(feature: str, stats: InputStats, model_mb: float, history: History | None = None) -> ResourceParams:
    """Rules when fewer than two similar runs are known, else history with a margin."""
    rules = cold_start(stats, model_mb)
    peak = history.interpolate(feature, stats.bytes, "peak_mb") if history else None
    floor = history.floor_mb(feature, stats.bytes) if history else 0.0
    if peak is None:
        return ResourceParams(rules.split_mb, max(rules.worker_mb, floor), rules.batch_rows, rules.parallelism, "rules")
    return ResourceParams(rules.split_mb, max(peak * history.margin, floor), rules.batch_rows, rules.parallelism, "history")


def preset(name: str, stats: InputStats, model_mb: float = 0.0) -> ResourceParams:
    """default: what Spark ships; expert: sized by hand from the model and the largest records."""
    if name == "default":
        return ResourceParams(128.0, 384.0, 10_000, max(1, math.ceil(stats.bytes / (128 * MB))), "default")
    p99 = max(stats.p99_record, stats.mean_record, 1.0)
    batch = int(min(4096, max(16, 32 * MB // p99)))
    return ResourceParams(128.0, 256 + 2.2 * model_mb + batch * p99 * 3 / MB, batch, max(1, math.ceil(stats.bytes / (128 * MB))), "expert")


def demand_mb(params: ResourceParams, stats: InputStats, model_mb: float) -> float:
    """What a worker needs: the model, and three copies of the rows in flight."""
    p99 = max(stats.p99_record, stats.mean_record, 1.0)
    return 200 + 2 * model_mb * min(1.0, stats.bytes / (256 * MB)) + params.batch_rows * p99 * 3 / MB


def after_memory_failure(params: ResourceParams) -> ResourceParams:
    return ResourceParams(max(4.0, params.split_mb / 2), params.worker_mb * 1.5, max(16, params.batch_rows // 2), params.parallelism * 2, params.source)
