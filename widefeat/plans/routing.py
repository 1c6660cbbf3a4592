"""Which lane a feature runs in: sql (Catalyst), arrow (vectorised Python) or gpu (simulated where there is none)."""

from __future__ import annotations

from dataclasses import dataclass

from ..model import FeatureSpec


@dataclass(frozen=True)
class OperatorProfile:
    has_model: bool = False
    model_mb: float = 0.0
    native: bool = True

    @classmethod
    def of(cls, spec: FeatureSpec) -> OperatorProfile:
        return cls(spec.model_mb > 0, spec.model_mb, spec.fn is None)


@dataclass(frozen=True)
class ClusterLoad:
    """Shares of busy slots, 0 to 1; gpu None: there is none."""

    cpu: float = 0.0
    gpu: float | None = 0.0


SMALL_MODEL_MB, BUSY = 1024.0, 0.9


def choose_lane(mode: str, profile: OperatorProfile, load: ClusterLoad = ClusterLoad()) -> str:
    """cpu_only never leaves the CPU, gpu_only never uses it; all: small models on a free CPU, else a free GPU, else the shorter queue."""
    on_cpu = "sql" if profile.native else "arrow"
    if mode == "cpu_only":
        return on_cpu
    if mode == "gpu_only":
        return "gpu"
    if not profile.has_model:
        return on_cpu
    gpu = 1.0 if load.gpu is None else load.gpu
    if profile.model_mb <= SMALL_MODEL_MB and load.cpu < BUSY:
        return on_cpu
    if gpu < BUSY:
        return "gpu"
    return on_cpu if load.cpu <= gpu else "gpu"
