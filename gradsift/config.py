"""Settings of a run, and the scalar rules that follow from them."""

from __future__ import annotations

import math
from dataclasses import dataclass

CHOICES = {
    "lr_mode": ("accumulate", "update"),
    "stages": (0, 1, 2),
    "rounding": ("nearest", "floor", "ceil"),
    "quota_scope": ("worker", "leader"),
    "quota_policy": ("norm", "size", "energy"),
    "pack_policy": ("greedy", "round_robin", "contiguous", "size"),
    "cost_model": ("log", "scan"),
    "norm_of": ("accumulator", "gradient"),
    "error_at": ("residual", "accumulator"),
    "kernel": ("window", "two_phase", "threshold", "arrow"),
}


@dataclass(frozen=True)
class RunConfig:
    """
    points behind the choices; the first of each is the default."""

    n_workers: int = 4
    density: float | None = None
    k: int | None = None
    lr: float = 1.0
    lr_mode: str = "accumulate"
    decay_steps: tuple[int, ...] = ()
    gamma: float = 0.1
    epochs: int = 1
    local_batch: int = 32
    error_feedback: bool = True
    stages: int = 2
    rounding: str = "nearest"
    cap: bool = True
    min_quota: int = 0
    refill: bool = False
    quota_scope: str = "worker"
    quota_policy: str = "norm"
    pack_policy: str = "greedy"
    cost_model: str = "log"
    norm_of: str = "accumulator"
    error_at: str = "residual"
    kernel: str = "window"
    seed: int = 42

    def __post_init__(self) -> None:
        if (self.density is None) == (self.k is None):
            raise ValueError("give exactly one of density and k")
        if self.density is not None and not 0 < self.density <= 1:
            raise ValueError("density must be in (0, 1]")
        if self.k is not None and self.k < 1:
            raise ValueError("k must be at least 1")
        if self.n_workers < 1 or self.lr <= 0:
            raise ValueError("n_workers and lr must be positive")
        for name, allowed in CHOICES.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")

    def resolve_k(self, n_g: int) -> int:
        """The number of parameters to select among n_g."""
        return min(n_g, self.k if self.k is not None else max(1, math.floor(self.density * n_g + 0.5)))

    def lr_at(self, t: int) -> float:
        """Learning rate of iteration t under step decay."""
        return self.lr * self.gamma ** sum(t >= s for s in self.decay_steps)

    def leader_of(self, t: int) -> int:
        """The worker that decides in iteration t."""
        return t % self.n_workers
