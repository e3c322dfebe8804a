"""Settings of a similarity join."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class JoinConfig:
    eps: float
    recall: float = 0.9
    memory_fraction: float = 0.10
    centers_fraction: float = 0.001
    centers: int | None = None  # instead of the fraction
    metric: str = "l2"  # or cosine: vectors are scaled to unit length first
    eps_is_squared: bool = False
    seed: int = 42
    prune: bool = True
    scale: str = "mu"  # mu, unit or cap: what an arc counts in the pruning sum
    radius_mode: str = "bucket_plus_eps"  # mean_plus_eps, quantile_plus_eps, eps, or calibrated (with radius_share)
    radius_share: float = 1.0  # for calibrated: eps + share x bucket radius
    radius_quantile: float = 0.9  # for quantile_plus_eps: share of a bucket's members within the radius
    task_bytes: int = 1 << 30  # of vectors in memory, at most, in one task
    edge_merge: str = "union"  # or intersection
    neighbor_limit: int | None = None
    order: str = "overlap"  # id, random
    policy: str = "opt"  # lru, fifo, lfu, lifo
    pin_partner: bool = True
    executor: str = "segment"  # in planned order, each bucket once a segment; or edge_join, native
    block_rows: int = 4096
    margin_filter: bool = False

    def __post_init__(self) -> None:
        if not self.eps > 0:
            raise ValueError("eps must be positive")
        if not 0 < self.recall <= 1:
            raise ValueError("recall lies in (0, 1]")
        if not 0 < self.memory_fraction <= 1 or not 0 < self.centers_fraction <= 1:
            raise ValueError("fractions lie in (0, 1]")
        if self.centers is not None and self.centers < 1:
            raise ValueError("at least one centre is needed")
        for name, allowed in (("metric", ("l2", "cosine")), ("scale", ("mu", "unit", "cap")), ("radius_mode", ("bucket_plus_eps", "mean_plus_eps", "quantile_plus_eps", "eps", "calibrated")), ("edge_merge", ("union", "intersection")), ("order", ("overlap", "id", "random")), ("policy", ("opt", "lru", "fifo", "lfu", "lifo")), ("executor", ("native", "edge_join", "segment"))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} is one of {', '.join(allowed)}")

    @property
    def distance(self) -> float:
        return self.eps**0.5 if self.eps_is_squared else self.eps
