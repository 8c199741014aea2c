"""Parameters of mining runs. Bad values raise ValueError before any job starts."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

SLACK = 1e-9  # sums differ in their last digits by order, so pruning keeps what is this near to a threshold


def _one_of(name: str, value: str, *allowed: str) -> None:
    if value not in allowed:
        raise ValueError(f"{name} must be one of {', '.join(allowed)}, not {value!r}")


@dataclass(frozen=True)
class MiningParams:
    min_sup: float
    wgt_fct: float = 1.0
    support_cap: str = "tight"  # or loose
    weight_cap: str = "local"  # or global
    verify: str = "fused"  # or final_scan
    prune: str = "cap"  # or exact
    i_ext: str = "suffix"  # or cooccurring
    freq: str = "occurrences"  # or sequences
    max_len: int | None = None
    max_candidates: int = 1_000_000  # live nodes of one pass; a larger level takes several
    engine: str = "arrow"  # or relational

    def __post_init__(self):
        if not 0 <= self.min_sup <= 1:
            raise ValueError("min_sup must lie in [0, 1]")
        if self.wgt_fct <= 0:
            raise ValueError("wgt_fct must be positive")
        if self.max_len is not None and self.max_len < 1:
            raise ValueError("max_len must be at least 1")
        if self.max_candidates < 1:
            raise ValueError("max_candidates must be at least 1")
        _one_of("support_cap", self.support_cap, "tight", "loose")
        _one_of("weight_cap", self.weight_cap, "local", "global")
        _one_of("verify", self.verify, "fused", "final_scan")
        _one_of("prune", self.prune, "cap", "exact")
        _one_of("i_ext", self.i_ext, "suffix", "cooccurring")
        _one_of("freq", self.freq, "occurrences", "sequences")
        _one_of("engine", self.engine, "arrow", "relational")


@dataclass(frozen=True)
class IncrementParams:
    mu: float = 0.7
    gamma: float = 0.8
    local: float | Callable[[dict], float] | None = None  # a local threshold of the caller's own

    def __post_init__(self):
        if not 0 < self.mu <= 1:
            raise ValueError("mu must lie in (0, 1]")
        if self.gamma < 0:
            raise ValueError("gamma must not be negative")
