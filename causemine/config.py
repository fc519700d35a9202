"""Parameters of an analysis, and presets for common situations."""

from __future__ import annotations

from dataclasses import dataclass, replace

MICRO = 1_000_000


@dataclass(frozen=True)
class Config:
    min_support: float = 0.1
    max_length: int = 5
    min_lift: float = 1.0
    h_lift_long: float = 1.0
    h_lift_short: float = 1.0
    h_supp: float = 1.05
    mode: str = "simultaneous"
    distinct_ratio: float = 0.02
    exclude: tuple[str, ...] = ()
    algorithm: str = "auto"
    parallelism: int | None = None
    shards: int | None = None
    min_count: int = 1

    def __post_init__(self) -> None:
        if not 0 < self.min_support <= 1:
            raise ValueError("min_support must be in (0, 1]")
        if self.max_length < 1:
            raise ValueError("max_length must be at least 1")
        if min(self.h_lift_long, self.h_lift_short, self.h_supp) < 1:
            raise ValueError("the multipliers of the filters must be at least 1")
        if self.mode not in ("simultaneous", "sequential"):
            raise ValueError("mode must be simultaneous or sequential")
        if self.algorithm not in ("auto", "cuboids", "levelwise", "patterntree"):
            raise ValueError("unknown algorithm")

    def with_(self, **changes) -> Config:
        return replace(self, **changes)

    @classmethod
    def urgent(cls) -> Config:
        """Mission-critical: a quick answer that covers nearly all failures."""
        return cls(min_support=0.95, max_length=3)

    @classmethod
    def thorough(cls) -> Config:
        """Long-term: every combination that explains four failures in ten."""
        return cls(min_support=0.4, max_length=5)

    @classmethod
    def monitor(cls) -> Config:
        """Continuous: rare but strong causes."""
        return cls(min_support=0.1, max_length=5, min_lift=5.0)


def least_count(min_support: float, positives: int, min_count: int = 1) -> int:
    """The least weight that reaches the support, worked out in integers."""
    micro = round(min_support * MICRO)
    return max(min_count, -(-micro * positives // MICRO))
