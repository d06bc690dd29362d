"""Search parameters, checked once."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class SearchParams:
    """tau: least similarity; k: neighbours kept; window: partitions in a row without a hit before a query stops; nprobe: most partitions."""

    tau: float
    window: int = 8
    nprobe: int = 90
    k: int = 10
    microbatch: int = 16384
    #: Ranks a query may send in one wave; None sends all that are committed.
    ranks_per_wave: int | None = None
    drop_self: bool = False

    def __post_init__(self):
        if math.isnan(self.tau):
            raise ValueError("tau is NaN")
        for name in ("window", "nprobe", "k", "microbatch"):
            if getattr(self, name) < 1:
                raise ValueError(f"{name} must be at least 1")
        if self.ranks_per_wave is not None and self.ranks_per_wave < 1:
            raise ValueError("ranks_per_wave must be at least 1")

    @property
    def distance_bound(self) -> float:
        return 1.0 - self.tau

    def with_(self, **changes) -> SearchParams:
        return replace(self, **changes)
