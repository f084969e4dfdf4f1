"""Parameters of a clustering run, validated where they are made."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

METHODS = ("slab_pruned", "slab_full", "grid_full", "grid_approx", "kdtree_pruned", "reference", "bucket_pruned", "brute")
BORDER_RULES = ("min_cluster", "nearest_core", "all")


@dataclass(frozen=True)
class ClusterParams:
    """eps: radius of the closed ball; min_pts: its least population, the point itself included.

    fold: repeated coordinates are clustered as one point of their weight.
    strict: pairs of cells that only rounding could bring within eps are not met, so
    that pairs count as the definition says. index_bytes: memory for bit tables in a
    tile. tile_points: how many own points a tile should have; tile_limit, tile_bytes:
    beyond how many rows, halo included, or bytes it is dealt to several tasks.
    """

    eps: float
    min_pts: int
    method: str = "slab_pruned"
    border_rule: str = "min_cluster"
    corner_rule: str = "exact"
    visit: str = "once"
    order: str = "as_given"
    box_prune: bool = True
    rho: float = 0.001
    null_policy: str = "fail"
    max_offsets: int = 100_000
    strict: bool = False
    fold: bool = False
    index_bytes: int = 256 << 20
    tile_points: int = 4_000
    tile_limit: int = 4_000_000
    tile_bytes: int = 512 << 20
    driver_roots: int = 2_000_000

    def __post_init__(self):
        if not (self.eps > 0 and math.isfinite(self.eps)):
            raise ValueError("eps must be positive")
        if int(self.min_pts) != self.min_pts or self.min_pts < 1:
            raise ValueError("min_pts must be a positive integer")
        for value, known in ((self.method, METHODS), (self.border_rule, BORDER_RULES), (self.corner_rule, ("exact", "box")), (self.visit, ("once", "both")), (self.order, ("as_given", "nearest_first", "densest_first")), (self.null_policy, ("fail", "drop"))):
            if value not in known:
                raise ValueError(f"{value!r} is none of {known}")
        if not 0 < self.rho:
            raise ValueError("rho must be positive")

    def rows_limit(self, d: int) -> int:
        """Rows of ``d`` coordinates that one task takes; a row is held three times."""
        return max(2, min(self.tile_limit, self.tile_bytes // (24 * d + 64)))

    def with_(self, **changes) -> ClusterParams:
        return replace(self, **changes)
