"""Parameters of a clustering run."""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class ClusterSpec:
    """Radius and density of the model, and how a run is carried out.

    Distances are compared as integers: a pair is near if the sum of squared
    differences is at most ``eps ** 2``. A point counts among its own neighbours
    and is a core point from ``min_pts`` neighbours on.
    """

    eps: int
    min_pts: int
    index_fanout: int | None = None
    block_points: int = 60_000
    early_stop: bool = True

    def __post_init__(self) -> None:
        if int(self.eps) != self.eps or self.eps <= 0 or self.min_pts < 1:
            raise ValueError("eps must be a positive integer and min_pts at least 1")

    def reach(self, d: int) -> int:
        """Cells per dimension within which neighbours of a cell lie."""
        return math.isqrt(d - 1) + 1


def dims(df) -> int:
    """Number of coordinates x1, x2, ... of a point set."""
    d = 0
    while f"x{d + 1}" in df.columns:
        d += 1
    if not d:
        raise ValueError("a point set has columns point_id, x1, x2, ...")
    return d


def xs(d: int) -> list[str]:
    return [f"x{j}" for j in range(1, d + 1)]


def ks(d: int) -> list[str]:
    return [f"k{j}" for j in range(1, d + 1)]
