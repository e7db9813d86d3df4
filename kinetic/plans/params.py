"""Parameters of the optimiser and of the experiments."""

from __future__ import annotations

from dataclasses import dataclass

#: Critical values of the chi-square test by (bins a side, level) (fixed values).
CHI2 = {(2, 0.10): 6.251389, (2, 0.05): 7.814728, (2, 0.01): 11.344867, (4, 0.10): 22.307130, (4, 0.05): 24.995790, (4, 0.01): 30.577914}


def capacity_of(node_bytes: int = 4096, fill: float = 1.0, entry_bytes: int = 40) -> int:
    """Objects that a node of so many bytes holds."""
    return int(node_bytes * fill // entry_bytes)


@dataclass(frozen=True)
class OptimizerParams:
    """q speed layers, node capacity, horizon in seconds, depth and test of the quad trees, and the variants of the estimate.

    node_rounding: ceil, round, floor or exact. quadrant_grain: off, on, speed,
    region or part. layering: equal_width, equal_depth or distinct.
    representative: mean or max. effect: least chi-square over n that splits a
    cell, against the test's power at huge counts (0: the plain test).
    """

    q: int = 50
    capacity: int = 102
    horizon: float = 120.0
    max_depth: int = 5
    alpha: float = 0.05
    bins: int = 2
    node_rounding: str = "ceil"
    quadrant_grain: str = "part"
    layering: str = "equal_width"
    representative: str = "mean"
    x0: float = 0.0
    y0: float = 0.0
    side: float = 10000.0
    clamp_quadrant: bool = False
    effect: float = 0.0

    @property
    def critical(self) -> float:
        return CHI2[self.bins, self.alpha]

    @property
    def counted_depth(self) -> int:
        """Levels that are counted: a 4 x 4 test looks two levels down."""
        return self.max_depth + (1 if self.bins == 4 else 0)
