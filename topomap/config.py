"""Settings of one training run, and what follows from them."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

INITS = ("gradient", "random", "given")
SELECTIONS = ("staggered", "random", "random_replace", "sequential")
STOPS = ("no_moves", "max")


@dataclass(frozen=True)
class MapConfig:
    """``horizon`` None means the training-list length; ``max_passes`` caps the passes run and doesn't enter the decays."""

    rows: int = 4
    cols: int = 3
    initial_rate: float = 0.1
    base: float = math.e
    init: str = "gradient"
    selection: str = "staggered"
    seed: int | None = None
    horizon: int | None = None
    max_passes: int | None = 10
    stop: str = "no_moves"
    clock: str = "pass"
    moves: str = "presented"
    neighbourhood: str = "circle"
    on_missing: str = "drop"

    def __post_init__(self):
        if self.rows < 1 or self.cols < 1:
            raise ValueError("a grid has at least one row and one column")
        if not 0 < self.initial_rate <= 1:
            raise ValueError("the initial rate lies in (0, 1]")
        if self.base <= 1:
            raise ValueError("the base is greater than 1")
        for value, known in ((self.init, INITS), (self.selection, SELECTIONS), (self.stop, STOPS), (self.clock, ("pass", "sample")), (self.moves, ("presented", "frozen")), (self.neighbourhood, ("circle", "square")), (self.on_missing, ("drop", "error"))):
            if value not in known:
                raise ValueError(f"{value!r} is none of {known}")
        if (self.init == "random" or self.selection.startswith("random")) and self.seed is None:
            raise ValueError("a random start or order needs a seed")
        if self.stop == "no_moves" and self.max_passes is None and self.horizon is None:
            raise ValueError("stopping when nothing moves may never happen: set max_passes or a horizon")

    @property
    def nodes(self) -> int:
        return self.rows * self.cols

    def with_rate(self, rate: float) -> MapConfig:
        return replace(self, initial_rate=rate)

    def resolved(self, n: int) -> MapConfig:
        """Horizon and passes for a list of ``n`` samples."""
        horizon = self.horizon or max(1, n)
        return replace(self, horizon=horizon, max_passes=min(horizon, self.max_passes or horizon))


def grid_from_density(n: int, per_node: float, longest: int | None = None) -> tuple[int, int]:
    """Rows and columns whose product is nearest to n / per_node nodes, at most twice as long as wide, of the grids with sides up to ``longest`` if that is given."""
    target = max(1, round(n / per_node))
    side = math.isqrt(target) * 2 + 3
    shapes = [(r, c) for c in range(1, min(side, (longest or side) + 1)) for r in range(c, min(2 * c, longest or 2 * c) + 1)]
    return min(shapes, key=lambda s: (abs(s[0] * s[1] - target), s[0] - s[1], -s[0] * s[1]))
