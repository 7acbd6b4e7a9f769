"""Grid specifications and cell arithmetic. All of it is public, chosen by the owner, never inferred from private rows."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Cells beyond which a dense matrix is refused.
MOST_CELLS = 2_000_000_000


@dataclass(frozen=True)
class GridSpec:
    """Bounds and number of parts per dimension."""

    lo: tuple[float, ...]
    hi: tuple[float, ...]
    g: tuple[int, ...]

    def __post_init__(self):
        if not len(self.lo) == len(self.hi) == len(self.g) or not self.g:
            raise ValueError("bounds and parts need the same number of dimensions")
        if any(not (math.isfinite(a) and math.isfinite(b) and a < b) for a, b in zip(self.lo, self.hi, strict=True)):
            raise ValueError("each dimension needs finite bounds, lower before upper")
        if any(k < 1 for k in self.g):
            raise ValueError("each dimension needs a part")

    @property
    def n(self) -> int:
        return len(self.g)

    @property
    def cells(self) -> int:
        return math.prod(self.g)

    def coarse(self, level: int = 1) -> tuple[int, ...]:
        """Parts per dimension after so many halvings."""
        return tuple(-(-k // 2**level) for k in self.g)

    def dense_cells(self) -> int:
        if self.cells > MOST_CELLS:
            raise ValueError(f"{self.cells} cells are too many for a dense matrix")
        return self.cells


def unit(g: int, n: int = 2) -> GridSpec:
    """The unit cube with ``g`` parts per dimension."""
    return GridSpec((0.0,) * n, (1.0,) * n, (g,) * n)


def index_of(x: Column, lo: float, hi: float, g: int) -> Column:
    """Part of ``x``; the upper bound belongs to the last part, values outside to the nearest."""
    part = F.floor((x - F.lit(float(lo))) * F.lit(float(g)) / F.lit(float(hi - lo)))
    return F.greatest(F.least(part, F.lit(g - 1)), F.lit(0)).cast("long")


def linear(indexes: list[Column], g: tuple[int, ...]) -> Column:
    """Row-major number of a cell."""
    made = indexes[0]
    for i, k in zip(indexes[1:], g[1:], strict=True):
        made = made * k + i
    return made.cast("long")


def coordinates(cell: Column, g: tuple[int, ...]) -> list[Column]:
    """Inverse of ``linear``."""
    made, below = [], math.prod(g)
    for k in g:
        below //= k
        made.append(F.floor(cell / below).cast("long") % k if below > 1 else cell % k)
    return [c.cast("long") for c in made]


def block_of(cell: Column, spec: GridSpec, level: int = 1) -> Column:
    """Number of the block that holds a cell after ``level`` halvings."""
    return linear([F.floor(i / 2**level).cast("long") for i in coordinates(cell, spec.g)], spec.coarse(level))


def inside(df: DataFrame, cols: list[str], spec: GridSpec, out_of_bounds: str = "clamp") -> DataFrame:
    """Rows with finite coordinates, under a policy for those outside the bounds: ``clamp``, ``drop`` or ``error``."""
    sound = df
    for c in cols:
        v = F.col(c).cast("double")
        sound = sound.where(v.isNotNull() & ~F.isnan(v))
    if out_of_bounds == "clamp":
        return sound
    within = F.lit(True)
    for c, lo, hi in zip(cols, spec.lo, spec.hi, strict=True):
        within = within & (F.col(c) >= lo) & (F.col(c) <= hi)
    if out_of_bounds == "drop":
        return sound.where(within)
    if out_of_bounds == "error":
        return sound.where(F.when(within, F.lit(True)).otherwise(F.raise_error(F.lit("point outside the bounds")).cast("boolean")))
    raise ValueError(f"policy {out_of_bounds!r}")


def cell_of(cols: list[str], spec: GridSpec) -> Column:
    return linear([index_of(F.col(c).cast("double"), lo, hi, g) for c, lo, hi, g in zip(cols, spec.lo, spec.hi, spec.g, strict=True)], spec.g)
