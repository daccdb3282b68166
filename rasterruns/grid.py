"""The global grid: 2^order x 2^order half-open cells over a square integer domain."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Side of the default domain; one empty margin cell must stay around all objects.
DOMAIN_BITS = 20
DOMAIN = 1 << DOMAIN_BITS


@dataclass(frozen=True)
class GridSpec:
    """``order`` bits an axis from the corner (x0, y0); ``cell`` is a cell's side in lattice units."""

    order: int = 16
    x0: int = 0
    y0: int = 0
    cell: int = 0

    def __post_init__(self):
        if not 1 <= self.order <= 30:
            raise ValueError("order must be 1 to 30")
        if not self.cell:
            if self.order > DOMAIN_BITS:
                raise ValueError("give the cell side where the order exceeds the domain's bits")
            object.__setattr__(self, "cell", 1 << (DOMAIN_BITS - self.order))

    @property
    def side(self) -> int:
        return 1 << self.order

    def cell_of(self, x: Column, y: Column) -> tuple[Column, Column]:
        """Cell indexes of a point (operands are non-negative inside the domain)."""
        if self.cell & (self.cell - 1) == 0:
            s = self.cell.bit_length() - 1
            return F.shiftright(x - self.x0, s), F.shiftright(y - self.y0, s)
        return F.floor((x - self.x0) / self.cell).cast("long"), F.floor((y - self.y0) / self.cell).cast("long")
