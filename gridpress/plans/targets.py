"""Error targets and their budgets of squared error."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import functions as F

from gridpress.plans.grid import GridFrame


@dataclass(frozen=True)
class GridStats:
    low: float
    high: float
    energy: float
    cells: int

    @property
    def span(self) -> float:
        return self.high - self.low


def grid_stats(grid: GridFrame) -> GridStats:
    """Range and energy over all lattice points; points that are not stored are 0."""
    n, lo, hi, e = grid.df.agg(F.count("v"), F.min("v"), F.max("v"), F.sum(F.col("v").cast("double") * F.col("v"))).first()
    lo, hi = float(lo or 0.0), float(hi or 0.0)
    if n < grid.spec.cells:
        lo, hi = min(lo, 0.0), max(hi, 0.0)
    return GridStats(lo, hi, float(e or 0.0), grid.spec.cells)


@dataclass(frozen=True)
class ErrorTarget:
    kind: str  # rel, rmse, psnr, sse or size
    value: float

    rel = classmethod(lambda cls, v: cls("rel", v))
    rmse = classmethod(lambda cls, v: cls("rmse", v))
    psnr = classmethod(lambda cls, v: cls("psnr", v))
    size = classmethod(lambda cls, v: cls("size", v))

    def to_sse(self, s: GridStats) -> float:
        if self.kind == "sse":
            return self.value
        if self.kind == "rel":
            return self.value**2 * s.energy
        if self.kind == "rmse":
            return self.value**2 * s.cells
        if self.kind == "psnr":
            return s.cells * (s.span / (2 * 10 ** (self.value / 20))) ** 2
        raise ValueError(f"a {self.kind} target has no budget of error")
