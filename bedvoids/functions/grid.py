"""Regular grids: bin edges, voxel numbers, boxes and Gaussians as plain values that become literals of a plan."""

from __future__ import annotations

from dataclasses import dataclass
from math import sqrt

from pyspark.sql import Column
from pyspark.sql import functions as F

AXES = ("x", "y", "z")
INDEX = ("ix", "iy", "iz")
#: Spread of the rounding of counts: keeps empty regions comparable.
SIGMA_FLOOR = sqrt(1 / 12)
SPANS = {"x": (900.0, 105000.0), "y": (0.0, 10.0), "z": (0.0, 50.0)}


@dataclass(frozen=True)
class GridSpec:
    """Bins are half-open, a value on the upper bound falls into the last one, anything outside into none."""

    lo: tuple[float, float, float]
    hi: tuple[float, float, float]
    n: tuple[int, int, int]

    @property
    def voxels(self) -> int:
        return self.n[0] * self.n[1] * self.n[2]

    @property
    def widths(self) -> tuple[float, float, float]:
        return tuple((h - l) / n for l, h, n in zip(self.lo, self.hi, self.n, strict=True))

    @property
    def voxel_volume(self) -> float:
        a, b, c = self.widths
        return a * b * c

    def inside(self) -> Column:
        test = F.lit(True)
        for a, lo, hi in zip(AXES, self.lo, self.hi, strict=True):
            test = test & F.col(a).between(F.lit(lo), F.lit(hi))
        return test

    def bins(self) -> dict[str, Column]:
        out = {}
        for a, i, lo, w, n in zip(AXES, INDEX, self.lo, self.widths, self.n, strict=True):
            out[i] = F.least(F.floor((F.col(a) - F.lit(lo)) / F.lit(w)), F.lit(n - 1)).cast("int")
        return out

    def voxel(self, ix: str | Column = "ix", iy: str | Column = "iy", iz: str | Column = "iz") -> Column:
        ix, iy, iz = (F.col(c) if isinstance(c, str) else c for c in (ix, iy, iz))
        return ((ix.cast("long") * self.n[1] + iy) * self.n[2] + iz).cast("long")

    def indices(self, voxel: str | Column = "voxel") -> dict[str, Column]:
        v = F.col(voxel) if isinstance(voxel, str) else voxel
        plane = self.n[1] * self.n[2]
        return {"ix": F.expr(f"cast({_sql(voxel)} div {plane} as int)") if isinstance(voxel, str) else F.floor(v / plane).cast("int"), "iy": F.floor(F.pmod(v, F.lit(plane)) / self.n[2]).cast("int"), "iz": F.pmod(v, F.lit(self.n[2])).cast("int")}

    def morton(self) -> Column:
        """A key that keeps neighbours together: the bits of ix, iy and iz in turn, lowest first."""
        out = F.lit(0).cast("long")
        for bit in range(max(self.n).bit_length()):
            for place, i in enumerate(INDEX):
                out = out + F.shiftleft(F.shiftright(F.col(i).cast("long"), bit).bitwiseAND(F.lit(1).cast("long")), 3 * bit + place)
        return out

    def bucket(self, axis: int) -> Column:
        """The bin of an axis by the built-in function; the same as in `bins` but for rounding on the edges of bins."""
        lo, hi, n = self.lo[axis], self.hi[axis], self.n[axis]
        return F.least(F.width_bucket(F.col(AXES[axis]), F.lit(lo), F.lit(hi), F.lit(n)) - 1, F.lit(n - 1)).cast("int")

    def centre(self, axis: int) -> Column:
        return F.lit(self.lo[axis]) + (F.col(INDEX[axis]) + F.lit(0.5)) * F.lit(self.widths[axis])

    def coarser(self, factor: int) -> GridSpec:
        if any(n % factor for n in self.n):
            raise ValueError("bin counts must be multiples of the factor")
        return GridSpec(self.lo, self.hi, tuple(n // factor for n in self.n))


def _sql(name: str) -> str:
    return f"`{name}`"


@dataclass(frozen=True)
class Box:
    """Index ranges, bounds included."""

    ix: tuple[int, int]
    iy: tuple[int, int]
    iz: tuple[int, int]

    def test(self) -> Column:
        return F.col("ix").between(*self.ix) & F.col("iy").between(*self.iy) & F.col("iz").between(*self.iz)


@dataclass(frozen=True)
class Target:
    """The Gaussian of a selected region; counts depend on the bins, so the grid goes with it."""

    mu: float
    sigma: float
    n: int
    grid: GridSpec | None = None

    def check(self, grid: GridSpec) -> Target:
        if self.grid is not None and tuple(round(w, 12) for w in self.grid.widths) != tuple(round(w, 12) for w in grid.widths):
            raise ValueError("the target was taken on bins of another size")
        return self


def simulation_step(step: str | Column, factor: int = 100) -> Column:
    """The simulation's own number of a linearised step."""
    return (F.col(step) if isinstance(step, str) else step) * factor


def bed_grid(n: tuple[int, int, int] = (24, 6, 24)) -> GridSpec:
    return GridSpec(tuple(SPANS[a][0] for a in AXES), tuple(SPANS[a][1] for a in AXES), n)
