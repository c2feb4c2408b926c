"""The map, its uniform grid and the counts per cell. Row 0 is the top, y grows upward."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cutlearn.config import EmptyInput


@dataclass(frozen=True)
class GridSpec:
    x0: int
    y0: int
    x1: int
    y1: int
    g: int = 30

    @property
    def width(self) -> int:
        return self.x1 - self.x0 + 1

    @property
    def height(self) -> int:
        return self.y1 - self.y0 + 1

    @property
    def state_dim(self) -> int:
        return (self.g + 1) ** 2 * 3

    @property
    def actions(self) -> int:
        return self.g * self.g * 2

    def finer(self, times: int) -> GridSpec:
        return GridSpec(self.x0, self.y0, self.x1, self.y1, self.g * times)

    def _clamped(self, v: Column) -> Column:
        return F.least(F.greatest(v, F.lit(0)), F.lit(self.g - 1)).cast("int")

    def col(self, x: Column) -> Column:
        """Column of cells; what lies off the map counts to its border cells."""
        return self._clamped(F.floor((x - self.x0) * self.g / F.lit(self.width)) if self.g * self.width < 1 << 50 else F.floor((x - self.x0) / F.lit(self.width) * self.g))

    def row(self, y: Column) -> Column:
        return self._clamped(F.floor((self.y1 - y) * self.g / F.lit(self.height)) if self.g * self.height < 1 << 50 else F.floor((self.y1 - y) / F.lit(self.height) * self.g))

    def col_of(self, x: int) -> int:
        return min(max((x - self.x0) * self.g // self.width, 0), self.g - 1)

    def row_of(self, y: int) -> int:
        return min(max((self.y1 - y) * self.g // self.height, 0), self.g - 1)

    def x_line(self, j: int) -> float:
        return self.x0 + j * self.width / self.g

    def y_line(self, i: int) -> float:
        return self.y1 - i * self.height / self.g


def fit_grid(points: DataFrame, g: int = 30) -> GridSpec:
    """One scan; one row reaches the driver."""
    r = points.agg(*(f(c) for c in ("x", "y") for f in (F.min, F.max))).first()
    if r[0] is None:
        raise EmptyInput("no points to fit a map to")
    return GridSpec(int(r[0]), int(r[2]), int(r[1]), int(r[3]), g)


def with_cell(points: DataFrame, spec: GridSpec) -> DataFrame:
    return points.withColumns({"row": spec.row(F.col("y")), "col": spec.col(F.col("x"))})


def cell_histogram(points: DataFrame, spec: GridSpec) -> DataFrame:
    """row, col, n; partial aggregation leaves at most g^2 rows per task to shuffle."""
    return with_cell(points.select("x", "y"), spec).groupBy("row", "col").agg(F.count("*").alias("n"))


def dense(histogram: DataFrame, g: int) -> np.ndarray:
    """The g by g counts on the driver: bounded by the grid, never by the points."""
    out = np.zeros((g, g), np.int64)
    for r, c, n in histogram.select("row", "col", "n").collect():
        out[r, c] = n
    return out


def prefix(hist: np.ndarray) -> np.ndarray:
    """Sums over [0, i) by [0, j)."""
    out = np.zeros((hist.shape[0] + 1, hist.shape[1] + 1), hist.dtype)
    out[1:, 1:] = hist.cumsum(0).cumsum(1)
    return out
