"""Layouts: disjoint rectangles of cells that cover the grid, and the columns that place rows by them."""

from __future__ import annotations

import json
from dataclasses import dataclass
from functools import cached_property
from typing import NamedTuple

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cutlearn.config import InvalidLayout
from cutlearn.plans.grid import GridSpec, prefix

LAYOUT_SCHEMA = "part_id int, r0 int, r1 int, c0 int, c1 int"


class Rect(NamedTuple):
    """Rows [r0, r1) by columns [c0, c1)."""

    r0: int
    r1: int
    c0: int
    c1: int

    @property
    def area(self) -> int:
        return (self.r1 - self.r0) * (self.c1 - self.c0)


@dataclass(frozen=True)
class Layout:
    rects: tuple[Rect, ...]
    g: int

    @staticmethod
    def whole(g: int) -> Layout:
        return Layout((Rect(0, g, 0, g),), g)

    @cached_property
    def key(self) -> tuple[Rect, ...]:
        """Equal for equal layouts, whatever the order of their cuts."""
        return tuple(sorted(self.rects))

    @cached_property
    def lookup(self) -> np.ndarray:
        out = np.full((self.g, self.g), -1, np.int64)
        for k, r in enumerate(self.rects):
            out[r.r0 : r.r1, r.c0 : r.c1] = k
        return out

    def validate(self) -> Layout:
        inside = all(0 <= r.r0 < r.r1 <= self.g and 0 <= r.c0 < r.c1 <= self.g for r in self.rects)
        if not inside or sum(r.area for r in self.rects) != self.g**2 or (self.lookup < 0).any():
            raise InvalidLayout("rectangles must be disjoint and cover the grid")
        return self

    def counts(self, hist: np.ndarray) -> np.ndarray:
        p = prefix(hist)
        return np.array([p[r.r1, r.c1] - p[r.r0, r.c1] - p[r.r1, r.c0] + p[r.r0, r.c0] for r in self.rects])

    def part(self, row: Column, col: Column) -> Column:
        cells = F.expr(f"array({', '.join(map(str, self.lookup.ravel().tolist()))})")  # one call to the JVM, not one a cell
        return F.element_at(cells, (row * self.g + col + 1).cast("int"))

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(k, *map(int, r)) for k, r in enumerate(self.rects)], LAYOUT_SCHEMA)

    @staticmethod
    def from_df(df: DataFrame, g: int) -> Layout:
        rows = sorted(df.select("part_id", "r0", "r1", "c0", "c1").collect())
        return Layout(tuple(Rect(*r[1:]) for r in rows), g).validate()

    def to_json(self) -> str:
        return json.dumps({"g": self.g, "rects": [list(map(int, r)) for r in self.rects]})

    @staticmethod
    def from_json(text: str) -> Layout:
        d = json.loads(text)
        return Layout(tuple(Rect(*r) for r in d["rects"]), d["g"]).validate()


def assign(points: DataFrame, spec: GridSpec, layout: Layout) -> DataFrame:
    """points with part, the region that owns each."""
    return points.withColumn("part", layout.part(spec.row(F.col("y")), spec.col(F.col("x"))))


def replica_parts(spec: GridSpec, layout: Layout, d: int) -> Column:
    """Regions touched by the box of half side d around (x, y), each once. A box inside one cell is looked up at once.
    The box reaches the corners too, so it holds the disc; the few regions touched by corners alone get no pairs."""
    x, y = F.col("x"), F.col("y")
    r0, r1, c0, c1 = spec.row(y + d), spec.row(y - d), spec.col(x - d), spec.col(x + d)
    one = F.array(layout.part(r0, c0))
    if d * spec.g > 16 * min(spec.width, spec.height):
        # a box over very many cells is held against the rectangles themselves
        hits = [F.when((r0 < r.r1) & (r1 >= r.r0) & (c0 < r.c1) & (c1 >= r.c0), F.lit(k)) for k, r in enumerate(layout.rects)]
        return F.array_compact(F.array(*hits))
    rows = F.sequence(r0, r1)
    many = F.array_distinct(F.flatten(F.transform(rows, lambda r: F.transform(F.sequence(c0, c1), lambda c: layout.part(r, c)))))
    return F.when((r0 == r1) & (c0 == c1), one).otherwise(many)


def overlap(a: Layout, b: Layout, spark: SparkSession) -> DataFrame:
    """part_a, part_b, cells: how the regions of two layouts share cells."""
    l, r = a.to_df(spark).alias("a"), b.to_df(spark).alias("b")
    meet = F.expr("a.r0 < b.r1 and b.r0 < a.r1 and a.c0 < b.c1 and b.c0 < a.c1")
    cells = F.expr("(least(a.r1, b.r1) - greatest(a.r0, b.r0)) * (least(a.c1, b.c1) - greatest(a.c0, b.c0))")
    return l.join(r, meet).select(F.col("a.part_id").alias("part_a"), F.col("b.part_id").alias("part_b"), cells.cast("long").alias("cells"))
