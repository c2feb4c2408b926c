"""Functions for SQL users. Each Python one has a native twin that the library itself uses."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cutlearn.plans.grid import GridSpec
from cutlearn.plans.layout import Layout


@F.pandas_udf(T.DoubleType())
def haversine_udf(lon1: pd.Series, lat1: pd.Series, lon2: pd.Series, lat2: pd.Series) -> pd.Series:
    a, b, c, d = (np.radians(v) for v in (lon1, lat1, lon2, lat2))
    return 2 * 6_371_008.8 * np.arcsin(np.sqrt(np.sin((d - b) / 2) ** 2 + np.cos(b) * np.cos(d) * np.sin((c - a) / 2) ** 2))


@F.pandas_udf(T.DoubleType())
def gini_udf(n: pd.Series) -> float:
    v = np.sort(n.to_numpy(float))
    m = len(v)
    return float(2 * (np.arange(1, m + 1) * v).sum() / (m * v.sum()) - (m + 1) / m) if m and v.sum() else 0.0


@F.udtf(returnType=T.StructType([T.StructField(c, T.IntegerType()) for c in ("part_id", "r0", "r1", "c0", "c1")]))
class LayoutRects:
    """Rectangles of a layout given as JSON."""

    def eval(self, layout: str):
        for k, r in enumerate(Layout.from_json(layout).rects):
            yield (k, *map(int, r))


def register(spark: SparkSession, spec: GridSpec) -> None:
    """cell_of(x, y) as a SQL function, and layout_rects(json) as a table function."""
    w, h, g = spec.width, spec.height, spec.g
    clamp = lambda e: f"least(greatest({e}, 0L), {g - 1}L)"
    row, col = clamp(f"(({spec.y1}L - y) * {g}) div {h}L"), clamp(f"((x - {spec.x0}L) * {g}) div {w}L")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION cell_of(x BIGINT, y BIGINT) RETURNS INT RETURN CAST({row} * {g} + {col} AS INT)")
    spark.udtf.register("layout_rects", LayoutRects)


def wkt(x: Column, y: Column) -> Column:
    return F.format_string("POINT(%d %d)", x, y)


def from_wkt(text: Column) -> tuple[Column, Column]:
    pick = lambda k: F.regexp_extract(text, r"POINT\((-?\d+) (-?\d+)\)", k).cast("long")
    return pick(1), pick(2)


def action_name(i: Column, j: Column, direction: Column) -> Column:
    return F.format_string("(%d,%d,%s)", i, j, F.when(direction == 0, F.lit("right")).otherwise(F.lit("down")))


@F.pandas_udf(T.BinaryType())
def wkb(x: pd.Series, y: pd.Series) -> pd.Series:
    """Little-endian WKB of points, for engines with geometry types."""
    head = (1).to_bytes(1, "little") + (1).to_bytes(4, "little")
    return pd.Series([head + np.array([a, b], "<f8").tobytes() for a, b in zip(x, y, strict=True)])
