"""Range and nearest-neighbour search, exact, with ties broken by id."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutlearn.operators.joins import bucket
from cutlearn.plans.grid import GridSpec, prefix
from cutlearn.plans.layout import Layout


def regions_of_box(spec: GridSpec, layout: Layout, x0: int, y0: int, x1: int, y1: int) -> list[int]:
    a, b, c, d = spec.row_of(y1), spec.row_of(y0), spec.col_of(x0), spec.col_of(x1)
    return sorted({int(v) for v in layout.lookup[a : b + 1, c : d + 1].ravel()})


def range_query(points: DataFrame, x0: int, y0: int, x1: int, y1: int, spec: GridSpec | None = None, layout: Layout | None = None) -> DataFrame:
    """Points in a closed box. On points stored by region (column part) only the regions that meet the box are read."""
    box = F.col("x").between(x0, x1) & F.col("y").between(y0, y1)
    if layout is not None and "part" in points.columns:
        box &= F.col("part").isin(regions_of_box(spec, layout, x0, y0, x1, y1))
    return points.where(box)


def radius_filter(points: DataFrame, x: int, y: int, d: int) -> DataFrame:
    near = F.col("x").between(x - d, x + d) & F.col("y").between(y - d, y + d)
    return points.where(near & ((F.col("x") - x) * (F.col("x") - x) + (F.col("y") - y) * (F.col("y") - y) <= d * d))


def haversine(lon1, lat1, lon2, lat2):
    """Great-circle metres between columns of degrees, on a sphere of mean earth radius."""
    half = lambda a, b: F.pow(F.sin((F.radians(b) - F.radians(a)) / 2), 2)
    return 2 * 6_371_008.8 * F.asin(F.sqrt(half(lat1, lat2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * half(lon1, lon2)))


def safe_radius(hist: np.ndarray, spec: GridSpec, x: int, y: int, k: int) -> int:
    """A radius around (x, y) that surely holds k points: rings of cells are added until their counts reach k."""
    r, c = spec.row_of(y), spec.col_of(x)
    for ring in range(spec.g + 1):
        if hist[max(0, r - ring) : r + ring + 1, max(0, c - ring) : c + ring + 1].sum() >= k:
            break
    dx, dy = (ring + 1) * math.ceil(spec.width / spec.g), (ring + 1) * math.ceil(spec.height / spec.g)
    off_x, off_y = max(spec.x0 - x, x - spec.x1, 0), max(spec.y0 - y, y - spec.y1, 0)
    return math.isqrt((dx + off_x) ** 2 + (dy + off_y) ** 2) + 1


def knn_query(points: DataFrame, x: int, y: int, k: int, spec: GridSpec, hist: np.ndarray) -> DataFrame:
    """pid, d2 of the k nearest points; one pruned scan and a bounded top-k."""
    near = radius_filter(points, x, y, safe_radius(hist, spec, x, y, k))
    return near.select("pid", ((F.col("x") - x) * (F.col("x") - x) + (F.col("y") - y) * (F.col("y") - y)).alias("d2")).orderBy("d2", "pid").limit(k)


def knn_join(a: DataFrame, b: DataFrame, k: int, spec: GridSpec, hist: np.ndarray) -> DataFrame:
    """pid_a, pid_b, d2, rank of the k nearest b for each a. hist counts b on the grid of spec; a finer grid gives
    tighter radii. Each cell's safe radius groups the left
    rows into classes of doubling radius; a class joins on buckets of its own size, so sparse cells don't make dense
    ones look far. The last step keeps k rows for each left point."""
    g = spec.g
    cell = math.hypot(spec.width / g, spec.height / g)
    sums, at, ring = prefix(hist), np.arange(g), np.full((g, g), g, np.int64)
    for n in range(g - 1, -1, -1):
        lo, hi = np.maximum(at - n, 0), np.minimum(at + n + 1, g)
        held = sums[np.ix_(hi, hi)] - sums[np.ix_(lo, hi)] - sums[np.ix_(hi, lo)] + sums[np.ix_(lo, lo)]
        ring[held >= k] = n
    radius = np.ceil((ring + 1) * cell).astype(np.int64) + 1
    sizes = (np.ceil(np.log2(radius))).astype(np.int64)
    side_of = F.element_at(F.array(*[F.lit(int(1) << int(v)) for v in sizes.ravel()]), (spec.row(F.col("y")) * g + spec.col(F.col("x")) + 1).cast("int"))
    near = F.sequence(F.lit(-1), F.lit(1))
    key = lambda v, o, s: F.floor((v - o) / s).cast("long")
    left = a.select(F.col("pid").alias("pid_a"), F.col("x").alias("ax"), F.col("y").alias("ay"), side_of.alias("side"))
    left = left.withColumn("ox", F.explode(near)).withColumn("oy", F.explode(near))
    left = left.withColumns({"kx": key(F.col("ax"), spec.x0, F.col("side")) + F.col("ox"), "ky": key(F.col("ay"), spec.y0, F.col("side")) + F.col("oy")})
    classes = sorted({int(1) << int(v) for v in sizes.ravel()})
    right = b.select(F.col("pid").alias("pid_b"), F.col("x").alias("bx"), F.col("y").alias("by"), F.explode(F.array(*[F.lit(s) for s in classes])).alias("side"))
    right = right.withColumns({"kx": key(F.col("bx"), spec.x0, F.col("side")), "ky": key(F.col("by"), spec.y0, F.col("side"))})
    dx, dy = F.col("ax") - F.col("bx"), F.col("ay") - F.col("by")
    joined = left.join(right, ["side", "kx", "ky"]).select("pid_a", "pid_b", (dx * dx + dy * dy).alias("d2"))
    w = Window.partitionBy("pid_a").orderBy("d2", "pid_b")
    return joined.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def asof(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """left rows (key, time and more) with last_<value>: the value of the latest right row of their key at or before
    them. A union and one running window per key; no join. Ties in time: the largest value."""
    cols = [c for c in left.columns if c not in (key, time)]
    l = left.select(key, time, *cols, F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"))
    r = right.select(key, time, *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in cols], F.col(value).alias("_v"), F.lit(0).alias("_side"))
    w = Window.partitionBy(key).orderBy(time, "_side", F.col("_v").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return l.unionByName(r).withColumn(f"last_{value}", F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_v", "_side")


def interval_join(a: DataFrame, b: DataFrame, width: int) -> DataFrame:
    """pid_a, pid_b of rows (pid, t) whose times differ by at most width: bucket keys of that width, three probed."""
    left = a.select(F.col("pid").alias("pid_a"), F.col("t").alias("ta"), (F.floor(F.col("t") / width)).alias("k0")).withColumn("k", F.explode(F.array(F.col("k0") - 1, F.col("k0"), F.col("k0") + 1)))
    right = b.select(F.col("pid").alias("pid_b"), F.col("t").alias("tb"), F.floor(F.col("t") / width).alias("k"))
    return left.join(right, "k").where((F.abs(F.col("ta") - F.col("tb")) <= width) & (F.col("pid_a") < F.col("pid_b"))).select("pid_a", "pid_b")


__all__ = ["asof", "bucket", "haversine", "interval_join", "knn_join", "knn_query", "radius_filter", "range_query", "regions_of_box", "safe_radius"]
