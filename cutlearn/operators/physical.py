"""Placing rows: on tasks, in files and in tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutlearn.operators.cells import zorder
from cutlearn.plans.grid import GridSpec
from cutlearn.plans.layout import Layout, assign


def place(points: DataFrame, spec: GridSpec, layout: Layout, m: int | None = None) -> DataFrame:
    """points with part, each region in a task of its own."""
    return assign(points, spec, layout).repartitionById(m or len(layout.rects), F.col("part"))


def place_finely(points: DataFrame, spec: GridSpec, layout: Layout, buckets: int, tasks: int) -> DataFrame:
    """For many more executors than regions: part, and a bucket inside it, dealt together over `tasks` tasks. A hot
    region spreads over its buckets and the region still decides which files hold it."""
    placed = assign(points, spec, layout).withColumn("bucket", F.pmod(F.xxhash64("pid"), F.lit(buckets)).cast("int"))
    return placed.repartition(tasks, "part", "bucket")


def write_regions(points: DataFrame, spec: GridSpec, layout: Layout, path: str) -> None:
    """Parquet in a folder per region, rows in Z-order, so box filters skip folders and row groups."""
    placed = place(points, spec, layout).withColumn("z", zorder(spec.row(F.col("y")), spec.col(F.col("x"))))
    placed.sortWithinPartitions("part", "z").drop("z").write.mode("overwrite").partitionBy("part").parquet(path)
