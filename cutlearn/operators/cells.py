"""Aggregates, windows and orders over cells."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cutlearn.plans.grid import GridSpec


def ranks(hist: DataFrame) -> DataFrame:
    """Cells with dense_rank and percent_rank by count. At most g * g rows are ranked in one task."""
    w = Window.orderBy(F.col("n").desc())
    return hist.select("row", "col", "n", F.dense_rank().over(w).alias("dense_rank"), F.round(F.percent_rank().over(w), 9).alias("percent_rank"))


def top_cells(hist: DataFrame, k: int) -> DataFrame:
    return hist.orderBy(F.col("n").desc(), "row", "col").limit(k)


def prefix_sums(hist: DataFrame) -> DataFrame:
    """Count of each cell and all above and left of it, from two running sums over the occupied cells' full grid."""
    rows, cols = hist.select("row").distinct(), hist.select("col").distinct()
    full = rows.crossJoin(cols).join(hist, ["row", "col"], "left").select("row", "col", F.coalesce("n", F.lit(0)).alias("n"))  # at most g * g rows
    run = lambda p, o: Window.partitionBy(p).orderBy(o).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return full.withColumn("s", F.sum("n").over(run("row", "col"))).withColumn("s", F.sum("s").over(run("col", "row"))).select("row", "col", F.col("s").alias("total"))


def sweep_gaps(points: DataFrame, spec: GridSpec) -> DataFrame:
    """Gap in x to the point before and after in the same row of cells."""
    w = Window.partitionBy("row").orderBy("x", "pid")
    p = points.withColumn("row", spec.row(F.col("y")))
    return p.select("pid", "row", (F.col("x") - F.lag("x").over(w)).alias("gap_before"), (F.lead("x").over(w) - F.col("x")).alias("gap_after"))


def band_counts(points: DataFrame, spec: GridSpec, d: int) -> DataFrame:
    """How many points of the same row of cells lie within d along x, itself included."""
    w = Window.partitionBy("row").orderBy("x").rangeBetween(-d, d)
    return points.withColumn("row", spec.row(F.col("y"))).select("pid", F.count("*").over(w).alias("n_band"))


def zorder(row: Column, col: Column, bits: int = 5) -> Column:
    """Interleaved bits of row and column: neighbours in the key are mostly neighbours on the map."""
    out = F.lit(0)
    for k in range(bits):
        out = out + F.shiftleft(F.shiftright(col, k).bitwiseAND(F.lit(1)), 2 * k) + F.shiftleft(F.shiftright(row, k).bitwiseAND(F.lit(1)), 2 * k + 1)
    return out


def hilbert(row: Column, col: Column, bits: int = 5) -> Column:
    """Place of a cell on the Hilbert curve of a 2^bits square, as a nested expression."""
    x, y, d = col, row, F.lit(0)
    for k in range(bits - 1, -1, -1):
        rx, ry = F.shiftright(x, k).bitwiseAND(F.lit(1)), F.shiftright(y, k).bitwiseAND(F.lit(1))
        d = d + (F.lit(3) * rx).bitwiseXOR(ry) * (1 << (2 * k))
        x, y = x.bitwiseAND(F.lit((1 << k) - 1)), y.bitwiseAND(F.lit((1 << k) - 1))
        flip = (ry == 0) & (rx == 1)
        fx, fy = F.when(flip, (1 << k) - 1 - x).otherwise(x), F.when(flip, (1 << k) - 1 - y).otherwise(y)
        x, y = F.when(ry == 0, fy).otherwise(fx), F.when(ry == 0, fx).otherwise(fy)
    return d


def hot_cells(hist: DataFrame, m: int) -> DataFrame:
    """Cells heavier than a fair share of m regions: no layout on this grid can balance them; refine or salt them."""
    total = hist.agg(F.sum("n").alias("total"))
    return hist.crossJoin(F.broadcast(total)).where(F.col("n") * m > F.col("total")).select("row", "col", "n")  # one row beside g * g
