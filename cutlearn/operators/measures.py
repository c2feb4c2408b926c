"""Measures of layouts over points: balance, replication, the exact modelled cost, reductions and search curves."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cutlearn.operators.joins import bucket, owners, replicas
from cutlearn.plans.grid import GridSpec
from cutlearn.plans.layout import Layout


def region_counts(placed: DataFrame, m: int) -> DataFrame:
    """part, n for each of m regions, empty ones included. placed has a column part."""
    spark = placed.sparkSession
    every = spark.range(m).select(F.col("id").cast("int").alias("part"))
    return every.join(placed.groupBy("part").agg(F.count("*").alias("n")), "part", "left").select("part", F.coalesce("n", F.lit(0)).alias("n"))


def balance(counts: DataFrame) -> DataFrame:
    """One row: parts, total, largest, max_over_mean, stddev, gini of the counts of regions (part, n)."""
    ranked = counts.withColumn("k", F.row_number().over(Window.orderBy("n", "part")))  # M rows
    m, total = F.count("*"), F.sum("n")
    return ranked.agg(
        m.alias("parts"), total.alias("total"), F.max("n").alias("largest"),
        F.round(F.max("n") * m / total, 6).alias("max_over_mean"),
        F.round(F.stddev_pop("n"), 4).alias("stddev"),
        F.round(2 * F.sum(F.col("k") * F.col("n")) / (m * total) - (m + 1) / m, 6).alias("gini"),
    )


def replication(points: DataFrame, spec: GridSpec, layout: Layout, d: int) -> DataFrame:
    """part, owned, received: rows that live in a region, and rows it gets for a join at distance d."""
    m = len(layout.rects)
    own = region_counts(owners(points, spec, layout), m).withColumnRenamed("n", "owned")
    got = region_counts(replicas(points, spec, layout, d), m).withColumnRenamed("n", "received")
    return own.join(got, "part")


def exact_cost(points: DataFrame, spec: GridSpec, layout: Layout, ds: tuple[int, ...], local_index: bool) -> DataFrame:
    """d, cost_64: the modelled cost from exact counts, in 64ths: rows weigh 64, candidate pairs 1, copies sent 256."""
    out = None
    for d in ds:
        counts = replication(points, spec, layout, d)
        if local_index:
            key = lambda df: df.select("part", bucket(F.col("x"), spec.x0, d).alias("kx"), bucket(F.col("y"), spec.y0, d).alias("ky")).groupBy("part", "kx", "ky")
            left = key(owners(points, spec, layout)).agg(F.count("*").alias("a"))
            near = F.sequence(F.lit(-1), F.lit(1))
            left = left.withColumn("ox", F.explode(near)).withColumn("oy", F.explode(near)).select("part", (F.col("kx") + F.col("ox")).alias("kx"), (F.col("ky") + F.col("oy")).alias("ky"), "a")
            right = key(replicas(points, spec, layout, d)).agg(F.count("*").alias("b"))
            pairs = left.join(right, ["part", "kx", "ky"]).groupBy("part").agg(F.sum(F.col("a") * F.col("b")).alias("cand"))
            counts = counts.join(pairs, "part", "left").withColumn("cand", F.coalesce("cand", F.lit(0)))
        else:
            counts = counts.withColumn("cand", F.col("owned") * F.col("received"))
        cost = F.max(64 * (F.col("owned") + F.col("received")) + F.col("cand")) + 256 * (F.sum("received") - F.sum("owned"))
        row = counts.agg(cost.alias("cost_64")).select(F.lit(d).cast("long").alias("d"), "cost_64")
        out = row if out is None else out.union(row)
    return out


def reductions(times: DataFrame, ours: str, baseline: str) -> DataFrame:
    """case, method, seconds rows to case, best_other, vs_best_other, vs_baseline (per cent), win."""
    other = F.min(F.when(F.col("method") != ours, F.col("seconds")))
    mine, base = (F.max(F.when(F.col("method") == k, F.col("seconds"))) for k in (ours, baseline))
    return times.groupBy("case").agg(
        other.alias("best_other"), F.round(100 * (other - mine) / other, 1).alias("vs_best_other"),
        F.round(100 * (base - mine) / base, 1).alias("vs_baseline"), (mine < other).alias("win"),
    )


def best_so_far(history: DataFrame) -> DataFrame:
    """arm, episode, cost rows with best_cost, the running least of each arm."""
    w = Window.partitionBy("arm").orderBy("episode").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return history.withColumn("best_cost", F.min("cost").over(w))


def rewards(times: DataFrame) -> DataFrame:
    """layout, freq, best_s, now_s rows (a row per query) to the reward of each layout."""
    return times.groupBy("layout").agg(
        F.round(F.pow(F.sum(F.col("freq") * F.col("best_s") / F.greatest("now_s", F.lit(1e-9))), 2), 9).alias("mean_of_ratios"),
        F.round(F.pow(F.sum(F.col("freq") * F.col("best_s")) / F.sum(F.col("freq") * F.col("now_s")), 2), 9).alias("ratio_of_means"),
    )


def workload_times(times: DataFrame) -> DataFrame:
    return times.groupBy("layout").agg(F.round(F.sum(F.col("freq") * F.col("now_s")), 9).alias("workload_s"))


def state_frame(spark: SparkSession, hist: DataFrame, layout: Layout) -> DataFrame:
    """row, col, h, v, mass of every cell: the state as a table, joined from the histogram and the layout."""
    g = layout.g
    cells = spark.range(g * g).select((F.col("id") / g).cast("int").alias("row"), (F.col("id") % g).cast("int").alias("col"))
    rects = F.broadcast(layout.to_df(spark))  # M rows
    own = cells.join(rects, (cells.row >= rects.r0) & (cells.row < rects.r1) & (cells.col >= rects.c0) & (cells.col < rects.c1))
    filled = own.join(hist, ["row", "col"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    region = F.sum("n").over(Window.partitionBy("part_id"))
    total = F.sum("n").over(Window.partitionBy())  # g * g rows
    return filled.select("row", "col", (F.col("row") == F.col("r0")).cast("int").alias("h"), (F.col("col") == F.col("c0")).cast("int").alias("v"), F.round(F.col("n") * region / (total * total), 12).alias("mass"))
