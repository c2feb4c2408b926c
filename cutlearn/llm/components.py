"""Connected components of a link table by alternating star contraction, all in DataFrames.

Each round points a node's larger neighbours, then its smaller ones, at the least node it sees. Rounds end when the
links no longer change; every round is cut off in the shared checkpoint folder. Only a count and a checksum reach
the driver. Sums and minima are pre-aggregated, so a node with very many links doesn't gather in one task.

A counted table of at most FEW links is joined by union-find in a single task instead: the result is the same, without
the dozens of small exchanges of the rounds.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutlearn.llm.session import cut

FEW = 50_000


def _union(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links u, m (at most FEW) to node, root."""
    above: dict[int, int] = {}

    def root(x: int) -> int:
        while (up := above.setdefault(x, x)) != x:
            above[x] = above[up]
            x = up
        return x

    for batch in batches:
        for u, m in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            a, b = root(u), root(m)
            above[max(a, b)] = min(a, b)
    found = [(x, r) for x in list(above) if (r := root(x)) != x]
    yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.int64()) for k in (0, 1)], ["node", "root"])


def _sum(links: DataFrame) -> tuple:
    return tuple(links.agg(F.count("*"), F.sum(F.pmod(F.xxhash64("u", "m"), F.lit((1 << 31) - 1)))).first())


def star_components(links: DataFrame, rounds: int = 60, few: int = FEW) -> DataFrame:
    """links: a, b (long, either way round, repeats and loops allowed). Returns node, root (the least node of its
    component) for each node of a link between different nodes."""
    now = cut(
        links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("m")).distinct()
    )
    before = _sum(now)
    if before[0] <= few:
        return now.coalesce(1).mapInArrow(_union, "node long, root long")
    for _ in range(rounds):
        if not before[0]:
            break
        both = now.select("u", "m").union(now.select(F.col("m").alias("u"), F.col("u").alias("m")))
        least = both.groupBy("u").agg(F.least(F.min("m"), F.col("u")).alias("r"))
        large = both.join(least, "u").where("m > u").select(F.col("m").alias("u"), F.col("r").alias("m")).where("u <> m").distinct()
        down = large.groupBy("u").agg(F.min("m").alias("r"))
        small = large.join(down, "u")
        now = cut(
            small.where("m <> r").select(F.col("m").alias("u"), F.col("r").alias("m"))
            .union(small.select("u", F.col("r").alias("m"))).where("u <> m").distinct()
        )
        after = _sum(now)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("components did not settle")
    return now.groupBy(F.col("u").alias("node")).agg(F.min("m").alias("root"))
