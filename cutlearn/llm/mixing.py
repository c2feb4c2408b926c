"""Mixing sources to target weights by pivotal dependent rounding.

Each source's share of the mix, divided by its size, is how many times each of its documents should be taken. The
whole part is taken outright. The fractional parts are rounded by pivotal steps: two documents meet, and words move
at random from one to the other until one of them is wholly in or wholly out; the odds of the two directions keep
every document's expected share. A step moves words, not probability, so the words of the pair stay the same and a
source's taken words don't drift. Steps run inside blocks of BLOCK documents; each block leaves at most one document
undecided, and the undecided ones meet again as blocks of the next level: a reduction tree that ends with at most one
undecided document in each source. That one is taken in part (`partial`, so the source meets its target to a word)
or rounded at random (`whole`).

Randomness comes from hashes of the seed and the document, so reruns agree. Defined cases: size of a null text is 0,
and such documents take 0; sources rank by code point with null last; a source without words has target 0; repeated
rows are documents of their own; an empty table gives an empty mix.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutlearn.llm import textblocks as tb
from cutlearn.llm.session import cut, shuffle_parts

WEIGHTS = (5, 2, 1)
TOTAL_SHARE, MOST = 1.5, 2.0
BLOCK = 1_000
SEED = 7
EPS = 1e-9
WORD = r"[^\x20\x09-\x0D]+"

ROUNDED = "source string, doc_id long, size long, share double, settled boolean"


def sized(docs: DataFrame) -> DataFrame:
    """source, doc_id, size."""
    return docs.select("source", F.col("doc_id").cast("long"), F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long").alias("size"))


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, total: float = TOTAL_SHARE, most: float = MOST) -> DataFrame:
    """source, source_size, target. Sources are dealt by ranges of their names and ranked inside each, so however many
    there are, no task sees them all."""
    n, spark = shuffle_parts(sizes.sparkSession), sizes.sparkSession
    rows = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_docs"))
    rows = cut(rows.repartitionByRange(n, F.col("source").asc_nulls_last()).withColumn("range", F.spark_partition_id()))
    held = dict(rows.groupBy("range").agg(F.count("*").alias("n")).collect())  # a row per range
    before = spark.createDataFrame([(k, sum(m for j, m in held.items() if j < k)) for k in sorted(held)], "range int, before long")
    rank = F.row_number().over(Window.partitionBy("range").orderBy(F.col("source").asc_nulls_last())) - 1 + F.col("before")
    weight = F.element_at(F.array(*map(F.lit, weights)), (rank % len(weights) + 1).cast("int")).cast("double")
    rows = cut(rows.join(F.broadcast(before), "range").withColumn("weight", weight).drop("range", "before"))
    limit = most * F.col("source_size")
    whole = rows.agg(F.sum("source_size")).first()[0] or 0
    per_weight = 0.0
    while True:
        # sources that stay under their limit share what the others leave; the level only rises
        full = limit <= per_weight * F.col("weight")
        used, free = rows.agg(F.sum(F.when(full, limit).otherwise(0.0)), F.sum(F.when(full, 0.0).otherwise(F.col("weight")))).first()
        level = (total * whole - used) / free if free else per_weight
        if level <= per_weight * (1 + 1e-12):
            break
        per_weight = level
    return rows.select("source", "source_size", "n_docs", F.least(limit, per_weight * F.col("weight")).alias("target"))


def _uniform(*parts: np.ndarray) -> np.ndarray:
    h = np.full(len(parts[0]), SEED, np.uint64)
    for p in parts:
        h = tb.mix(h * tb.GOLDEN + p)
    return (h >> np.uint64(11)).astype(np.float64) / 2**53


def pivot(size: np.ndarray, share: np.ndarray, draw: np.ndarray) -> int | None:
    """Settles shares in place, in order; returns the row that stays undecided, if one does."""
    held = None
    sizes, shares, draws = size.tolist(), share.tolist(), draw.tolist()
    for i, (s, p) in enumerate(zip(sizes, shares, strict=True)):
        if p <= EPS or p >= 1 - EPS or not s:
            shares[i] = float(p >= 1 - EPS) if s else 0.0
            continue
        if held is None:
            held = i
            continue
        q, t = shares[held], sizes[held]
        give, take = min(q * t, (1 - p) * s), min((1 - q) * t, p * s)  # words from held to i, and back
        if draws[i] * (give + take) < take:
            q, p = q - give / t, p + give / s
        else:
            q, p = q + take / t, p - take / s
        loose = []
        for k, x in ((held, q), (i, p)):
            if x <= EPS or x >= 1 - EPS:
                shares[k] = float(round(x))
            else:
                shares[k] = x
                loose.append(k)
        held = loose[0] if loose else None
    share[:] = shares
    return held


def _rounder(level: int):
    def settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows of a (source, block) are together, in order; a block that goes on in the next batch is carried."""
        rest: pa.Table | None = None

        def blocks(t: pa.Table, last: bool) -> tuple[pa.Table | None, pa.Table | None]:
            block, source = np.asarray(t["block"]), t["source_hash"].to_numpy()
            edge = np.flatnonzero(np.concatenate([[True], (block[1:] != block[:-1]) | (source[1:] != source[:-1])]))
            stop = len(block) if last else edge[-1]
            size, share, ids = (t[c].to_numpy().copy() for c in ("size", "share", "id_hash"))
            draw = _uniform(ids.view(np.uint64), np.full(len(ids), level, np.uint64))
            settled = np.ones(len(block), bool)
            for a, z in zip(edge, [*edge[1:], len(block)], strict=True):
                if a < stop and (k := pivot(size[a:z], share[a:z], draw[a:z])) is not None:
                    settled[a + k] = False
            done = t.slice(0, stop).select(["source", "doc_id", "size"])
            done = done.append_column("share", pa.array(share[:stop])).append_column("settled", pa.array(settled[:stop]))
            return done, t.slice(stop)

        for batch in batches:
            t = pa.Table.from_batches([batch])
            t = pa.concat_tables([rest, t]).combine_chunks() if rest is not None and rest.num_rows else t
            if t.num_rows:
                done, rest = blocks(t, False)
                yield from done.combine_chunks().to_batches()
        if rest is not None and rest.num_rows:
            done, _ = blocks(rest.combine_chunks(), True)
            yield from done.combine_chunks().to_batches()

    return settle


def _round(rows: DataFrame, counts: DataFrame, block: int, level: int) -> DataFrame:
    """rows: source, doc_id, size, share. counts: source, n_docs, one row per source."""
    n = shuffle_parts(rows.sparkSession)
    dealt = rows.join(F.broadcast(counts) if counts.count() <= 10_000 else counts, rows.source.eqNullSafe(counts.source)).select(
        rows.source, "doc_id", "size", "share",
        F.xxhash64(rows.source).alias("source_hash"),
        F.xxhash64("doc_id", "size").alias("id_hash"),
        F.pmod(F.xxhash64(F.lit(level), "doc_id"), F.ceil(F.col("n_docs") / block).cast("long")).alias("block"),
    )
    dealt = dealt.repartition(n, "source_hash", "block").sortWithinPartitions("source_hash", "block", "doc_id", "size")
    return dealt.mapInArrow(_rounder(level), ROUNDED)


def mix(docs: DataFrame, block: int = BLOCK, last: str = "partial", weights: tuple[int, ...] = WEIGHTS, total: float = TOTAL_SHARE, most: float = MOST) -> DataFrame:
    """doc_id, source, size, source_size, target, copies (double; whole unless the document is the one taken in part),
    taken (words)."""
    sizes = cut(sized(docs))
    goal = cut(targets(sizes, weights, total, most))
    small = goal.count() <= 10_000
    plan = F.broadcast(goal) if small else goal
    each = sizes.join(plan, sizes.source.eqNullSafe(goal.source)).drop(goal.source)
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    near = F.round(ratio)
    ratio = F.when(F.abs(ratio - near) < 1e-9, near).otherwise(ratio)
    level, settled, rows, counts = 0, [], each.select("source", "doc_id", "size", (ratio - F.floor(ratio)).alias("share")), goal.select("source", "n_docs")
    while True:
        out = cut(_round(rows, counts, block, level))
        settled.append(out.where("settled").select("source", "doc_id", "size", "share"))
        rows = out.where("not settled").select("source", "doc_id", "size", "share")
        counts = rows.groupBy("source").agg(F.count("*").alias("n_docs"))
        level += 1
        if not counts.where("n_docs > 1").limit(1).count():
            break
        counts = cut(counts)
    if last == "whole":
        draw = F.pmod(F.xxhash64(F.lit(SEED), "doc_id", "size"), F.lit(1 << 30)) / float(1 << 30)
        rows = rows.withColumn("share", F.when(draw < F.col("share"), 1.0).otherwise(0.0))
    settled.append(rows)
    every = settled[0]
    for x in settled[1:]:
        every = every.unionByName(x)
    joined = every.join(plan, every.source.eqNullSafe(goal.source)).drop(goal.source)
    copies = F.floor(ratio) + F.col("share")
    return joined.select("doc_id", "source", "size", "source_size", "target", copies.alias("copies"), F.round(copies * F.col("size")).cast("long").alias("taken"))


def mixed_documents(docs: DataFrame) -> DataFrame:
    """docs with a column copy (replaced, if there is one), a row for each time that the mix takes a document; the mix
    takes whole texts only. Repeated rows with equal doc_id, source and size share their copies evenly, rounded up."""
    plan = mix(docs, last="whole").groupBy("doc_id", "source", "size").agg(F.sum("copies").cast("long").alias("copies"), F.count("*").alias("times"))
    size = F.coalesce(F.regexp_count(docs.text, F.lit(WORD)), F.lit(0)).cast("long")
    same = docs.doc_id.eqNullSafe(plan.doc_id) & docs.source.eqNullSafe(plan.source) & (size == plan["size"])
    each = F.ceil(plan.copies / plan.times).cast("int")
    return docs.join(plan.where("copies > 0"), same).select(*(docs[c] for c in docs.columns if c != "copy"), F.explode(F.sequence(F.lit(1), each)).alias("copy"))
