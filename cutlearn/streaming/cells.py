"""Keeping cell counts and drift up to date over a stream of events."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from cutlearn.plans.grid import GridSpec
from cutlearn.plans.layout import Layout

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
LATE = "10 minutes"
#: Weight of the newest day in a smoothed cell count.
WEIGHT = 0.3


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events as a stream of files: pid, x, y, event_type and at (a timestamp; the session's zone is UTC)."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.select(
        F.col("event_id").alias("pid"), F.expr("cast(timestampdiff(SECOND, timestamp_ntz'2024-01-01 00:00:00', ts) as bigint)").alias("x"),
        F.round(F.col("value") * 1000).cast("long").alias("y"), "event_type", F.col("ts").cast("timestamp").alias("at"),
    ).withWatermark("at", LATE)


def with_cells(stream: DataFrame, spec: GridSpec) -> DataFrame:
    return stream.withColumns({"row": spec.row(F.col("y")), "col": spec.col(F.col("x"))})


def tumbling(stream: DataFrame, spec: GridSpec, width: str = "1 day") -> DataFrame:
    return with_cells(stream, spec).groupBy(F.window("at", width), "row", "col").agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("win"), "row", "col", "n")


def sliding(stream: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    return stream.groupBy(F.window("at", width, step), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("win"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "5 minutes") -> DataFrame:
    return stream.groupBy(F.session_window("at", gap), "event_type").agg(F.count("*").alias("n")).select(F.col("session_window.start").cast("timestamp_ntz").alias("win"), "event_type", "n")


DAY_MS = 86_400_000


def _smoother(weight: float):
    def smooth(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        """The state holds the counts of open days, the last closed day and the smoothed count up to it. A day is
        closed by the watermark, never by a later day, so the order in which events come changes nothing."""
        days, counts, last, level = state.get if state.exists else ([], [], None, 0.0)
        still = dict(zip(days, counts, strict=True))
        for frame in () if state.hasTimedOut else frames:
            for d, n in frame["day"].value_counts().items():
                if last is None or d > last:
                    still[int(d)] = still.get(int(d), 0) + int(n)
        mark = state.getCurrentWatermarkMs()
        rows = []
        for d in sorted(d for d in still if (d + 1) * DAY_MS <= mark):
            level = level * (1 - weight) ** (d - last if last is not None else 0) + weight * still[d]
            rows.append((d, still.pop(d), level))
            last = d
        days = sorted(still)
        state.update((days, [still[d] for d in days], last, level))
        if days:
            state.setTimeoutTimestamp((days[0] + 1) * DAY_MS)
        if rows:
            out = pd.DataFrame(rows, columns=["day", "n", "level"])
            yield out.assign(row=key[0], col=key[1])[["row", "col", "day", "n", "level"]]

    return smooth


def smoothed(stream: DataFrame, spec: GridSpec, weight: float = WEIGHT) -> DataFrame:
    """win, row, col, n, level: closed days of each cell with an exponentially smoothed count; days without events fade
    it. A custom stateful operator: a cell's state is a number and its open days. Append mode."""
    days = with_cells(stream, spec).select("row", "col", F.datediff("at", F.lit("1970-01-01")).cast("long").alias("day"), "at")
    out = days.groupBy("row", "col").applyInPandasWithState(
        _smoother(weight), "row int, col int, day long, n long, level double", "days array<long>, counts array<long>, last long, level double", "append", GroupStateTimeout.EventTimeTimeout
    )
    return out.select(F.date_from_unix_date(F.col("day").cast("int")).cast("timestamp_ntz").alias("win"), "row", "col", "n", F.round("level", 9).alias("level"))


def by_region(stream: DataFrame, spec: GridSpec, layout: Layout) -> DataFrame:
    """A stream joined with a fixed layout: events per region and day; points off the map count to its border cells."""
    placed = stream.withColumn("part", layout.part(spec.row(F.col("y")), spec.col(F.col("x"))))
    return placed.groupBy(F.window("at", "1 day"), "part").agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("win"), "part", "n")


def distinct_events(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(["pid"]).groupBy("event_type").agg(F.count("*").alias("n"))


def drained(out: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over what there is, into a table in memory; for tests and small results."""
    name = f"stream_{uuid.uuid4().hex}"
    q = out.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return out.sparkSession.table(name)


def drift(now: DataFrame, learned: DataFrame) -> DataFrame:
    """Total variation distance of two cell histograms (row, col, n): 0 for equal shares, 1 for disjoint ones."""
    share = lambda df, c: df.crossJoin(F.broadcast(df.agg(F.sum("n").alias("t")))).select("row", "col", (F.col("n") / F.col("t")).alias(c))  # noqa: E731  one row beside the cells
    both = share(now, "a").join(share(learned, "b"), ["row", "col"], "full")
    return both.agg(F.round(F.sum(F.abs(F.coalesce("a", F.lit(0.0)) - F.coalesce("b", F.lit(0.0)))) / 2, 9).alias("drift"))


def apply_layout(stream: DataFrame, spec: GridSpec, layouts, path: str):
    """A foreachBatch sink that places each batch by the newest of `layouts()` (version, layout) and writes it under
    that version, so a layout learned meanwhile is picked up by the next batch. A batch that is run again overwrites
    its own folder."""

    def write(batch: DataFrame, batch_id: int) -> None:
        version, layout = layouts()
        placed = batch.withColumn("part", layout.part(spec.row(F.col("y")), spec.col(F.col("x"))))
        placed.write.mode("overwrite").partitionBy("part").parquet(f"{path}/version={version}/batch={batch_id}")

    return stream.writeStream.foreachBatch(write)
