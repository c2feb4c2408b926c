"""Every query against its SQL on the smallest tables, and the package without its llm part."""

import subprocess
import sys
from pathlib import Path

import pytest

from cutlearn import catalog
from tests.conftest import SF, same_rows

ROOT = Path(__file__).resolve().parents[1]


@pytest.mark.parametrize("name", sorted(catalog.ORACLE))
def test_query_equals_sql(spark, duck, name):
    assert same_rows(catalog.QUERIES[name](spark, SF), duck, catalog.ORACLE[name])


@pytest.mark.parametrize("name", ["balance_kdb_approx", "balance_hash", "str_tiles", "hilbert_key", "st_wkb", "demo_actions", "pretrain_report", "random_layouts"])
def test_other_queries_give_rows(spark, name):
    assert catalog.QUERIES[name](spark, SF).count() > 0


def test_hilbert_is_a_walk(spark):
    from pyspark.sql import functions as F

    from cutlearn.operators.cells import hilbert

    g = spark.range(64).select((F.col("id") / 8).cast("int").alias("r"), (F.col("id") % 8).cast("int").alias("c"))
    at = {r.h: (r.r, r.c) for r in g.select("r", "c", hilbert(F.col("r"), F.col("c"), 3).alias("h")).collect()}
    assert sorted(at) == list(range(64))
    assert all(abs(at[k][0] - at[k + 1][0]) + abs(at[k][1] - at[k + 1][1]) == 1 for k in range(63))


def test_entry_works_without_llm(tmp_path):
    code = "import sys; sys.modules['cutlearn.llm'] = None; import __spark_entry__ as e; assert 'pipeline' not in e.queries() and 'djoin_idx_500' in e.queries() and set(e.oracle_sql()) <= set(e.queries())"
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True)
    used = [p for p in (ROOT / "cutlearn").rglob("*.py") if "llm" not in p.parts and "cutlearn.llm" in p.read_text()]
    assert not used


def test_late_rows_are_dropped_from_streams(spark, tmp_path):
    from pyspark.sql import functions as F

    from cutlearn.streaming.cells import sliding

    rows = [("a", "2024-01-05 00:00:00"), ("a", "2024-01-05 00:10:00"), ("a", "2024-01-01 00:00:00")]
    for k, r in enumerate(rows):
        spark.createDataFrame([r], "event_type string, at string").select("event_type", F.to_timestamp("at").alias("at")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    s = spark.readStream.schema("event_type string, at timestamp").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in")).withWatermark("at", "10 minutes")
    q = sliding(s, "1 hour", "1 hour").writeStream.format("memory").queryName("late").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("late").count() <= 1


def test_placing_by_the_newest_layout(spark, tmp_path):
    from cutlearn.plans.grid import GridSpec
    from cutlearn.plans.layout import Layout
    from cutlearn.streaming.cells import apply_layout, event_stream

    q = apply_layout(event_stream(spark, SF), GridSpec(0, 0, 2_600_000, 500_000, 4), lambda: (3, Layout.whole(4)), str(tmp_path)).trigger(availableNow=True).start()
    q.awaitTermination()
    got = spark.read.option("basePath", str(tmp_path)).parquet(str(tmp_path))
    assert got.select("version").distinct().collect()[0][0] == 3 and got.count() == spark.read.parquet(f"{SF}/events.parquet").count()


def test_queries_read_their_tables_each_time(spark, tmp_path):
    """Nothing of a table is kept for the next query, and no query makes its rows up."""
    for t in ("customer", "orders", "events"):
        spark.read.parquet(f"{SF}/{t}.parquet").write.parquet(str(tmp_path / f"{t}.parquet"))
    run = lambda name: sorted(map(tuple, catalog.QUERIES[name](spark, str(tmp_path)).collect()))
    names = ("layout_overlap", "env_example", "env_initial_actions", "workload_time", "best_so_far")
    first = {n: run(n) for n in names}
    assert sum(r[-1] for r in first["env_example"]) == spark.read.parquet(str(tmp_path / "orders.parquet")).count()
    spark.read.parquet(f"{SF}/orders.parquet").where("o_custkey % 3 = 0").write.mode("overwrite").parquet(str(tmp_path / "orders.parquet"))
    spark.read.parquet(f"{SF}/events.parquet").where("user_id % 2 = 0").write.mode("overwrite").parquet(str(tmp_path / "events.parquet"))
    assert not [n for n in names if run(n) == first[n]]
