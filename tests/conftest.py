import sys
from pathlib import Path

import pytest
from pyspark.sql import SparkSession

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    s = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4").config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "4g").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.warehouse.dir", str(tmp_path_factory.mktemp("warehouse")))
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="session")
def duck():
    import duckdb

    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def plain(v):
    import datetime

    import numpy as np
    import pandas as pd

    if v is None or v is pd.NaT or isinstance(v, float) and np.isnan(v):
        return ""
    if isinstance(v, datetime.datetime):
        return str(pd.Timestamp(v))
    if isinstance(v, bool | np.bool_):
        return str(bool(v))
    if isinstance(v, float | int | np.integer | np.floating):
        return f"{float(v):.9g}" if abs(v) < 1e9 else str(v)
    return str(v)


def same_rows(df, duck, sql):
    """Whether the rows of a DataFrame and of a SQL text are equal, in any order."""
    cols = sorted(df.columns)
    ours = sorted(tuple(plain(r[c]) for c in cols) for r in df.collect())
    d = duck.sql(sql)
    at = [list(d.columns).index(c) for c in cols]
    return sorted(d.columns) == cols and ours == sorted(tuple(plain(r[k]) for k in at) for r in d.fetchall())
