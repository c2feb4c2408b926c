"""Point sets derived from the given tables with whole-number arithmetic, so any SQL engine gets the same points.

Each set is described once, as SQL text with a placeholder for whole-number division and the few functions whose
names differ between engines.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Dialect:
    div: str
    element: str
    seconds: str
    days: str
    spaces: str


SPARK = Dialect("div", "embedding[{i}]", "timestampdiff(SECOND, timestamp_ntz'2024-01-01 00:00:00', ts)", "datediff(l_shipdate, date'1995-01-01')", "char_length(text) - char_length(replace(text, ' ', ''))")
DUCKDB = Dialect("//", "embedding[{i}+1]", "date_diff('second', timestamp '2024-01-01 00:00:00', ts)", "date_diff('day', timestamp '1995-01-01', l_shipdate)", "length(text) - length(replace(text, ' ', ''))")


@dataclass(frozen=True)
class PointSet:
    tables: tuple[str, ...]
    on: str
    pid: str
    x: str
    y: str

    def sql(self, d: Dialect) -> str:
        """A SELECT over the tables in the dialect."""
        fill = lambda s: (
            s.replace("DIV", d.div).replace("E0", d.element.format(i=0)).replace("E1", d.element.format(i=1))
            .replace("SECONDS", d.seconds).replace("DAYS", d.days).replace("SPACES", d.spaces)
        )
        source = f" JOIN {self.tables[1]} ON {self.on}" if len(self.tables) > 1 else ""
        return f"SELECT {fill(self.pid)} AS pid, CAST({fill(self.x)} AS BIGINT) AS x, CAST({fill(self.y)} AS BIGINT) AS y FROM {self.tables[0]}{source}"


_K = "CAST(o_orderkey AS BIGINT)"
_N = "CAST(CASE WHEN c_nationkey < 10 THEN c_nationkey % 4 ELSE c_nationkey END AS BIGINT)"
_A, _B, _E, _F = (f"(({p} * {_K} + {q}) % {m})" for p, q, m in ((7919, 13, 10007), (5309, 71, 10009), (104729, 7, 10037), (3571, 3, 10039)))
_R = f"(40 + ((7 * {_N}) % 9) * 20)"
_CX, _CY = f"((37 * {_N} * {_N} + 11 * {_N} + 5) % 97)", f"((53 * {_N} + 29) % 89)"

POINT_SETS = {
    "geo_hot": PointSet(
        ("orders", "customer"), "o_custkey = c_custkey", _K,
        f"CASE WHEN {_K} % 10 = 0 THEN 200 * {_A} ELSE 16000 * {_CX} + 200000 + ((({_A} + {_B}) * {_R}) DIV 10) END",
        f"CASE WHEN {_K} % 10 = 0 THEN 120 * {_E} ELSE 9000 * {_CY} + 200000 + ((({_E} + {_F}) * {_R}) DIV 10) END",
    ),
    "events_xy": PointSet(("events",), "", "CAST(event_id AS BIGINT)", "SECONDS", "round(value * 1000)"),
    "embed_xy": PointSet(("embeddings",), "", "CAST(vec_id AS BIGINT)", "round(CAST(E0 AS DOUBLE) * 100000)", "round(CAST(E1 AS DOUBLE) * 100000)"),
    "lineitem_xy": PointSet(
        ("lineitem",), "", "concat_ws('-', CAST(l_orderkey AS STRING), CAST(l_linenumber AS STRING), CAST(l_partkey AS STRING), CAST(l_suppkey AS STRING), CAST(CAST(round(l_extendedprice * 100) AS BIGINT) AS STRING))",
        "round(l_extendedprice * 100)", "4000 * DAYS",
    ),
    "part_lattice": PointSet(("part",), "", "CAST(p_partkey AS BIGINT)", "CAST(round(p_retailprice * 10) AS BIGINT) * 100", "1000 * p_size"),
    "docs_diag": PointSet(("documents",), "", "CAST(doc_id AS BIGINT)", "10 * n_chars", "50 * (SPACES + 1)"),
    "sites": PointSet(("supplier",), "", "CAST(s_suppkey AS BIGINT)", "200 * ((7919 * CAST(s_suppkey AS BIGINT) + 13) % 10007)", "120 * ((104729 * CAST(s_suppkey AS BIGINT) + 7) % 10037)"),
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def points(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """pid, x, y of a point set. The scan reads the columns of the expressions alone; customers are joined as Spark's
    statistics say (a small side is broadcast under the session's own bound)."""
    s = POINT_SETS[name]
    df = table(spark, sf_dir, s.tables[0])
    if len(s.tables) > 1:
        df = df.join(table(spark, sf_dir, s.tables[1]), F.expr(s.on))
    select = s.sql(SPARK)
    cols = select[len("SELECT ") : select.index(" FROM ")]
    parts = cols.rsplit(" AS pid, ", 1)
    x, y = parts[1].rsplit(" AS x, ", 1)
    return df.select(F.expr(parts[0]).alias("pid"), F.expr(x).alias("x"), F.expr(y.removesuffix(" AS y")).alias("y"))


def clean(df: DataFrame) -> DataFrame:
    """Points with an id and both coordinates; a NaN or infinite coordinate counts as missing."""
    return df.where("pid is not null and x is not null and y is not null and not isnan(x) and not isnan(y) and abs(x) < 2e9 and abs(y) < 2e9").select("pid", F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"))


def hash_sample(df: DataFrame, per_mille: int, key: str = "pid") -> DataFrame:
    """A share of the rows chosen by whole-number arithmetic on the key: the same rows in any engine and every run."""
    return df.where(F.pmod(F.pmod(F.col(key), F.lit(1_000_003)) * 7919 + 13, F.lit(1000)) < per_mille)
