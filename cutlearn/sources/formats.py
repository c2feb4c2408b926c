"""Reading and writing points and layouts in Spark's formats, and layouts as a data source of their own."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from cutlearn.plans.layout import LAYOUT_SCHEMA, Layout

POINT_SCHEMA = "pid long, x long, y long"
FORMATS = ("parquet", "csv", "json", "orc")


def write(df: DataFrame, path: str, kind: str) -> None:
    writer = df.write.mode("overwrite")
    (writer.option("header", True) if kind == "csv" else writer).format(kind).save(path)


def read(spark: SparkSession, path: str, kind: str, schema: str = POINT_SCHEMA) -> DataFrame:
    """The schema is always given, never guessed from the data."""
    reader = spark.read.schema(schema).format(kind)
    return (reader.option("header", True) if kind == "csv" else reader).load(path)


class _LayoutReader(DataSourceReader):
    def __init__(self, text: str):
        self.text = text

    def partitions(self):
        return [InputPartition(0)]

    def read(self, partition):
        for k, r in enumerate(Layout.from_json(self.text).rects):
            yield (k, *map(int, r))


class LayoutSource(DataSource):
    """spark.read.format("cut_layout").option("layout", json): a layout's rectangles as rows."""

    @classmethod
    def name(cls) -> str:
        return "cut_layout"

    def schema(self) -> str:
        return LAYOUT_SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _LayoutReader(self.options["layout"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(LayoutSource)
