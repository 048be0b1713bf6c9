"""Reading the given tables and update logs in several formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

UPDATES = T.StructType([T.StructField("i", T.LongType()), T.StructField("j", T.LongType()), T.StructField("c", T.LongType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_updates(spark: SparkSession, path: str, form: str = "parquet") -> DataFrame:
    """An update log written as parquet, orc, json or csv."""
    reader = spark.read.schema(UPDATES)
    return reader.option("header", True).csv(path) if form == "csv" else reader.format(form).load(path)


def write_updates(updates: DataFrame, path: str, form: str = "parquet", by_level: str | None = None) -> None:
    """Write an update log, with by_level partitioned so that a sample reads its levels alone."""
    writer = updates.write.mode("overwrite").format(form)
    writer = writer.option("header", True) if form == "csv" else writer
    (writer.partitionBy(by_level) if by_level else writer).save(path)
