"""Tables written once into the folder all executors share, to cut lineage and share results."""

from __future__ import annotations

import gc
import uuid

from pyspark.sql import DataFrame, SparkSession

from ..operators.checkpoints import mark, noted, release, shared_folder

shared_dir = shared_folder


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet in the shared folder and read it back; survives the loss of executors."""
    spark = df.sparkSession
    path = noted(f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}")
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def tidy(spark: SparkSession, since: int, keep: tuple[DataFrame, ...]) -> None:
    """Delete the tables written since a mark but those that keep reads, and the shuffles of DataFrames that are gone: Spark's
    cleaner deletes those only after a collection on the driver, which a large heap puts off."""
    release(spark, since, keep)
    gc.collect()
    spark._jvm.System.gc()


__all__ = ["mark", "materialize", "release", "shared_dir", "tidy"]
