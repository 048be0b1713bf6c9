"""Cutting lineage with a table in the shared checkpoint folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_written: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir. A temporary one only where none is set and all runs in this process, as in tests."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not folder:
        master = spark.sparkContext.master
        if not (master == "local" or master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="turnstile_")
        spark.conf.set("spark.checkpoint.dir", folder)
    return folder.rstrip("/")


def noted(path: str) -> str:
    """path, remembered for release."""
    _written.append(path)
    return path


def mark() -> int:
    """A place to release from."""
    return len(_written)


def release(spark: SparkSession, since: int = 0, keep: tuple[DataFrame, ...] = ()) -> int:
    """Delete the intermediate tables written since a mark, but for those that keep still reads; how many went.

    DataFrames that read a deleted table can no longer run: call it when their results are written.
    """
    used = [f for df in keep for f in df.inputFiles()]
    jvm, conf, gone = spark._jvm, spark._jsc.hadoopConfiguration(), 0
    for path in _written[since:]:
        if any(path.rsplit("/", 1)[-1] in f for f in used):  # names are unique
            continue
        at = jvm.org.apache.hadoop.fs.Path(path)
        gone += bool(at.getFileSystem(conf).delete(at, True))
        _written.remove(path)
    return gone


def cut(df: DataFrame) -> DataFrame:
    """df, written and read again: survives lost executors and keeps plans short."""
    spark = df.sparkSession
    path = noted(f"{shared_folder(spark)}/cut-{uuid.uuid4().hex}")
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
