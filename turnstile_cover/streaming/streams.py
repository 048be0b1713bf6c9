"""Sketch states over streams, windows, and the stateful operators around them.

States are sums, so order does not matter and no watermark is needed for them; windows need one,
and NTZ timestamps are cast first, since watermarks refuse them.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import l0
from ..operators.checkpoints import shared_folder
from ..operators.cells import merge
from ..sources.tables import table

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stage_events(spark: SparkSession, sf_dir: str, name: str, files: int = 4) -> str:
    """The events table as a folder of files for a file stream, appended one by one in time order."""
    path = f"{shared_folder(spark)}/{name}"
    events = table(spark, sf_dir, "events")
    ends = events.select(F.unix_micros(F.col("ts").cast("timestamp")).alias("us")).agg(F.percentile_approx("us", [n / files for n in range(1, files)], 1000)).first()[0] or []
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    for n in range(len(ends) + 1):
        part = events.where((us > ends[n - 1] if n else F.lit(True)) & (us <= ends[n] if n < len(ends) else F.lit(True)))
        part.coalesce(1).write.mode("append").parquet(path)
        time.sleep(0.02)  # files are taken by their time of change
    return path


def read_stream(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_end(out: DataFrame, folder: str, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what there is into a Parquet sink and read it; complete: every batch writes the whole result under its own
    number, and the last one is read, so nothing is held by the driver and a repeated batch overwrites itself."""
    spark = out.sparkSession
    if mode == "append":
        q = out.writeStream.format("parquet").option("path", f"{folder}/{name}").option("checkpointLocation", f"{folder}/{name}-log").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(out.schema).parquet(f"{folder}/{name}")
    last = [0]

    def write(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/{name}/at={n}")
        last[0] = n

    q = out.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{folder}/{name}-log").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{folder}/{name}/at={last[0]}")


def maintain(stream: DataFrame, build: Callable[[DataFrame], DataFrame], folder: str) -> None:
    """Keep a state's increments up to date, one folder a batch; a repeated batch overwrites its own, so restarts do not count twice."""

    def add(batch: DataFrame, n: int) -> None:
        build(batch).write.mode("overwrite").parquet(f"{folder}/state/batch={n}")

    q = stream.writeStream.foreachBatch(add).option("checkpointLocation", f"{folder}/state-log").trigger(availableNow=True).start()
    q.awaitTermination()


def snapshot(spark: SparkSession, folder: str) -> DataFrame:
    """The state so far: increments merged. The stream can go on afterwards."""
    return merge(spark.read.parquet(f"{folder}/state").drop("batch"))


def compact(spark: SparkSession, folder: str) -> int:
    """All increments but the newest become one, so a snapshot reads few files; how many went. Call it between runs of the
    stream: the newest batch may be repeated after a restart and must overwrite its own increment."""
    state = spark.read.parquet(f"{folder}/state")
    batches = sorted(r[0] for r in state.select("batch").distinct().collect())
    if len(batches) < 3:
        return 0
    old, keep = batches[:-1], batches[-2]
    path = f"{folder}/compacted-{uuid.uuid4().hex}"
    merge(state.where(F.col("batch") <= keep).drop("batch")).write.parquet(path)
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    fs = jvm.org.apache.hadoop.fs.Path(folder).getFileSystem(conf)
    for b in old:
        fs.delete(jvm.org.apache.hadoop.fs.Path(f"{folder}/state/batch={b}"), True)
    fs.rename(jvm.org.apache.hadoop.fs.Path(path), jvm.org.apache.hadoop.fs.Path(f"{folder}/state/batch={keep}"))
    return len(old) - 1


def monitor(stream: DataFrame, build: Callable[[DataFrame], DataFrame], answer: Callable[[DataFrame], DataFrame], folder: str) -> DataFrame:
    """After every batch the state grows and answer(state) is kept as that batch's risk rows."""
    spark = stream.sparkSession

    def step(batch: DataFrame, n: int) -> None:
        build(batch).write.mode("overwrite").parquet(f"{folder}/state/batch={n}")
        answer(snapshot(spark, folder)).withColumn("batch", F.lit(n)).write.mode("overwrite").parquet(f"{folder}/risk/at={n}")

    q = stream.writeStream.foreachBatch(step).option("checkpointLocation", f"{folder}/risk-log").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{folder}/risk").drop("at")


def type_updates(events: DataFrame) -> DataFrame:
    """Updates of the coverage workload of users by key, signed by event type."""
    return events.select(F.col("user_id").alias("i"), F.get_json_object("props", "$.k").cast("long").alias("j"), F.when(F.col("event_type") == "error", -1).otherwise(1).cast("long").alias("c"))


def column_cells(events: DataFrame) -> DataFrame:
    return l0.build(type_updates(events), ["j"], slots=256, reps=1, levels=12)


def tumbling(events: DataFrame, late: str = "1 hour", width: str = "1 day", slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    out = events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return out.select(F.col("w.start").cast("timestamp_ntz").alias("w_start"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    out = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("s_start"), "n")


def deduplicated(events: DataFrame, late: str = "40 days") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def changes(events: DataFrame) -> DataFrame:
    """Value changes of (user, type) in order of time, as updates new - old, with state kept by key."""
    keyed = events.select("user_id", "event_type", "event_id", F.unix_micros("ts").alias("us"), F.get_json_object("props", "$.k").cast("long").alias("k"))

    def step(key, pdfs: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        old = state.get[0] if state.exists else 0
        out = []
        for e, k in pd.concat(list(pdfs)).sort_values(["us", "event_id"])[["event_id", "k"]].itertuples(index=False):
            out.append((key[0], key[1], e, int(k) - old))
            old = int(k)
        state.update((old,))
        yield pd.DataFrame(out, columns=["user_id", "event_type", "event_id", "c"])

    return keyed.groupBy("user_id", "event_type").applyInPandasWithState(step, "user_id long, event_type string, event_id long, c long", "old long", "append", "NoTimeout")


def count_late(stream: DataFrame, folder: str, delay_us: int) -> DataFrame:
    """late, in_time: rows older than the newest row of earlier batches less the delay, which a watermark would drop."""
    spark = stream.sparkSession

    def step(batch: DataFrame, n: int) -> None:
        earlier = spark.read.schema("newest long, late long, in_time long").parquet(f"{folder}/late").agg(F.max("newest")).first()[0] if n else None
        us = F.unix_micros("ts")
        late = F.lit(False) if earlier is None else us < earlier - delay_us
        batch.agg(F.max(us).alias("newest"), F.count_if(late).alias("late"), F.count_if(~late).alias("in_time")).coalesce(1).write.mode("overwrite").parquet(f"{folder}/late/batch={n}")

    q = stream.writeStream.foreachBatch(step).option("checkpointLocation", f"{folder}/late-log").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{folder}/late").agg(F.sum("late").alias("late"), F.sum("in_time").alias("in_time"))
