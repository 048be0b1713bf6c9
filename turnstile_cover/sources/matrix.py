"""Tables as signed updates (i, j, c), net matrices, and the coverage workloads."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from .tables import table


def updates(df: DataFrame, row: str | Column, col: str | Column, delta: Column | int = 1) -> DataFrame:
    c = delta if isinstance(delta, Column) else F.lit(delta)
    named = lambda x: F.col(x) if isinstance(x, str) else x
    return df.select(named(row).alias("i"), named(col).alias("j"), c.cast("long").alias("c"))


def net(u: DataFrame) -> DataFrame:
    """Nonzero entries (i, j, v)."""
    return u.groupBy("i", "j").agg(F.sum("c").alias("v")).where("v <> 0")


def encode_column(x: Column, kind: str, width: float = 1.0) -> Column:
    """A value as a nonzero bigint for equality: string, double (bins of width), timestamp (days), boolean, int; null is -1."""
    code = {"string": lambda: F.pmod(F.xxhash64(x), F.lit((1 << 31) - 1)), "double": lambda: F.floor(x / width), "timestamp": lambda: F.unix_date(x.cast("date")), "boolean": lambda: x.cast("int"), "int": lambda: x}[kind]().cast("long")
    return F.when(x.isNull(), F.lit(-1)).otherwise(F.when(code >= 0, code + 1).otherwise(code - 1))


def change_to_updates(events: DataFrame, row: str, col: str, value: str, order: list[str]) -> DataFrame:
    """A new value of a cell takes back the old one: i, j, c = new - old, in the order given."""
    w = Window.partitionBy(row, col).orderBy(*order)
    return events.select(F.col(row).alias("i"), F.col(col).alias("j"), (F.col(value) - F.coalesce(F.lag(value).over(w), F.lit(0))).cast("long").alias("c"))


def part_by_supplier(spark: SparkSession, d: str) -> DataFrame:
    return updates(table(spark, d, "lineitem"), "l_partkey", "l_suppkey")


def part_by_supplier_returns(spark: SparkSession, d: str) -> DataFrame:
    """Every line adds; a returned line takes itself back later."""
    lines = table(spark, d, "lineitem").select("l_partkey", "l_suppkey", F.explode(F.when(F.col("l_returnflag") == "R", F.array(F.lit(1), F.lit(-1))).otherwise(F.array(F.lit(1)))).alias("c"))
    return updates(lines, "l_partkey", "l_suppkey", F.col("c"))


def customer_by_supplier(spark: SparkSession, d: str) -> DataFrame:
    joined = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey").join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return updates(joined, "o_custkey", "l_suppkey")


def order_by_part(spark: SparkSession, d: str) -> DataFrame:
    return updates(table(spark, d, "lineitem"), "l_orderkey", "l_partkey")


def _keyed_events(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k"), "event_type")


def user_by_key(spark: SparkSession, d: str) -> DataFrame:
    return updates(_keyed_events(spark, d), "user_id", "k")


def user_by_key_signed(spark: SparkSession, d: str) -> DataFrame:
    return updates(_keyed_events(spark, d), "user_id", "k", F.when(F.col("event_type") == "error", -1).otherwise(1))


def word_by_source(spark: SparkSession, d: str, by: str = "source") -> DataFrame:
    words = F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0)))
    return updates(table(spark, d, "documents").select(words.alias("w"), F.col(by).alias("s")), "w", "s")


def vector_neighbours(spark: SparkSession, d: str, at_least: float = 0.2) -> DataFrame:
    """Vectors within a cosine of each other; the vectors come in pairs of hashed blocks whose number follows theirs, so no side is
    broadcast and no task grows."""
    e = table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x))
    e = e.withColumn("n", norm)
    blocks = max(4, math.ceil(e.count() / 2048))  # a pair of blocks is one task's work, however many vectors there are
    b = F.pmod(F.xxhash64("vec_id"), F.lit(blocks))
    left = e.select(F.col("vec_id").alias("i"), F.col("v").alias("x"), F.col("n").alias("nx"), b.alias("p"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("q"))
    right = e.select(F.col("vec_id").alias("j"), F.col("v").alias("y"), F.col("n").alias("ny"), b.alias("q"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("p"))
    dot = F.aggregate(F.zip_with("x", "y", lambda a, c: a * c), F.lit(0.0), lambda a, c: a + c)
    return updates(left.join(right, ["p", "q"]).where(dot >= at_least * F.col("nx") * F.col("ny")), "i", "j")


#: name: (updates, the same as SQL)
WORKLOADS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "c1": (part_by_supplier, "SELECT l_partkey AS i, l_suppkey AS j, 1 AS c FROM lineitem"),
    "c1t": (part_by_supplier_returns, "SELECT l_partkey AS i, l_suppkey AS j, 1 AS c FROM lineitem UNION ALL SELECT l_partkey, l_suppkey, -1 FROM lineitem WHERE l_returnflag = 'R'"),
    "c2": (customer_by_supplier, "SELECT o_custkey AS i, l_suppkey AS j, 1 AS c FROM lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "c3": (order_by_part, "SELECT l_orderkey AS i, l_partkey AS j, 1 AS c FROM lineitem"),
    "c4": (user_by_key, "SELECT user_id AS i, CAST(props->>'$.k' AS BIGINT) AS j, 1 AS c FROM events"),
    "c4t": (user_by_key_signed, "SELECT user_id AS i, CAST(props->>'$.k' AS BIGINT) AS j, CASE WHEN event_type = 'error' THEN -1 ELSE 1 END AS c FROM events"),
    "c5": (word_by_source, r"SELECT unnest(regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+')) AS i, source AS j, 1 AS c FROM documents"),
    "c5d": (lambda s, d: word_by_source(s, d, "doc_id"), r"SELECT unnest(regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+')) AS i, doc_id AS j, 1 AS c FROM documents"),
    "c6": (vector_neighbours, "SELECT a.vec_id AS i, b.vec_id AS j, 1 AS c FROM embeddings a JOIN embeddings b ON list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= 0.2"),
}


def net_sql(name: str) -> str:
    return f"SELECT i, j, sum(c)::BIGINT AS v FROM ({WORKLOADS[name][1]}) GROUP BY i, j HAVING sum(c) <> 0"
