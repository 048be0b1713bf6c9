"""CountSketch: signed counters in independent repetitions, read by medians."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import Seed, poly4, sign
from .cells import accumulate


def _seeds(seed: int, rep: int) -> tuple[Seed, Seed]:
    return Seed.of(seed, 10 * rep + 4), Seed.of(seed, 10 * rep + 5)


def _spread(df: DataFrame, key: str, slots: int, reps: int, seed: int) -> DataFrame:
    parts = [F.struct(F.lit(r).alias("rep"), (poly4(key, a) % slots).cast("int").alias("slot"), sign(poly4(key, b)).alias("sg")) for r in range(reps) for a, b in [_seeds(seed, r)]]
    return df.withColumn("x", F.explode(F.array(*parts))).select("*", "x.*").drop("x")


def build(u: DataFrame, key: str, slots: int = 256, reps: int = 5, seed: int = 1) -> DataFrame:
    """Cells (rep, slot, s0) of updates with column c."""
    return accumulate(_spread(u.select(key, "c"), key, slots, reps, seed), ["rep", "slot"], {"s0": F.col("c") * F.col("sg")})


def estimate(cells: DataFrame, candidates: DataFrame, key: str, slots: int = 256, reps: int = 5, seed: int = 1) -> DataFrame:
    """key and estimate of each candidate."""
    read = _spread(candidates.select(key), key, slots, reps, seed).join(cells, ["rep", "slot"], "left")
    return read.groupBy(key).agg(F.median(F.coalesce("s0", F.lit(0)) * F.col("sg")).alias("estimate"))


def estimate_sql(u: str, candidates: str, key: str, slots: int = 256, reps: int = 5, seed: int = 1) -> str:
    def spread(q: str, more: str) -> str:
        return " UNION ALL ".join(f"SELECT {key}{more}, {r} AS rep, {a.sql(key)} % {slots} AS slot, 2 * ({b.sql(key)} & 1) - 1 AS sg FROM ({q})" for r in range(reps) for a, b in [_seeds(seed, r)])

    return f"""WITH s AS (SELECT rep, slot, sum(c * sg)::BIGINT AS s0 FROM ({spread(u, ', c')}) GROUP BY ALL)
    SELECT q.{key}, median(coalesce(s0, 0) * sg)::DOUBLE AS estimate FROM ({spread(candidates, '')}) q LEFT JOIN s USING (rep, slot) GROUP BY q.{key}"""


def residual_bound(u: DataFrame, key: str, slots: int) -> DataFrame:
    """One row: the tail norm that the error is held against, over the largest slots / 4 keys left out, divided by sqrt(slots)."""
    totals = u.groupBy(key).agg(F.sum("c").alias("f"))
    largest = totals.orderBy(F.abs("f").desc(), key).limit(max(1, slots // 4)).select(key)
    return totals.join(largest, key, "left_anti").agg((F.sqrt(F.coalesce(F.sum(F.col("f").cast("double") ** 2), F.lit(0.0))) / slots**0.5).alias("bound"))
