"""Noisy greedy for monotone submodular functions that linear states can answer."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Protocol

from pyspark.sql import DataFrame, functions as F

from ..plans.params import Params
from . import l0
from .combine import columns
from .greedy import trajectory


class SketchableFunction(Protocol):
    """A set function of columns with a linear state; copy tells independent states apart."""

    def state(self, copy: int) -> DataFrame: ...

    def query(self, state: DataFrame, sets: DataFrame) -> DataFrame:
        """cand and value of every set in sets (cand, j)."""
        ...


@dataclass
class CoverageFn:
    """Rows with a nonzero in some column, from column L0 states."""

    updates: DataFrame
    params: Params
    built: dict[int, DataFrame] = field(default_factory=dict)

    def state(self, copy: int) -> DataFrame:
        from .checkpoints import cut

        if copy not in self.built:
            p = self.params
            self.built[copy] = cut(l0.build(self.updates, ["j"], "i", p.l0_slots, p.l0_reps, p.levels, p.seed + 1000 * copy))
        return self.built[copy]

    def query(self, state: DataFrame, sets: DataFrame) -> DataFrame:
        return l0.estimate(columns(state, sets, self.params.seed), ["cand"], self.params.l0_slots).withColumnRenamed("l0", "value")


@dataclass
class ExactCoverageFn:
    entries: DataFrame

    def state(self, copy: int) -> DataFrame:
        return self.entries

    def query(self, state: DataFrame, sets: DataFrame) -> DataFrame:
        return state.join(sets, "j").groupBy("cand").agg(F.countDistinct("i").cast("double").alias("value"))


@dataclass
class PairSeparationFn:
    """Pairs of users that differ on some column of a long table (uid, j, v) of whole rows; rows: of a hash sample, or all."""

    long: DataFrame
    n: int

    def state(self, copy: int) -> DataFrame:
        return self.long

    def query(self, state: DataFrame, sets: DataFrame) -> DataFrame:
        own = state.join(sets, "j").groupBy("cand", "uid").agg(F.sum((F.col("v").cast("decimal(20,0)") * (F.pmod(F.xxhash64("j"), F.lit(1 << 20)) + 1).cast("decimal(10,0)")).cast("decimal(38,0)")).alias("x"))
        f = own.groupBy("cand", "x").agg(F.count("*").alias("f")).groupBy("cand").agg(F.sum("f").alias("n"), F.sum(F.col("f").cast("double") * F.col("f")).alias("s"))
        return f.select("cand", ((F.col("n").cast("double") * F.col("n") - F.col("s")) / 2).alias("value"))


@dataclass
class ExactFn:
    """Any function of a set of columns, given as values of sets (cand, value)."""

    evaluate: Callable[[DataFrame], DataFrame]

    def state(self, copy: int):
        return None

    def query(self, state, sets: DataFrame) -> DataFrame:
        return self.evaluate(sets)


def sketch_sql(u: str, params: Params, k: int, fresh: bool) -> str:
    """The noisy greedy on column L0 states as one SQL text: round, col, and the total after it, to whole rows."""
    from .coverage import union_size_sql

    parts = [f"cols AS MATERIALIZED (SELECT DISTINCT j FROM ({u}))"]
    for r in range(1, k + 1):
        seed = params.seed + 1000 * (r if fresh else 1)
        cells = l0.build_sql(u, "j", slots=params.l0_slots, reps=params.l0_reps, levels=params.levels, seed=seed)
        have = " UNION ALL ".join(f"SELECT j FROM r{x}" for x in range(1, r)) or "SELECT j FROM cols WHERE false"
        sets = f"SELECT j AS cand, j FROM cols WHERE j NOT IN ({have}) UNION ALL SELECT c.j AS cand, h.j FROM cols c, ({have}) h WHERE c.j NOT IN ({have})"
        parts.append(f"r{r} AS MATERIALIZED (SELECT cand AS j, l0 FROM ({union_size_sql(cells, sets, 'cand', params)}) ORDER BY l0 DESC, cand LIMIT 1)")
    rows = " UNION ALL ".join(f"SELECT {r}::INT AS round, j AS col, l0 FROM r{r}" for r in range(1, k + 1))
    return f"WITH {', '.join(parts)} SELECT round, col, round(l0 - coalesce(lag(l0) OVER (ORDER BY round), 0))::BIGINT AS gain, round(l0)::BIGINT AS total FROM ({rows})"


def gain(fn: SketchableFunction, columns_: DataFrame, picked: list, state) -> DataFrame:
    """cand and value of picked with each further column: one job scores all candidates."""
    spark = columns_.sparkSession
    fresh = columns_.where(~F.col("j").isin(picked)) if picked else columns_
    kind = columns_.schema["j"].dataType.simpleString()
    sets = fresh.select(F.col("j").alias("cand"), "j")
    if picked:
        have = spark.createDataFrame([(p,) for p in picked], f"j {kind}")
        sets = sets.unionByName(fresh.select(F.col("j").alias("cand")).crossJoin(F.broadcast(have)))  # at most k rows
    return fn.query(state, sets)


def greedy(fn: SketchableFunction, columns_: DataFrame, k: int, fresh: bool = True) -> DataFrame:
    """round, col, gain, total: k rounds of the best marginal value; fresh takes an independent state each round, as the analysis
    asks, otherwise one state serves all rounds (a heuristic, as in experiments). The smallest column wins a tie."""
    picked, rows, before = [], [], 0.0
    for r in range(1, k + 1):
        best = gain(fn, columns_, picked, fn.state(r if fresh else 1)).orderBy(F.desc("value"), "cand").limit(1).collect()
        if not best:
            break
        j, value = best[0]["cand"], float(best[0]["value"])
        picked.append(j)
        rows.append((r, j, value - before, value))
        before = value
    kind = columns_.schema["j"].dataType.simpleString()
    return columns_.sparkSession.createDataFrame(rows, f"round int, col {kind}, gain double, total double")


__all__ = ["CoverageFn", "ExactCoverageFn", "ExactFn", "PairSeparationFn", "SketchableFunction", "gain", "greedy", "trajectory"]
