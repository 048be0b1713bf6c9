"""Linear sketch states as cell tables: merge, subtract, shift, expand levels, decode.

A state is a DataFrame of key columns and sums s0 (and s1, s2). Every operation is a hash
aggregation over cells; updates never pass through Python.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, functions as F

from ..functions.hashing import PRIME, Seed, poly4

SUMS = ("s0", "s1", "s2")


def keys(cells: DataFrame) -> list[str]:
    return [c for c in cells.columns if c not in SUMS]


def sums(cells: DataFrame) -> list[str]:
    return [c for c in SUMS if c in cells.columns]


def _added(cells: DataFrame, by: list[str], names: list[str]) -> DataFrame:
    out = cells.groupBy(*by).agg(*(F.sum(s).alias(s) for s in names))
    return out.where(reduce(lambda a, b: a | b, (F.col(s) != 0 for s in names)))


def accumulate(rows: DataFrame, by: list[str], terms: dict[str, Column], wide: bool = False) -> DataFrame:
    """Cells from update rows; wide keeps sums in decimal(38, 0) where bigint could overflow."""
    kind = "decimal(38,0)" if wide else "long"
    out = rows.groupBy(*by).agg(*(F.sum(t.cast(kind)).cast(kind).alias(s) for s, t in terms.items()))
    return out.where(reduce(lambda a, b: a | b, (F.col(s) != 0 for s in terms)))


def merge(*states: DataFrame) -> DataFrame:
    """The state of all inputs together; states must have the same keys."""
    if any(s.columns != states[0].columns for s in states):
        raise ValueError(f"states differ: {[s.columns for s in states]}")
    return _added(reduce(DataFrame.unionByName, states), keys(states[0]), sums(states[0]))


def negate(state: DataFrame) -> DataFrame:
    return state.select(*keys(state), *((-F.col(s)).alias(s) for s in sums(state)))


def subtract(a: DataFrame, b: DataFrame) -> DataFrame:
    """The state of a's updates without b's: a window's end, or the difference of two datasets."""
    return merge(a, negate(b))


def scale(state: DataFrame, factor: Column | int) -> DataFrame:
    f = factor if isinstance(factor, Column) else F.lit(factor)
    return state.select(*keys(state), *((F.col(s) * f).cast(state.schema[s].dataType).alias(s) for s in sums(state)))


def shift(state: DataFrame, unit: DataFrame, b: int) -> DataFrame:
    """The state of x - b for every coordinate of the universe, whose state of ones is unit."""
    return subtract(state, scale(unit, b))


def expand(state: DataFrame, level: str) -> DataFrame:
    """Updates are kept at their own level; level m holds those of every level from m up."""
    spread = state.withColumn(level, F.explode(F.sequence(F.lit(0), F.col(level))))
    return _added(spread, keys(state), sums(state))


def peel(slots: np.ndarray, s0: np.ndarray, s1: np.ndarray, s2: np.ndarray, size: int, fingerprint: Seed, places: tuple[Seed, ...], wide: bool = False) -> tuple[dict[int, int], bool]:
    """Entries id -> value of one recovery table of len(places) parts of size slots; True if nothing is left over."""
    cell = {int(s): [int(a), int(b), int(c)] for s, a, b, c in zip(slots, s0, s1, s2, strict=True)}
    todo, out, most = list(cell), {}, 1 << 62 if wide else PRIME
    while todo:
        s = todo.pop()
        a, b, c = cell.get(s, (0, 0, 0))
        if a == 0 or b % a or b // a < 0 or b // a >= most:
            continue
        x = b // a
        at = [p * size + seed.value(x, wide) % size for p, seed in enumerate(places)]
        if s not in at or (c - a * fingerprint.value(x, wide)) != 0:
            continue
        out[x] = out.get(x, 0) + a
        for t in at:
            old = cell.setdefault(t, [0, 0, 0])
            old[0], old[1], old[2] = old[0] - a, old[1] - b, old[2] - c
            todo.append(t)
    return {x: v for x, v in out.items() if v}, all(v == [0, 0, 0] for v in cell.values())


def recovery_terms(rows: DataFrame, item: str, size: int, seed: int, role: int, wide: bool = False) -> DataFrame:
    """rows with slot (one row for each part) and the three sums' terms t0, t1, t2 of column c; decimals with wide."""
    places = recovery_places(seed, role)
    slot = F.explode(F.array(*((F.lit(p * size) + poly4(item, s, wide) % size).cast("int") for p, s in enumerate(places))))
    with_slot = rows.withColumn("slot", slot)
    c = F.col("c").cast("decimal(19,0)") if wide else F.col("c")
    return with_slot.withColumns({"t0": F.col("c"), "t1": c * F.col(item), "t2": c * poly4(item, recovery_print(seed, role), wide)})


def recovery_places(seed: int, role: int) -> tuple[Seed, ...]:
    return tuple(Seed.of(seed, 100 * role + 11 + p) for p in range(3))


def recovery_print(seed: int, role: int) -> Seed:
    return Seed.of(seed, 100 * role + 10)


def decode(state: DataFrame, by: list[str], size: int, seed: int, role: int, task: list[str] | None = None, wide: bool = False) -> DataFrame:
    """Entries of every recovery table: columns of by, item, v and complete (the table decoded to nothing).

    task: columns of by that one Arrow group shares, so that small tables do not become a group each.
    """
    places, mark, group = recovery_places(seed, role), recovery_print(seed, role), task or by

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        for key, part in pdf.groupby(by, sort=True):
            found, complete = peel(*(part[c].to_numpy() for c in ("slot", *SUMS)), size, mark, places, wide)
            out += [(*(int(k) for k in key), x, v, complete) for x, v in sorted(found.items())]
        return pd.DataFrame(out, columns=[*by, "item", "v", "complete"])

    schema = ", ".join(f"{c} {state.schema[c].dataType.simpleString()}" for c in by) + ", item long, v long, complete boolean"
    return state.select(*dict.fromkeys((*by, *group)), "slot", *SUMS).groupBy(*group).applyInPandas(run, schema)
