"""Combining columns of a state into one vector by random integers."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import Seed, poly4
from .cells import _added, keys, sums


def weight(column: str, seed: int):
    """The random integer of a column, 1 to 2**20."""
    return (poly4(column, Seed.of(seed, 9)) % (1 << 20) + 1).cast("decimal(10,0)")


def columns(state: DataFrame, chosen: DataFrame, seed: int = 1, column: str = "j") -> DataFrame:
    """The state of A_C v for every set of chosen (columns: any set keys, and column).

    A row of A_C v is nonzero if and only if the row of A_C is, and two rows are equal if and only if they
    are in A_C, except with tiny probability over v: so the same combination serves coverage (count
    nonzeros) and fingerprinting (count distinct values). Sums are decimals: products pass 2**63.
    """
    sets = [c for c in chosen.columns if c != column]
    rows = state.join(chosen, column).select(*sets, *(k for k in keys(state) if k != column), *((F.col(s).cast("decimal(28,0)") * weight(column, seed)).cast("decimal(38,0)").alias(s) for s in sums(state)))
    return _added(rows, [*sets, *(k for k in keys(state) if k != column)], sums(state))


def column_values(wide: DataFrame, cols: list[str], seed: int = 1):
    """A_C v of wide rows of integers, as one decimal column."""
    total = F.lit(0).cast("decimal(38,0)")
    for n, c in enumerate(cols):
        total = (total + F.col(c).cast("decimal(20,0)") * F.lit(Seed.of(seed, 9).value(n) % (1 << 20) + 1)).cast("decimal(38,0)")
    return total
