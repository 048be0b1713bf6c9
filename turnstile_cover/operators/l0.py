"""Number of nonzero coordinates under deletions, by group."""

from __future__ import annotations

from math import log

from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import Seed, level, level_sql, poly4
from .cells import accumulate, decode, expand

FULL = 0.7


def exact_small(sampler_cells: DataFrame, by: list[str], size: int = 256, seed: int = 1) -> DataFrame:
    """by, l0 and exact: the number of nonzero coordinates by decoding level 0 of a sampler's state, where it holds all of them.

    With at most about size / 2 nonzeros the table decodes in full and l0 is the count; else exact is false and l0 null.
    """
    from .l0sampler import ROLE

    found = decode(expand(sampler_cells, "lvl").where("lvl = 0"), by, size, seed, ROLE)
    return found.groupBy(*by).agg(F.min("complete").alias("exact"), F.count("*").alias("l0")).select(*by, F.when(F.col("exact"), F.col("l0")).alias("l0"), "exact")


def exact_all(u: DataFrame, by: list[str], size: int = 256, seed: int = 1) -> DataFrame:
    """by, l0 and exact of every group: a group whose table does not decode in full gets a table of four times the slots and a new
    seed, until all do."""
    from . import l0sampler
    from .checkpoints import cut

    out = None
    while True:
        state = cut(l0sampler.build(u, by, size=size, seed=seed))
        got = cut(exact_small(state, by, size, seed).where("exact"))
        out = got if out is None else out.unionByName(got)
        failed = state.select(*by).distinct().join(got, by, "left_anti")  # an overfull table may give back nothing at all
        if failed.isEmpty():
            return out
        u, size, seed = u.join(failed, by, "left_semi"), 4 * size, seed + 1


def _seeds(seed: int, rep: int) -> tuple[Seed, Seed, Seed]:
    return tuple(Seed.of(seed, 10 * rep + r) for r in (1, 2, 3))


def rows(u: DataFrame, by: list[str], item: str = "i", slots: int = 1024, reps: int = 3, levels: int = 20, seed: int = 1, wide: bool = False) -> DataFrame:
    """The cells that each update touches, with its weight w."""
    spread = []
    for r in range(reps):
        where, place, weight = _seeds(seed, r)
        spread.append(F.struct(F.lit(r).alias("rep"), level(poly4(item, where, wide), levels).alias("lvl"), (poly4(item, place, wide) % slots).cast("int").alias("slot"), (poly4(item, weight, wide) + 1).alias("w")))
    return u.select(*by, "c", F.explode(F.array(*spread)).alias("x")).select(*by, "c", "x.*")


def build(u: DataFrame, by: list[str], item: str = "i", slots: int = 1024, reps: int = 3, levels: int = 20, seed: int = 1, wide: bool = False) -> DataFrame:
    """Cells (by, rep, lvl, slot, s0) of updates with column c; every group shares the seeds, so groups can be combined. wide: items up to
    2**62, and sums in decimals."""
    return accumulate(rows(u, by, item, slots, reps, levels, seed, wide), [*by, "rep", "lvl", "slot"], {"s0": (F.col("c").cast("decimal(19,0)") if wide else F.col("c")) * F.col("w")}, wide)


def build_sql(u: str, by: str, item: str = "i", slots: int = 1024, reps: int = 3, levels: int = 20, seed: int = 1) -> str:
    parts = []
    for r in range(reps):
        where, place, weight = (s.sql(item) for s in _seeds(seed, r))
        parts.append(f"SELECT {by}, {r} AS rep, {level_sql(where, levels)} AS lvl, CAST({place} % {slots} AS INT) AS slot, c * ({weight} + 1) AS w FROM ({u})")
    return f"SELECT {by}, rep, lvl, slot, sum(w)::BIGINT AS s0 FROM ({' UNION ALL '.join(parts)}) GROUP BY ALL HAVING sum(w) <> 0"


def estimate(cells: DataFrame, by: list[str], slots: int = 1024) -> DataFrame:
    """l0 of every group that has a nonzero coordinate: the median over repetitions."""
    filled = expand(cells, "lvl").groupBy(*by, "rep", "lvl").agg(F.count("*").alias("t"))
    open_ = F.col("t") <= FULL * slots
    picked = filled.groupBy(*by, "rep").agg(F.coalesce(F.min(F.when(open_, F.col("lvl"))), F.max("lvl")).alias("lv_"), F.map_from_entries(F.collect_list(F.struct("lvl", "t"))).alias("all"))
    t = F.least(F.element_at("all", F.col("lv_")), F.lit(slots - 1)).cast("double")
    value = F.pow(F.lit(2.0), F.col("lv_")) * F.log(1 - t / slots) / log(1 - 1 / slots)
    return picked.groupBy(*by).agg(F.round(F.median(value), 6).alias("l0")) if by else picked.agg(F.round(F.median(value), 6).alias("l0"))


def estimate_sql(cells: str, by: str, slots: int = 1024) -> str:
    return f"""WITH e AS (SELECT {by}, rep, m AS lvl, slot, sum(s0) AS s FROM (SELECT *, unnest(range(0, lvl + 1)) AS m FROM ({cells})) GROUP BY ALL HAVING sum(s0) <> 0),
    f AS (SELECT {by}, rep, lvl, count(*) AS t FROM e GROUP BY ALL),
    p AS (SELECT {by}, rep, coalesce(min(lvl) FILTER (t <= {FULL * slots}), max(lvl)) AS m FROM f GROUP BY ALL),
    v AS (SELECT p.{by}, p.rep, pow(2.0, m) * ln(1 - least(t, {slots - 1})::DOUBLE / {slots}) / ln(1 - 1 / {slots}.0::DOUBLE) AS x FROM p JOIN f ON p.{by} = f.{by} AND p.rep = f.rep AND f.lvl = p.m)
    SELECT {by}, round(median(x), 6) AS l0 FROM v GROUP BY {by}"""
