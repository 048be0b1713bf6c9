"""Uniform nonzero coordinates with exact values, from a linear state, under deletions."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import Seed, level, level_sql, poly4
from .cells import SUMS, accumulate, decode, expand, recovery_places, recovery_terms

ROLE = 7
FULL = 0.5


def build(u: DataFrame, by: list[str], item: str = "i", size: int = 256, levels: int = 20, seed: int = 1) -> DataFrame:
    """Cells (by, lvl, slot, s0, s1, s2): three recovery tables of size slots at each level."""
    lvl = level(poly4(item, Seed.of(seed, 6)), levels)
    rows = recovery_terms(u.select(*by, item, "c", lvl.alias("lvl")), item, size, seed, ROLE)
    return accumulate(rows, [*by, "lvl", "slot"], {s: F.col(f"t{n}") for n, s in enumerate(SUMS)})


def build_sql(u: str, by: str, item: str = "i", size: int = 256, levels: int = 20, seed: int = 1) -> str:
    from .cells import recovery_print

    lvl = level_sql(Seed.of(seed, 6).sql(item), levels)
    parts = [f"SELECT {by}, {lvl} AS lvl, CAST({p * size} + {place.sql(item)} % {size} AS INT) AS slot, c, c * {item} AS t1, c * {recovery_print(seed, ROLE).sql(item)} AS t2 FROM ({u})" for p, place in enumerate(recovery_places(seed, ROLE))]
    return f"SELECT {by}, lvl, slot, sum(c)::BIGINT AS s0, sum(t1)::BIGINT AS s1, sum(t2)::BIGINT AS s2 FROM ({' UNION ALL '.join(parts)}) GROUP BY ALL HAVING sum(c) <> 0 OR sum(t1) <> 0 OR sum(t2) <> 0"


def draw_batch(state: DataFrame, by: list[str], size: int = 256, seed: int = 1) -> DataFrame:
    """A sample without replacement of each group: by, lvl, i, v and status (OK or FAIL).

    The lowest level whose table is half empty is decoded; each coordinate of the vector is in it with
    probability 2**-lvl. A table that does not decode in full is FAIL, and its rows must not be used.
    """
    levels = expand(state, "lvl")
    used = levels.where(F.col("slot") < size).groupBy(*by, "lvl").agg(F.count("*").alias("t"))
    picked = used.groupBy(*by).agg(F.coalesce(F.min(F.when(F.col("t") <= FULL * size, F.col("lvl"))), F.max("lvl")).alias("lvl"))
    found = decode(levels.join(picked, [*by, "lvl"]), [*by, "lvl"], size, seed, ROLE)
    return found.select(*by, "lvl", F.col("item").alias("i"), "v", F.when(F.col("complete"), "OK").otherwise("FAIL").alias("status"))


def draw_again(u: DataFrame, by: list[str], size: int = 256, seed: int = 1, copies: int = 4) -> DataFrame:
    """The batch of each group from the first of up to copies independent states that decodes: two coordinates in the same three
    slots make a table fail (about one in a thousand), so one state alone fails for some of many groups."""
    from .checkpoints import cut

    out = None
    for n in range(copies):
        state = cut(build(u, by, size=size, seed=seed + n))
        got = cut(draw_batch(state, by, size, seed + n))
        failed = state.select(*by).distinct().join(got.where("status = 'OK'"), by, "left_anti")  # with those that give back nothing
        last = n == copies - 1 or failed.isEmpty()
        kept = got if last else got.where("status = 'OK'")
        out = kept if out is None else out.unionByName(kept)
        if last:
            return out
        u = u.join(failed, by, "left_semi")
    return out


def draw(state: DataFrame, by: list[str], size: int = 256, seed: int = 1, fresh: int = 99) -> DataFrame:
    """One coordinate of each group's batch, by the smallest fresh hash."""
    batch = draw_batch(state, by, size, seed)
    return batch.groupBy(*by).agg(F.min_by(F.struct("i", "v", "status"), F.struct(poly4("i", Seed.of(fresh, 8)), "i")).alias("x")).select(*by, "x.*")


def draw_sql(net: str, by: str, size: int = 256, levels: int = 20, seed: int = 1) -> str:
    """The batch by filtering the net vector (by, i, v) at the level that the tables' filling picks."""
    first = recovery_places(seed, ROLE)[0]
    return f"""WITH n AS (SELECT *, {level_sql(Seed.of(seed, 6).sql('i'), levels)} AS own, {first.sql('i')} % {size} AS slot FROM ({net})),
    e AS (SELECT *, unnest(range(0, own + 1))::INT AS lvl FROM n),
    f AS (SELECT {by}, lvl, count(*) AS t FROM (SELECT {by}, lvl, slot FROM e GROUP BY ALL HAVING sum(v) <> 0 OR sum(v * i) <> 0) GROUP BY ALL),
    p AS (SELECT {by}, coalesce(min(lvl) FILTER (t <= {FULL * size}), max(lvl)) AS lvl FROM f GROUP BY ALL)
    SELECT e.{by}, e.lvl, e.i, e.v, 'OK' AS status FROM e JOIN p ON e.{by} = p.{by} AND e.lvl = p.lvl"""
