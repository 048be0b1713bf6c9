"""Samples of a matrix with direct access: capped rows under a budget, and bucketed rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from ..functions.hashing import Seed, level, poly4
from ..plans.params import Params

BINS = 1024
SHIFT = 21


def entry_hash(seed: int, role: int = 1, wide: bool = False):
    """A hash of the entry from hashes of its row and column."""
    return poly4((poly4("i", Seed.of(seed, role), wide) + poly4("j", Seed.of(seed, role + 1), wide)) % ((1 << 31) - 1), Seed.of(seed, role + 2))


def entry_hash_sql(seed: int, role: int = 1) -> str:
    return Seed.of(seed, role + 2).sql(f"(({Seed.of(seed, role).sql('i')} + {Seed.of(seed, role + 1).sql('j')}) % {(1 << 31) - 1})")


def cap_and_budget(entries: DataFrame, cap: int, budget: int, seed: int, by: list[str] | None = None, wide: bool = False) -> DataFrame:
    """At most cap entries a row (smallest entry hashes first), rows in hash order until budget entries are reached.

    by: columns of independent samples. The running total is taken inside bins of the row hash over the bins' own totals, so no
    window spans the whole sample.
    """
    by = by or []
    w = Window.partitionBy(*by, "i").orderBy(entry_hash(seed, wide=wide), "j")
    kept = entries.withColumn("rn_", F.row_number().over(w)).where(F.col("rn_") <= cap).drop("rn_")
    kept = kept.withColumn("rh", poly4("i", Seed.of(seed, 4), wide))
    rows = kept.groupBy(*by, "rh", "i").agg(F.count("*").alias("n")).withColumn("bin", F.shiftright("rh", SHIFT))
    bins = rows.groupBy(*by, "bin").agg(F.sum("n").alias("in_bin"))
    base = bins.withColumn("base", F.sum("in_bin").over(Window.partitionBy(*by).orderBy("bin").rowsBetween(Window.unboundedPreceding, -1))).select(*by, "bin", F.coalesce("base", F.lit(0)).alias("base"))
    before = F.sum("n").over(Window.partitionBy(*by, "bin").orderBy("rh", "i").rowsBetween(Window.unboundedPreceding, -1))
    chosen = rows.join(base, [*by, "bin"]).withColumn("before", F.col("base") + F.coalesce(before, F.lit(0))).where(F.col("before") < budget).select(*by, "i")
    return kept.drop("rh").join(chosen, [*by, "i"], "left_semi")


def capped_sample(entries: DataFrame, params: Params) -> DataFrame:
    """The sample of the matrix (i, j) that greedy needs, by direct access."""
    return cap_and_budget(entries.select("i", "j").distinct(), params.cap, params.budget, params.seed, wide=params.wide)


def cap_and_budget_sql(entries: str, cap: int, budget: int, seed: int, by: str = "") -> str:
    """by: a column of independent samples, with a comma after it."""
    if by:
        col = by.rstrip(", ")
        return f"""WITH q AS (SELECT {by} i, j, row_number() OVER (PARTITION BY {by} i ORDER BY {entry_hash_sql(seed)}, j) AS rn, {Seed.of(seed, 4).sql('i')} AS rh FROM (SELECT DISTINCT {by} i, j FROM ({entries}))),
        kept AS (SELECT {by} i, j, rh FROM q WHERE rn <= {cap}), rs AS (SELECT {by} rh, i, count(*) AS n FROM kept GROUP BY ALL),
        b AS (SELECT {by} i, coalesce(sum(n) OVER (PARTITION BY {col} ORDER BY rh, i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM rs)
        SELECT {by} i, j FROM kept JOIN b USING ({by} i) WHERE before < {budget}"""
    return f"""WITH q AS (SELECT i, j, row_number() OVER (PARTITION BY i ORDER BY {entry_hash_sql(seed)}, j) AS rn, {Seed.of(seed, 4).sql('i')} AS rh FROM (SELECT DISTINCT i, j FROM ({entries}))),
    kept AS (SELECT i, j, rh FROM q WHERE rn <= {cap}), rs AS (SELECT rh, i, count(*) AS n FROM kept GROUP BY ALL),
    b AS (SELECT i, coalesce(sum(n) OVER (ORDER BY rh, i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM rs)
    SELECT i, j FROM kept WHERE i IN (SELECT i FROM b WHERE before < {budget})"""


def bucketed_sample(entries: DataFrame, params: Params, row_level: int = 0, bucket_cap: int | None = None) -> DataFrame:
    """Two-level hashing: rows of row_level and more fall into buckets, each keeps bucket_cap entries; of its repetitions a row
    takes the one where most of its entries survive, the first on a tie; then cap and budget."""
    most, seed = bucket_cap or 8 * -(-params.d // params.k), params.seed
    a = entries.select("i", "j").distinct().where(level(poly4("i", Seed.of(seed, 20), params.wide), params.levels) >= row_level)
    reps = F.explode(F.array(*(F.struct(F.lit(r).alias("rep"), (poly4("i", Seed.of(seed, 30 + r), params.wide) % params.buckets).alias("bucket")) for r in range(params.reps))))
    spread = a.withColumn("x", reps).select("i", "j", "x.rep", "x.bucket", entry_hash(seed, 40, params.wide).alias("eh"))
    kept = spread.withColumn("rn", F.row_number().over(Window.partitionBy("rep", "bucket").orderBy("eh", "i", "j"))).where(F.col("rn") <= most)
    best = kept.groupBy("i", "rep").agg(F.count("*").alias("n")).groupBy("i").agg(F.max_by("rep", F.struct("n", -F.col("rep"))).alias("rep"))
    return cap_and_budget(kept.join(best, ["i", "rep"], "left_semi").select("i", "j"), params.cap, params.budget, seed, wide=params.wide)


def bucketed_sample_sql(entries: str, params: Params, row_level: int = 0, bucket_cap: int | None = None) -> str:
    from ..functions.hashing import level_sql

    most, seed = bucket_cap or 8 * -(-params.d // params.k), params.seed
    reps = " UNION ALL ".join(f"SELECT i, j, {r} AS rep, {Seed.of(seed, 30 + r).sql('i')} % {params.buckets} AS bucket, {entry_hash_sql(seed, 40)} AS eh FROM a" for r in range(params.reps))
    inner = f"""WITH a AS (SELECT DISTINCT i, j FROM ({entries}) WHERE {level_sql(Seed.of(seed, 20).sql('i'), params.levels)} >= {row_level}),
    s AS ({reps}), k AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY rep, bucket ORDER BY eh, i, j) AS rn FROM s) WHERE rn <= {most}),
    g AS (SELECT i, rep, row_number() OVER (PARTITION BY i ORDER BY count(*) DESC, rep) AS o FROM k GROUP BY i, rep)
    SELECT k.i, k.j FROM k JOIN g ON k.i = g.i AND k.rep = g.rep WHERE o = 1"""
    return cap_and_budget_sql(inner, params.cap, params.budget, seed)


def large_and_small(entries: DataFrame, params: Params) -> DataFrame:
    """One row: rows with d / k entries or more, other rows, and the entries of each."""
    rows = entries.select("i", "j").distinct().groupBy("i").agg(F.count("*").alias("n"))
    large = F.col("n") * params.k >= params.d
    return rows.agg(F.count_if(large).alias("large_rows"), F.count_if(~large).alias("small_rows"), F.coalesce(F.sum(F.when(large, F.col("n"))), F.lit(0)).alias("large_entries"), F.coalesce(F.sum(F.when(~large, F.col("n"))), F.lit(0)).alias("small_entries"))


def isolation(entries: DataFrame, params: Params, bucket_cap: int | None = None) -> DataFrame:
    """One row: nonzero rows, and those that share no bucket with another large row and few small entries in some repetition."""
    most = bucket_cap or 8 * -(-params.d // params.k)
    rows = entries.select("i", "j").distinct().groupBy("i").agg(F.count("*").alias("n")).withColumn("large", F.col("n") * params.k >= params.d)
    reps = F.explode(F.array(*(F.struct(F.lit(r).alias("rep"), (poly4("i", Seed.of(params.seed, 30 + r), params.wide) % params.buckets).alias("bucket")) for r in range(params.reps))))
    placed = rows.withColumn("x", reps).select("i", "n", "large", "x.*")
    full = placed.groupBy("rep", "bucket").agg(F.count_if("large").alias("nl"), F.coalesce(F.sum(F.when(~F.col("large"), F.col("n"))), F.lit(0)).alias("ns"))
    alone = (F.col("nl") - F.col("large").cast("int") == 0) & (F.col("ns") - F.when(F.col("large"), 0).otherwise(F.col("n")) <= most)
    return placed.join(full, ["rep", "bucket"]).groupBy("i").agg(F.max(alone).alias("ok")).agg(F.count("*").alias("n_rows"), F.count_if("ok").alias("isolated"))


def isolation_sql(entries: str, params: Params) -> str:
    most = 8 * -(-params.d // params.k)
    reps = " UNION ALL ".join(f"SELECT i, n, large, {r} AS rep, {Seed.of(params.seed, 30 + r).sql('i')} % {params.buckets} AS bucket FROM w" for r in range(params.reps))
    return f"""WITH w AS (SELECT i, count(DISTINCT j) AS n, count(DISTINCT j) * {params.k} >= {params.d} AS large FROM ({entries}) GROUP BY i), p AS ({reps}),
    f AS (SELECT rep, bucket, count(*) FILTER (large) AS nl, coalesce(sum(n) FILTER (NOT large), 0) AS ns FROM p GROUP BY ALL),
    o AS (SELECT p.i, bool_or(nl - large::INT = 0 AND ns - CASE WHEN large THEN 0 ELSE n END <= {most}) AS ok FROM p JOIN f USING (rep, bucket) GROUP BY p.i)
    SELECT count(*)::BIGINT AS n_rows, count(*) FILTER (ok)::BIGINT AS isolated FROM o"""
