"""Frequency moments and the complement n^p - F_p with error relative to the complement."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..functions.hashing import PRIME, Seed, poly4, sign
from . import l0, l0sampler
from .cells import keys, merge, sums


def frequencies(values: DataFrame) -> DataFrame:
    """x and f of a table with column x."""
    return values.groupBy("x").agg(F.count("*").alias("f"))


def power_sum(f: str, p: int) -> Column:
    term = F.lit(1).cast("decimal(38,0)")
    for _ in range(p):
        term = (term * F.col(f).cast("decimal(19,0)")).cast("decimal(38,0)")
    return F.coalesce(F.sum(term).cast("decimal(38,0)"), F.lit(0).cast("decimal(38,0)"))


def fp(values: DataFrame, p: int) -> DataFrame:
    """One row: F_p; F_0 counts distinct values, F_1 all."""
    return frequencies(values).agg(power_sum("f", p).alias("fp"))


def complement_exact(values: DataFrame, p: int) -> DataFrame:
    n = power_sum("n", p)
    return frequencies(values).agg(F.sum("f").alias("n"), power_sum("f", p).alias("fp")).groupBy().agg(n.alias("np"), F.first("fp").alias("fp")).select((F.col("np") - F.col("fp")).cast("decimal(38,0)").alias("complement"))


def as_long(row: DataFrame, column: str, n: int, p: int) -> DataFrame:
    """A moment of n values as a long while n^p fits one; else it stays a decimal."""
    return row.select(F.col(column).cast("long").alias(column)) if n**p < 1 << 63 else row.select(column)


def skew(values: DataFrame) -> DataFrame:
    """One row: distinct * F_2 / n^2; 1 is even, larger is skewed."""
    return frequencies(values).agg((F.count("*") * F.sum(F.col("f").cast("double") ** 2) / F.sum("f").cast("double") ** 2).alias("skew"))


def sample_freqs(sample: DataFrame, population: float) -> DataFrame:
    """Values of a sample (column x) with their frequencies scaled to the population."""
    n = sample.agg(F.count("*").alias("t"))  # one row
    return frequencies(sample).crossJoin(F.broadcast(n)).select("x", (F.col("f") * population / F.col("t")).alias("f"))


def finish(first: DataFrame, rest: DataFrame, n: int, p: int, gamma: float) -> DataFrame:
    """complement, branch, b and f_b from the top value (b, f, f_shifted) and the frequencies (x, f) of the other values.

    Below the cut of all small values the answer is n^p; over half the population the top frequency comes from the
    shifted count; between, from the sample. Rare values of the rest are left out.
    """
    g = gamma ** (1 / (p - 1))
    small = F.col("f_top") < 0.75 * g * n
    top = F.when(F.col("f_top") > n / 2, F.col("f_shifted")).otherwise(F.col("f_top"))
    branch = F.when(small, "all_small").when(F.col("f_top") > n / 2, "dominant").otherwise("middle")
    head = first.select("b", "f_top", top.alias("f_b"), branch.alias("branch"))
    tail = rest.crossJoin(F.broadcast(head)).where((F.col("x") != F.col("b")) & (F.col("f") >= 0.25 * g * (n - F.col("f_b")))).agg(F.coalesce(F.sum(F.pow("f", F.lit(float(p)))), F.lit(0.0)).alias("tail"))
    whole = float(n) ** p
    value = F.when(F.col("branch") == "all_small", F.lit(whole)).otherwise(F.lit(whole) - F.pow("f_b", F.lit(float(p))) - F.col("tail"))
    return head.crossJoin(F.broadcast(tail)).select(F.greatest(value, F.lit(0.0)).alias("complement"), "branch", "b", "f_b")


HALVES = (0, 1)


def half_seeds(seed: int, half: int) -> tuple[int, int]:
    """Seeds of a half's L0 state and of its sampler: the two halves are independent."""
    return seed + 10 * half, seed + 1 + 10 * half


def from_draws(draws: list[DataFrame], unit: DataFrame, by: list[str], size: int, seed: int):
    """First sample (by, x, f: how often drawn) from the first half's sampler, and a function of the top values that draws from
    the second half after b is subtracted from every coordinate; draws that FAIL are left out."""
    def counted(state: DataFrame, half: int) -> DataFrame:
        drawn = l0sampler.draw_batch(state, by, size, half_seeds(seed, half)[1]).where("status = 'OK'")
        return drawn.groupBy(*by, F.col("v").alias("x")).agg(F.count("*").alias("f"))

    def second(tops: DataFrame) -> DataFrame:
        moved = counted(shift_by(draws[1], unit, tops, by), 1)
        return moved.join(tops.select(*by, "b"), by).select(*by, (F.col("x") + F.col("b")).alias("x"), "f")

    return counted(draws[0], 0), second


def shift_by(state: DataFrame, unit: DataFrame, tops: DataFrame, by: list[str]) -> DataFrame:
    """Every group's state of x - b; unit: cells of the vector of ones, without the group."""
    names = sums(state)
    taken = unit.crossJoin(F.broadcast(tops.where("b <> 0").select(*by, "b"))).select(*by, *keys(unit), *((-F.col("b").cast("decimal(19,0)") * F.col(x)).cast("decimal(38,0)").alias(x) for x in names))
    return merge(state.select(*keys(state), *(F.col(x).cast("decimal(38,0)").alias(x) for x in names)), taken.select(*keys(state), *names))


def complement_by(counts: list[DataFrame], unit: DataFrame, draws: tuple, groups: DataFrame, by: list[str], n: int, p: int, gamma: float, slots: int) -> DataFrame:
    """by, complement, branch, b, f_b of each group's vector, from two L0 states, the ones' second L0 state, and samples.

    Below the cut of all small values the answer is n^p; over half the population the top frequency comes from the
    shifted count; between, from the sample. Rare values of the rest are left out.
    """
    from .checkpoints import cut

    first, second = draws
    g, whole = gamma ** (1 / (p - 1)), float(n) ** p
    level_of = lambda cells: l0.estimate(cells, by, slots).select(*by, F.least(F.col("l0"), F.lit(float(n))).alias("w"))
    w1 = groups.join(level_of(counts[0]), by, "left").select(*by, F.coalesce("w", F.lit(0.0)).alias("w1"))
    best = first.groupBy(*by).agg(F.min_by(F.struct("x", "f"), F.struct(-F.col("f"), F.col("x"))).alias("top"), F.sum("f").alias("t"))
    seen = w1.join(best, by, "left").select(*by, "w1", F.col("top.x").alias("x"), (F.col("top.f") * F.col("w1") / F.col("t")).alias("f"))
    zero = n - F.col("w1")
    tops = cut(seen.select(*by, F.when(F.col("f") >= zero, F.col("x")).otherwise(0).cast("long").alias("b"), F.when(F.col("f") >= zero, F.col("f")).otherwise(zero).alias("f_top")))
    moved = level_of(shift_by(counts[1], unit, tops, by))
    head = tops.join(moved, by, "left").withColumn("w2", F.coalesce("w", F.lit(0.0))).drop("w")
    dominant = F.col("f_top") > n / 2
    head = head.withColumns({"f_b": F.when(dominant, n - F.col("w2")).otherwise(F.col("f_top")), "branch": F.when(F.col("f_top") < 0.75 * g * n, "all_small").when(dominant, "dominant").otherwise("middle")})
    other = second(tops)
    scaled = other.join(other.groupBy(*by).agg(F.sum("f").alias("t")), by).join(head, by).select(*by, "x", "b", "f_b", (F.col("f") * F.col("w2") / F.col("t")).alias("f"))
    tail = keep_large(scaled, n, g).groupBy(*by).agg(F.sum(F.pow("f", F.lit(float(p)))).alias("tail"))
    value = F.when(F.col("branch") == "all_small", F.lit(whole)).otherwise(whole - F.pow("f_b", F.lit(float(p))) - F.coalesce("tail", F.lit(0.0)))
    return head.join(tail, by, "left").select(*by, F.greatest(value, F.lit(0.0)).alias("complement"), "branch", "b", "f_b")


def keep_large(freqs: DataFrame, n: int, g: float) -> DataFrame:
    """Values but the top one (x, b, f, f_b) of at least a quarter of g of what the top value leaves."""
    return freqs.where((F.col("x") != F.col("b")) & (F.col("f") >= 0.25 * g * (n - F.col("f_b"))))


def complement(u: DataFrame, universe: DataFrame, n: int, p: int = 2, gamma: float = 0.05, size: int = 1024, slots: int = 1024, reps: int = 5, seed: int = 1) -> DataFrame:
    """The complement of a vector given by updates (i, c), from its linear states alone: two L0 states and two samplers.

    universe: the rows (i); their state of ones lets b be subtracted from every coordinate after the stream.
    """
    from .checkpoints import cut

    zero = F.lit(0)
    vector, ones = u.select(zero.alias("g"), "i", "c"), universe.select(zero.alias("g"), "i", F.lit(1).cast("long").alias("c"))
    counts = [cut(l0.build(vector, ["g"], slots=slots, reps=reps, seed=half_seeds(seed, h)[0])) for h in HALVES]
    unit = cut(l0.build(ones, ["g"], slots=slots, reps=reps, seed=half_seeds(seed, 1)[0]).drop("g"))
    draws = [cut(l0sampler.build(vector, ["g"], size=size, seed=half_seeds(seed, h)[1])) for h in HALVES]
    unit_draws = cut(l0sampler.build(ones, ["g"], size=size, seed=half_seeds(seed, 1)[1]).drop("g"))
    groups = u.sparkSession.range(1).select(F.lit(0).alias("g"))
    return complement_by(counts, unit, from_draws(draws, unit_draws, ["g"], size, seed), groups, ["g"], n, p, gamma, slots).drop("g")


def complement_sql(net: str, universe: str, p: int = 2, gamma: float = 0.05, size: int = 1024, slots: int = 1024, reps: int = 5, seed: int = 1) -> str:
    """The same by SQL on the net vector (i, v) over the universe (i): complement, branch, b, f_b."""
    g = gamma ** (1 / (p - 1))
    seeds = [half_seeds(seed, h) for h in HALVES]
    first = "SELECT 0 AS g, i, v FROM x"
    moved = "SELECT 0 AS g, u.i AS i, coalesce(x.v, 0) - (SELECT b FROM tops) AS v FROM uni u LEFT JOIN x USING (i) WHERE coalesce(x.v, 0) <> (SELECT b FROM tops)"
    counted = lambda q, s: l0.estimate_sql(l0.build_sql(f"SELECT g, i, v AS c FROM ({q})", "g", slots=slots, reps=reps, seed=s), "g", slots)
    drawn = lambda q, s: f"SELECT v AS x, count(*) AS f FROM ({l0sampler.draw_sql(q, 'g', size=size, seed=s)}) GROUP BY v"
    return f"""WITH uni AS MATERIALIZED ({universe}), x AS MATERIALIZED ({net}), n AS (SELECT count(*)::DOUBLE AS n FROM uni),
    w1 AS MATERIALIZED (SELECT least(coalesce((SELECT l0 FROM ({counted(first, seeds[0][0])})), 0.0), n) AS w FROM n), s1 AS MATERIALIZED ({drawn(first, seeds[0][1])}),
    t1 AS (SELECT x, f * (SELECT w FROM w1) / (SELECT sum(f) FROM s1) AS f FROM s1 ORDER BY f DESC, x LIMIT 1),
    tops AS MATERIALIZED (SELECT CASE WHEN coalesce(t1.f, -1) >= n - w THEN t1.x ELSE 0 END AS b, greatest(coalesce(t1.f, -1), n - w) AS f_top FROM n CROSS JOIN w1 LEFT JOIN t1 ON true),
    w2 AS MATERIALIZED (SELECT least(coalesce((SELECT l0 FROM ({counted(moved, seeds[1][0])})), 0.0), n) AS w FROM n),
    s2 AS MATERIALIZED (SELECT x + (SELECT b FROM tops) AS x, f FROM ({drawn(moved, seeds[1][1])})),
    head AS MATERIALIZED (SELECT b, f_top, CASE WHEN f_top > n / 2 THEN n - w2.w ELSE f_top END AS f_b, CASE WHEN f_top < {0.75 * g!r}::DOUBLE * n THEN 'all_small' WHEN f_top > n / 2 THEN 'dominant' ELSE 'middle' END AS branch FROM tops, n, w2),
    scaled AS (SELECT x, f * (SELECT w FROM w2) / (SELECT sum(f) FROM s2) AS f FROM s2),
    tail AS (SELECT coalesce(sum(pow(f, {p})), 0.0) AS t FROM scaled, head, n WHERE x <> b AND f >= {0.25 * g!r}::DOUBLE * (n - f_b))
    SELECT greatest(CASE WHEN branch = 'all_small' THEN pow(n, {p}) ELSE pow(n, {p}) - pow(f_b, {p}) - t END, 0.0) AS complement, branch, b::BIGINT AS b, f_b FROM head, tail, n"""


def complement_of_sample(vector: DataFrame, n: int, p: int, samples: int, seed: int = 1, gamma: float = 0.01) -> DataFrame:
    """The same from a vector at hand (uid, x): counts are exact, samples are the rows of the smallest hashes, or all rows where they are as many."""
    h = poly4(F.pmod("uid", F.lit(PRIME)), Seed.of(seed, 61))
    bound = int(min(1.0, (2 * samples + 50) / max(1, n)) * PRIME) + 1
    first = vector if samples >= n else vector.withColumn("h", h).where(F.col("h") < bound).orderBy("h", "uid").limit(samples)
    top = sample_freqs(first.select("x"), float(n)).orderBy(F.desc("f"), "x").limit(1).select(F.col("x").alias("b"), F.col("f").alias("f_top"))
    rest = vector.crossJoin(F.broadcast(top)).where("x <> b")
    w2 = rest.agg(F.count("*").alias("w2"))
    head = top.crossJoin(F.broadcast(w2)).select("b", "f_top", (F.lit(float(n)) - F.col("w2")).alias("f_shifted"), "w2")
    scale = F.least(F.lit(1.0), F.lit(2.0 * samples) / F.greatest(F.col("w2"), F.lit(1)))
    second = rest.crossJoin(F.broadcast(w2)).withColumn("h", h).where(F.col("h") < scale * PRIME)
    drawn = second.groupBy("x").agg(F.count("*").alias("f"), F.first("w2").alias("w2"))
    t = drawn.agg(F.sum("f").alias("t"))
    freqs = drawn.crossJoin(F.broadcast(t)).select("x", (F.col("f") * F.col("w2") / F.col("t")).alias("f"))
    return finish(head.select("b", "f_top", "f_shifted"), freqs, n, p, gamma)


def top_value(u: DataFrame, universe: DataFrame, n: int, **sizes) -> DataFrame:
    """The most frequent value under deletions and its frequency."""
    return complement(u, universe, n, 2, **sizes).select("b", "f_b")


def f2_sign_sketch(values: DataFrame, reps: int = 64, seed: int = 1) -> DataFrame:
    """One row: F_2 of integer values x by squared random-sign sums, and n^2 - F_2 from it: the error is relative to F_2, so the
    complement is poor when it is small."""
    parts = F.explode(F.array(*(F.struct(F.lit(r).alias("rep"), sign(poly4(F.pmod("x", F.lit(PRIME)), Seed.of(seed, 70 + r))).alias("s")) for r in range(reps))))
    # the sums are linear, so equal values are hashed once
    sums = frequencies(values).select("f", parts.alias("y")).groupBy("y.rep").agg(F.sum(F.col("y.s") * F.col("f")).alias("z"), F.sum("f").alias("n"))
    return sums.agg(F.avg(F.col("z").cast("double") ** 2).alias("f2"), F.max("n").alias("n")).select(F.round("f2", 6).alias("f2"), F.round(F.col("n").cast("double") ** 2 - F.col("f2"), 6).alias("complement"))


def f2_sign_sql(values: str, reps: int = 64, seed: int = 1) -> str:
    parts = " UNION ALL ".join(f"SELECT {r} AS rep, sum(2 * ({Seed.of(seed, 70 + r).sql('x')} & 1) - 1)::DOUBLE AS z, count(*)::DOUBLE AS n FROM ({values})" for r in range(reps))
    return f"SELECT round(avg(z * z), 6) AS f2, round(max(n) * max(n) - avg(z * z), 6) AS complement FROM ({parts})"
