"""Exact methods and older sketches that the methods are compared with."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame, functions as F

from ..sources.features import Wide
from . import fingerprint, targeted
from .greedy import cover_df, trajectory
from .moments import f2_sign_sketch


def greedy_cover(entries: DataFrame, k: int) -> DataFrame:
    """Greedy on the full input."""
    return cover_df(entries, k)


def targeted_exact(w: Wide, user: int, k: int) -> DataFrame:
    """The exact method for one target."""
    return targeted.exact(w, user, k)


def targeted_exact_many(w: Wide, users: DataFrame, k: int) -> DataFrame:
    """The exact method for many targets in one pass: no row is left out."""
    return targeted.fingerprint_all(w, users, k, 1.0)


def general_exact(w: Wide, k: int, onehot: bool = True, variant: str = "expression") -> DataFrame:
    """Class refinement on all users. variant cached_classes writes each round's classes instead of computing them from the row."""
    if variant != "cached_classes":
        return fingerprint.greedy_onehot(w, k) if onehot else fingerprint.greedy_raw(w, k)
    from .checkpoints import cut

    c = w.codes()
    n, rows, before = c.df.count(), [], 0
    state, left = c.df.withColumn("cls", F.lit(0).cast("long")), list(w.attributes)
    for r in range(1, min(k, len(left)) + 1):
        options = F.explode(F.array(*(F.struct(F.lit(w.attributes.index(a)).alias("a"), F.col(a).alias("v")) for a in left)))
        f = state.select("cls", options.alias("o")).groupBy("cls", "o").agg(F.count("*").alias("f"))
        best = f.groupBy("o.a").agg(F.sum(F.col("f").cast("decimal(19,0)") * F.col("f")).alias("s")).orderBy("s", "a").first()
        a = w.attributes[best["a"]]
        left.remove(a)
        total = (n * n - int(best["s"])) // 2
        rows.append((r, a, total - before, total))
        before = total
        state = cut(state.withColumn("cls", F.xxhash64("cls", a)))
    return trajectory(w.df.sparkSession, rows, "string")


def general_via_pairs(w: Wide, k: int) -> DataFrame:
    """Reduction to coverage over all pairs of users: quadratic, for a few thousand users; kept to show why it is not used."""
    a = w.df.select(F.col("uid").alias("u1"), *(F.col(c).alias(f"a_{c}") for c in w.attributes))
    b = w.df.select(F.col("uid").alias("u2"), *(F.col(c).alias(f"b_{c}") for c in w.attributes))
    both = a.join(b, F.col("u1") < F.col("u2"))
    differ = F.filter(F.array(*(F.when(F.col(f"a_{c}") != F.col(f"b_{c}"), F.lit(n)) for n, c in enumerate(w.attributes))), lambda x: x.isNotNull())
    entries = both.select(F.struct("u1", "u2").alias("i"), F.explode(differ).alias("j"))
    names = F.array(*map(F.lit, w.attributes))
    return cover_df(entries, k).select("round", F.element_at(names, F.col("col") + 1).alias("col"), "gain", "total")


def f2_sketch_complement(values: DataFrame, reps: int = 64, seed: int = 1) -> DataFrame:
    return f2_sign_sketch(values, reps, seed)


def optimum(entries: DataFrame, k: int, most_sets: int = 200_000) -> DataFrame:
    """The best k columns of all: round, col, gain, total; for small d and k. Sets are scored in one aggregate."""
    spark, a = entries.sparkSession, entries.select("i", "j").distinct()
    cols = sorted(r[0] for r in a.select("j").distinct().collect())
    sets = list(combinations(cols, min(k, len(cols))))
    if len(sets) > most_sets:
        raise ValueError(f"{len(sets)} sets of {k} of {len(cols)} columns are too many")
    kind = a.schema["j"].dataType.simpleString()
    listed = spark.createDataFrame([(n, list(s)) for n, s in enumerate(sets)], f"s int, cols array<{kind}>")
    scored = listed.select("s", F.explode("cols").alias("j")).join(a, "j").groupBy("s").agg(F.countDistinct("i").alias("total"))
    best = scored.orderBy(F.desc("total"), "s").limit(1).join(listed, "s")
    return best.select((F.posexplode("cols")), "total").select((F.col("pos") + 1).alias("round"), F.col("col"), F.lit(None).cast("long").alias("gain"), "total")


def hll_union(entries: DataFrame, columns: list) -> DataFrame:
    """Insertion-only sketch of a union: one row; wrong once entries are deleted."""
    per = entries.where(F.col("j").isin(columns)).groupBy("j").agg(F.hll_sketch_agg("i", F.lit(14)).alias("s"))
    return per.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("estimate"))


def theta_union(entries: DataFrame, columns: list) -> DataFrame:
    per = entries.where(F.col("j").isin(columns)).groupBy("j").agg(F.expr("theta_sketch_agg(i)").alias("s"))
    return per.agg(F.expr("theta_sketch_estimate(theta_union_agg(s))").alias("estimate"))


def bitmap_union(entries: DataFrame, columns: list) -> DataFrame:
    """Exact union of non-negative ids by bitmaps, a bucket at a time."""
    ids = entries.where(F.col("j").isin(columns)).select((F.col("i") + 1).alias("x"), "j")
    per = ids.groupBy("j", F.bitmap_bucket_number("x").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("x")).alias("m"))
    return per.groupBy("b").agg(F.bitmap_count(F.bitmap_or_agg("m")).alias("n")).agg(F.sum("n").alias("estimate"))
