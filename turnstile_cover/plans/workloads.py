"""The experiment runs: targeted and general sweeps, clustering, coverage and moments, as tables of results."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import baselines, checkpoints, cluster, coverage, fingerprint, measures, moments, targeted
from ..sources import features
from ..sources.matrix import WORKLOADS, net
from ..sources.tables import table
from .params import Params

WIDE = {"F1": features.people, "F2": features.census, "F2s": features.lines_only, "F3": features.evolving}


def clock(make):
    t = time.perf_counter()
    out = make()
    return out, time.perf_counter() - t


def targeted_sweep(spark: SparkSession, d: str, name: str, rates: list[float], k: int = 7, seeds: int = 10) -> DataFrame:
    """workload, rate, k, mean and least percent of the other users that a target's first k features separate, over every user of
    the table as target and all seeds."""
    w = WIDE[name](spark, d)
    c = w.codes()
    n = c.df.count()
    rows = targeted.sweep_totals(c, k, rates, seeds)
    pct = lambda x: 100 * F.col(x) / max(1, n - 1)
    return rows.groupBy("rate", "k").agg(F.avg(pct("separated")).alias("pct"), F.min(pct("least")).alias("least"), F.max("users").alias("targets"), F.countDistinct("seed").alias("seeds")).withColumn("workload", F.lit(name))


def targeted_times(spark: SparkSession, d: str, name: str, rates: list[float], k: int = 7, targets: int = 200) -> DataFrame:
    """rate, seconds a target with the sample built, of the build, and of the exact method for the same targets (rate 1) over them.

    All rates run the same code on the same targets (the users of the smallest hashes), so a speedup compares equal work.
    """
    w = WIDE[name](spark, d)
    c = w.codes()
    users = c.df.orderBy(F.xxhash64("uid"), "uid").limit(targets).select("uid")
    rows, base = [], None
    for rate in [1.0, *rates]:
        _, build = clock(lambda r=rate: targeted.fingerprint_all(w, users.limit(0), k, r, codes=c).count())
        _, whole = clock(lambda r=rate: targeted.fingerprint_all(w, users, k, r, codes=c).write.format("noop").mode("overwrite").save())
        each = max(1e-9, whole - build) / targets
        base = base or (each, whole)
        rows.append((name, rate, each, build, base[0] / each, base[1] / whole))
    return spark.createDataFrame(rows, "workload string, rate double, seconds_a_target double, build_seconds double, speedup double, speedup_with_build double")


def targeted_baseline(spark: SparkSession, d: str, name: str, k: int = 7, users: tuple[int, ...] = (0,)) -> DataFrame:
    """The exact method for single targets, a scan a round: uid, seconds, percent separated."""
    w, rows = WIDE[name](spark, d), []
    c = w.codes()
    n = c.df.count()
    for u in users:
        got, s = clock(lambda x=u: targeted.exact(w, x, k, codes=c).collect())
        rows.append((name, int(u), s, 100.0 * got[-1]["total"] / (n - 1) if got else float("nan")))
    return spark.createDataFrame(rows, "workload string, uid long, seconds double, pct double")


def general_sweep(spark: SparkSession, d: str, name: str, rows: list[int] | None = None, shares: list[float] | None = None, k: int = 20, seeds: int = 10) -> DataFrame:
    """workload, sample_rows, k, mean and least ratio of pairs separated to exact greedy's, over all seeds, for every k up to k."""
    w = WIDE[name](spark, d)
    c = w.codes()
    n = c.df.count()
    exact = {r["round"]: r["total"] for r in fingerprint.greedy_onehot(w, k, n, c).collect()}
    sizes = rows or [max(2, round(x * n)) for x in shares or []]
    runs = [(r["sample_rows"], r["seed"], [(p["a"], p["v"]) for p in r["picks"]]) for r in fingerprint.sweep_rowhash(c, k, sizes, seeds, n).collect()]  # a row a run
    pairs = fingerprint.prefix_pairs(c, [(i, picks) for i, (_, _, picks) in enumerate(runs)])
    named = spark.createDataFrame([(i, size, seed) for i, (size, seed, _) in enumerate(runs)], "run int, sample_rows int, seed int")
    best = spark.createDataFrame(sorted(exact.items()), "k int, exact long")
    ratio = F.col("separated") / F.col("exact")
    both = pairs.join(F.broadcast(named), "run").join(F.broadcast(best), "k")
    return both.groupBy("sample_rows", "k").agg(F.avg(ratio).alias("ratio"), F.min(ratio).alias("least"), F.count("*").alias("seeds")).withColumn("workload", F.lit(name))


def cluster_table(spark: SparkSession, d: str, name: str = "W1", xs: tuple[int, ...] = (3, 4, 5)) -> DataFrame:
    """x, method, accuracy, seconds of k-means on selected, random and all features."""
    df, names = features.letter_frequencies(spark, d) if name == "W1" else features.embedding_dims(spark, d)
    df = df.persist()
    k = df.select("lang").distinct().count()
    rows = []
    for x in xs:
        chosen = [r["col"] for r in cluster.select_features(df, names, x).orderBy("round").collect()]
        for method, make in (("selected", lambda c=chosen: cluster.reduce_and_cluster(df, c, k)), ("random", lambda x=x: cluster.kmeans_random(df, names, x, k))):
            acc, s = clock(lambda m=make: measures.purity(m()).first()["accuracy"])
            rows.append((name, x, method, float(acc), s))
    acc, s = clock(lambda: measures.purity(cluster.kmeans_full(df, names, k)).first()["accuracy"])
    rows.append((name, len(names), "all", float(acc), s))
    df.unpersist()
    return spark.createDataFrame(rows, "workload string, x int, method string, accuracy double, seconds double")


def coverage_table(spark: SparkSession, d: str, name: str = "c1t", k: int = 5) -> DataFrame:
    """method, coverage ratio to full greedy, seconds. The net entries are written once for all methods, also for the sketch: its cells are
    sums, so an entry's updates may be added before they are hashed. What a method wrote is deleted when its columns are known."""
    v = checkpoints.cut(net(WORKLOADS[name][0](spark, d)))
    a = v.select("i", "j")
    n, dd = a.agg(F.max("i") + 1, F.max("j") + 1).first()
    p, since = Params.practical(n, dd, k), checkpoints.mark()
    full = [r["col"] for r in baselines.greedy_cover(a, k).collect()]
    checkpoints.release(spark, since)
    rows = []
    for method, make in (("sketch", lambda: coverage.max_coverage_net(v, p).first()["cols"]), ("capped_sample", lambda: [r["col"] for r in coverage.cover_from_sample(a, p).collect()]), ("bucketed_sample", lambda: [r["col"] for r in coverage.cover_from_sample(a, p, "bucketed").collect()])):
        cols, s = clock(make)
        checkpoints.release(spark, since)
        rows.append((name, method, float(measures.ratio(a, list(cols), full).first()["ratio"]), s))
    return spark.createDataFrame(rows, "workload string, method string, ratio double, seconds double")


def moment_table(spark: SparkSession, d: str, ps: tuple[int, ...] = (2, 3)) -> DataFrame:
    """column, p, branch, relative error of the complement, and of the complement from an F_2 sketch (p = 2)."""
    lines, rows = table(spark, d, "lineitem"), []
    for c in ("l_linestatus", "l_linenumber", "l_suppkey"):
        code = F.pmod(F.xxhash64(F.col(c).cast("string")), F.lit(1 << 20)).alias("x")
        v = lines.select(F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("uid"), code)
        n = v.count()
        for p in ps:
            exact = float(moments.complement_exact(v, p).first()[0])
            got = moments.complement_of_sample(v, n, p, 1250).first()
            old = float(moments.f2_sign_sketch(v.select("x")).first()["complement"]) if p == 2 else float("nan")
            rows.append((c, p, got["branch"], abs(got["complement"] - exact) / exact, abs(old - exact) / exact))
    return spark.createDataFrame(rows, "col string, p int, branch string, rel_err double, rel_err_f2 double")
