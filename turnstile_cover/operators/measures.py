"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, functions as F

from ..plans.params import Params
from ..sources.features import Wide
from . import countsketch, coverage, fingerprint, l0, rowsample
from .checkpoints import cut


def coverage_of(entries: DataFrame, columns: list) -> DataFrame:
    """One row: items that the columns cover."""
    return entries.where(F.col("j").isin(columns)).agg(F.countDistinct("i").alias("covered"))


def ratio(entries: DataFrame, pick: list, reference: list) -> DataFrame:
    """One row: coverage of pick over coverage of reference."""
    both = entries.agg(F.countDistinct(F.when(F.col("j").isin(pick), F.col("i"))).alias("covered"), F.countDistinct(F.when(F.col("j").isin(reference), F.col("i"))).alias("reference"))
    return both.withColumn("ratio", F.round(F.try_divide("covered", "reference"), 6))


def pct_separated(w: Wide, user: int, cols: list[str]) -> DataFrame:
    """k and the percent of other users that the first k raw columns separate from the target."""
    row = w.df.where(F.col("uid") == user).select(*(F.col(c).alias(f"t_{c}") for c in cols))
    diff, parts = F.lit(False), []
    for n, c in enumerate(cols):
        diff = diff | ~F.col(c).eqNullSafe(F.col(f"t_{c}"))
        parts.append(F.struct(F.lit(n + 1).alias("k"), F.round(100 * F.count_if(diff) / F.count("*"), 6).alias("pct")))
    one = w.df.where(F.col("uid") != user).crossJoin(F.broadcast(row)).agg(F.array(*parts).alias("x"))
    return one.select(F.explode("x").alias("x")).select("x.k", "x.pct")


def pair_ratio(w: Wide, pick: list[str], reference: list[str], onehot: bool = True) -> DataFrame:
    """One row: pairs separated by pick over pairs separated by reference."""
    count = (lambda c: fingerprint.onehot_pairs(w, c)) if onehot else (lambda c: fingerprint.separated_pairs(w.df, c))
    both = count(pick).withColumnRenamed("separated", "ours").crossJoin(count(reference))
    return both.withColumn("ratio", F.round(F.try_divide("ours", "separated"), 6))


def rel_err(estimate: DataFrame, exact: DataFrame, column: str = "complement") -> DataFrame:
    both = estimate.select(F.col(column).cast("double").alias("estimate")).crossJoin(exact.select(F.col(column).cast("double").alias("exact")))
    return both.withColumn("rel_err", F.round(F.abs(F.col("estimate") - F.col("exact")) / F.greatest(F.abs("exact"), F.lit(1e-300)), 6))


def purity(labelled: DataFrame, cluster: str = "prediction", label: str = "lang") -> DataFrame:
    """One row: share of instances with the majority label of their cluster."""
    counts = labelled.groupBy(cluster, label).count().groupBy(cluster).agg(F.max("count").alias("most"), F.sum("count").alias("n"))
    return counts.agg(F.round(F.sum("most") / F.sum("n"), 6).alias("accuracy"), F.round(1 - F.sum("most") / F.sum("n"), 6).alias("error"))


def timed(make: Callable[[], DataFrame]) -> float:
    """Seconds to compute every row, without keeping them."""
    t = time.perf_counter()
    make().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def speedup(baseline_s: float, ours_s: float, once_s: float = 0.0) -> dict[str, float]:
    """Baseline time over ours, without and with the one-off part."""
    return {"speedup": baseline_s / ours_s, "speedup_with_build": baseline_s / (ours_s + once_s)}


def sketch_size(cells: DataFrame, n: int, d: int) -> DataFrame:
    """One row: cells against the n * d entries of the matrix."""
    return cells.agg(F.count("*").alias("cells")).select("cells", F.lit(n * d).alias("matrix_cells"), F.round(F.col("cells") / (n * d), 6).alias("share"))


def fanout(params: Params) -> dict[str, int]:
    """Cells that an update touches: recovery cells and column L0 cells."""
    return {"recovery": 3 * params.reps, "l0": params.l0_reps}


def counted_fanout(u: DataFrame, params: Params) -> DataFrame:
    """One row: updates, and the recovery cells and column L0 cells that they touch, counted before they are summed."""
    recovery, column = coverage.recovery_rows(u, params), l0.rows(u, ["j"], "i", params.l0_slots, params.l0_reps, params.levels, params.seed, params.wide)
    parts = [x.agg(F.count("slot" if n != "updates" else "c").alias(n)) for n, x in (("updates", u), ("recovery", recovery), ("l0", column))]
    return parts[0].crossJoin(F.broadcast(parts[1])).crossJoin(F.broadcast(parts[2]))  # a row each


def l0_over_seeds(u: DataFrame, by: str) -> DataFrame:
    """over_seeds of the largest l0_error. States are linear, so they are built from the net entries; those are dealt out by group
    once, and neither cells nor estimates of any seed are dealt out again."""
    a = cut(u.groupBy(by, "i").agg(F.sum("c").alias("c")).where("c <> 0"))
    parts = a.sparkSession.conf.get("spark.sql.shuffle.partitions")
    dealt = a.repartition(int(parts), by)
    return over_seeds(lambda x: l0_error(dealt, by, seed=x).agg(F.max("rel_err").alias("worst")), "worst")


def over_seeds(run: Callable[[int], DataFrame], value: str, seeds: range = range(10)) -> DataFrame:
    """One row: mean, least and 95th percentile of a one-row result over seeds."""
    rows = [run(s).select(F.lit(s).alias("seed"), F.col(value).cast("double").alias("value")) for s in seeds]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out.agg(F.avg("value").alias("mean"), F.min("value").alias("least"), F.percentile("value", 0.95).alias("p95"))


def failure_rate(draws: DataFrame, by: list[str]) -> DataFrame:
    """One row: groups, groups whose draw failed, and their share."""
    groups = draws.groupBy(*by).agg(F.max(F.col("status") != "OK").alias("failed"))
    return groups.agg(F.count("*").alias("trials"), F.count_if("failed").alias("failures")).withColumn("rate", F.try_divide("failures", "trials"))


def l0_error(u: DataFrame, by: str, slots: int = 1024, **sizes) -> DataFrame:
    """by, exact and estimated nonzeros, relative error."""
    exact = u.groupBy(by, "i").agg(F.sum("c").alias("v")).where("v <> 0").groupBy(by).agg(F.count("*").alias("exact"))
    est = l0.estimate(l0.build(u, [by], slots=slots, **sizes), [by], slots)
    return exact.join(est, by).select(by, "exact", "l0", F.round(F.abs(F.col("l0") - F.col("exact")) / F.col("exact"), 6).alias("rel_err"))


def countsketch_error(u: DataFrame, key: str, slots: int = 256, reps: int = 5, seed: int = 1) -> DataFrame:
    """One row: largest error of the estimates and the tail bound it is held against."""
    exact = u.groupBy(key).agg(F.sum("c").alias("f"))
    est = countsketch.estimate(countsketch.build(u, key, slots, reps, seed), exact, key, slots, reps, seed)
    worst = exact.join(est, key).agg(F.max(F.abs(F.col("f") - F.col("estimate"))).alias("max_error"))
    return worst.crossJoin(countsketch.residual_bound(u, key, slots))


def loss_split(entries: DataFrame, params: Params, pick: list, sample_pick: list, full_pick: list) -> DataFrame:
    """One row: coverage of the final answer, of greedy on the sample and of greedy on all, so each step's loss shows."""
    return entries.agg(*(F.countDistinct(F.when(F.col("j").isin(c), F.col("i"))).alias(n) for n, c in (("answer", pick), ("sample_greedy", sample_pick), ("full_greedy", full_pick))))


def exchange_bytes(df: DataFrame) -> int:
    """Bytes written by the exchanges of one run of df, from the metrics of its executed plan."""
    query = df._jdf.queryExecution()
    plan = query.executedPlan()
    query.toRdd().count()
    todo, total = [plan], 0
    while todo:
        node = todo.pop()
        if node.getClass().getSimpleName() == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
            continue
        if node.getClass().getSimpleName().endswith("QueryStageExec"):
            todo.append(node.plan())
        metric = node.metrics().get("shuffleBytesWritten")
        total += metric.get().value() if metric.isDefined() else 0
        children = node.children()
        todo += [children.apply(i) for i in range(children.size())]
    return total


def dataset_risk(w: Wide, cols: list[str]) -> DataFrame:
    """Sizes of groups with equal values on cols and the users in such groups: size 1 is unique, size below k breaks k-anonymity."""
    return w.df.groupBy(*cols).agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("classes"), F.sum("size").alias("users"))


large_small = rowsample.large_and_small
isolation = rowsample.isolation
