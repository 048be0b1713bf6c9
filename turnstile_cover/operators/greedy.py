"""Greedy maximum coverage: exact rounds over a DataFrame, and a local form for samples."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from .checkpoints import cut


def trajectory(spark: SparkSession, rows: list[tuple], col_type: str) -> DataFrame:
    return spark.createDataFrame(rows, f"round int, col {col_type}, gain long, total long")


def cover_df(entries: DataFrame, k: int) -> DataFrame:
    """k rounds over entries (i, j): each picks the column that covers most open items, the smallest on a tie.

    One aggregate and one anti-join a round; only picks reach the driver. A round without gain takes the smallest
    column left. Fewer columns than k: all of them.
    """
    spark, kind = entries.sparkSession, entries.schema["j"].dataType.simpleString()
    whole = cut(entries.select("i", "j").distinct())
    left, picked, rows, total = whole, [], [], 0
    for r in range(1, k + 1):
        best = left.groupBy("j").agg(F.count("*").alias("g")).orderBy(F.desc("g"), "j").limit(1).collect()
        if not best:
            others = whole.where(~F.col("j").isin(picked)) if picked else whole
            rest = others.agg(F.min("j")).first()[0]
            if rest is None:
                break
            best = [(rest, 0)]
        j, gain = best[0][0], int(best[0][1])
        picked.append(j)
        total += gain
        rows.append((r, j, gain, total))
        if r < k and gain:
            left = cut(left.where(F.col("j") != j).join(left.where(F.col("j") == j).select("i"), "i", "left_anti"))
    return trajectory(spark, rows, kind)


def cover_local(pdf: pd.DataFrame, k: int, columns: np.ndarray | None = None, lazy: bool = True) -> list[tuple[int, int, int, int]]:
    """The same on a sample in memory; lazy keeps upper bounds of earlier rounds (gains never rise)."""
    items, i = np.unique(pdf["i"].to_numpy(), return_inverse=True)
    cols = np.unique(pdf["j"].to_numpy()) if columns is None else np.asarray(columns)
    place = {c: x for x, c in enumerate(cols.tolist())}
    members: list[list[int]] = [[] for _ in cols]
    for a, c in zip(i.tolist(), pdf["j"].tolist(), strict=True):
        members[place[c]].append(a)
    sets = [np.unique(np.array(m, np.int64)) for m in members]
    covered, bound = np.zeros(len(items), bool), np.array([len(s) for s in sets], np.int64)
    open_, out, total = np.ones(len(cols), bool), [], 0
    for r in range(1, min(k, len(cols)) + 1):
        best, best_gain = -1, -1
        for x in np.lexsort((np.arange(len(cols)), -bound)):
            if not open_[x]:
                continue
            if lazy and (bound[x] < best_gain or bound[x] == best_gain and x > best):
                break
            gain = int((~covered[sets[x]]).sum())
            bound[x] = gain
            if gain > best_gain or gain == best_gain and x < best:
                best, best_gain = int(x), gain
        covered[sets[best]] = True
        open_[best], bound[best] = False, -1
        total += best_gain
        out.append((r, int(cols[best]), best_gain, total))
    return out


def greedy_sql(entries: str, k: int, col_type: str = "BIGINT") -> str:
    """The trajectory as one SQL text; entries: a query of i and j."""
    parts = [f"a AS MATERIALIZED (SELECT DISTINCT i, j FROM ({entries}))"]
    for r in range(1, k + 1):
        taken = " UNION ALL ".join(f"SELECT j FROM r{x}" for x in range(1, r)) or "SELECT j FROM a WHERE false"
        open_ = f"a.i NOT IN (SELECT i FROM c{r - 1})" if r > 1 else "true"
        parts.append(f"r{r} AS MATERIALIZED (SELECT j, count(*) FILTER ({open_}) AS g FROM a WHERE j NOT IN ({taken}) GROUP BY j ORDER BY g DESC, j LIMIT 1)")
        before = f"SELECT i FROM c{r - 1} UNION " if r > 1 else ""
        parts.append(f"c{r} AS MATERIALIZED ({before}SELECT i FROM a WHERE j = (SELECT j FROM r{r}))")
    rows = " UNION ALL ".join(f"SELECT {r}::INT AS round, j::{col_type} AS col, g::BIGINT AS gain, (SELECT count(*) FROM c{r})::BIGINT AS total FROM r{r}" for r in range(1, k + 1))
    return f"WITH {', '.join(parts)} {rows}"
