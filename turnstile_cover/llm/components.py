"""Connected components by contraction: nodes hook onto smaller neighbours, and only links between different roots go on."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from .store import materialize


def connected_components(edges: DataFrame) -> DataFrame:
    """node and component (smallest node reachable) of every node of edges (a, b).

    Every tree of a round has two nodes at least, so each round halves what is left or better. Loops and
    links with a null end are no links.
    """
    low, high = F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")
    links = materialize(edges.where("a <> b").select(low, high).distinct(), "cc-edges")
    labels = links.select(F.col("a").alias("node"), F.col("b").alias("component"))
    first = True
    while not links.isEmpty():
        both = links.union(links.select("b", "a"))
        hook = materialize(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("near")).select("node", F.least("node", "near").alias("component")), "cc-hooks")
        while True:  # paths of hooks halve until all nodes know their root
            up = hook.select(F.col("node").alias("component"), F.col("component").alias("jump"))
            jumped = materialize(hook.join(up, "component").select("node", F.col("component").alias("old"), F.col("jump").alias("component")), "cc-hooks")
            hook = jumped.select("node", "component")
            if jumped.where("component <> old").isEmpty():
                break
        ends = [hook.select(F.col("node").alias(x), F.col("component").alias(f"{x}_root")) for x in ("a", "b")]
        moved = links.join(ends[0], "a").join(ends[1], "b").select(F.col("a_root").alias("a"), F.col("b_root").alias("b"))
        links = materialize(moved.where("a <> b").select(low, high).distinct(), "cc-edges")
        if first:
            labels, first = hook, False
        else:
            up = hook.select(F.col("node").alias("component"), F.col("component").alias("root"))
            labels = materialize(labels.join(up, "component", "left").select("node", F.coalesce("root", "component").alias("component")), "cc-labels")
    return labels
