"""SQL functions: the hash, levels and estimators as inlined SQL functions, and a selection table function."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..functions.hashing import Seed


@udtf(returnType="round int, col long, gain long, total long")
class CoverageSelect:
    """Greedy columns of a decoded sample (i, j), which fits one task by its budget."""

    def __init__(self):
        self.rows, self.k = [], 0

    def eval(self, row, k: int):
        self.rows.append((row["i"], row["j"]))
        self.k = k

    def terminate(self):
        import pandas as pd

        from .greedy import cover_local

        if self.rows:
            yield from cover_local(pd.DataFrame(self.rows, columns=["i", "j"]), self.k)


def register(spark: SparkSession, seed: int = 1) -> None:
    """tc_hash(x), tc_level(h, top), tc_sign(h), tc_l0(filled, slots, level) and coverage_select(TABLE(entries), k)."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION tc_hash(x BIGINT) RETURNS BIGINT RETURN {Seed.of(seed).sql('x')}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tc_level(h BIGINT, top INT) RETURNS INT RETURN least(bit_count((h & -h) - 1), top)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tc_sign(h BIGINT) RETURNS BIGINT RETURN 2 * (h & 1) - 1")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tc_l0(filled BIGINT, slots BIGINT, level INT) RETURNS DOUBLE RETURN pow(2, level) * ln(1 - filled / slots) / ln(1 - 1 / slots)")
    spark.udtf.register("coverage_select", CoverageSelect)
