"""Feature selection before k-means, with all features and random ones to compare."""

from __future__ import annotations

import random

from pyspark.ml.clustering import KMeans
from pyspark.ml.feature import StandardScaler, VectorAssembler
from pyspark.sql import DataFrame

from ..sources.features import Wide, quantised
from . import fingerprint


def select_features(df: DataFrame, names: list[str], x: int, bins: int = 10) -> DataFrame:
    """The x quantised columns that separate the most pairs: round, col, gain, total."""
    q = quantised(df, names, bins).withColumnRenamed("doc_id", "uid")
    return fingerprint.greedy_raw(Wide(q, tuple(names), frozenset(), ""), x)


def reduce_and_cluster(df: DataFrame, features: list[str], k: int, seed: int = 1, init: str = "k-means||") -> DataFrame:
    """df with prediction: k-means on the standardised features; init: k-means|| (parallel k-means++) or random."""
    assembled = VectorAssembler(inputCols=features, outputCol="raw_").transform(df)
    scaled = StandardScaler(inputCol="raw_", outputCol="features_", withMean=True, withStd=True).fit(assembled).transform(assembled)
    model = KMeans(k=k, seed=seed, featuresCol="features_", initMode=init).fit(scaled)
    return model.transform(scaled).drop("raw_", "features_")


def kmeans_full(df: DataFrame, names: list[str], k: int, seed: int = 1) -> DataFrame:
    return reduce_and_cluster(df, names, k, seed)


def kmeans_random(df: DataFrame, names: list[str], x: int, k: int, seed: int = 1) -> DataFrame:
    return reduce_and_cluster(df, sorted(random.Random(seed).sample(names, x)), k, seed)
