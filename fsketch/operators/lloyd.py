"""Assignment and Lloyd steps: map-only labels, partial sums per cluster, centroids as literals."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import feature_names, nearest


def assign(df: DataFrame, centroids: np.ndarray, prefix: str = "z") -> DataFrame:
    """Adds g (nearest centroid, the smallest index on ties) and d2."""
    g, d2 = nearest(feature_names(df, prefix), centroids)
    return df.withColumn("g", g).withColumn("d2", d2)


def cluster_means(assigned: DataFrame, k: int, prefix: str = "z") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(means, counts, sums of d2) on the driver: k rows. Means of empty clusters are NaN."""
    cols = feature_names(assigned, prefix)
    rows = assigned.groupBy("g").agg(F.count(F.lit(1)).alias("n"), F.sum("d2").alias("s"), *[F.avg(c).alias(c) for c in cols]).collect()
    means, counts, spread = np.full((k, len(cols)), np.nan), np.zeros(k, np.int64), np.zeros(k)
    for r in rows:
        means[r.g], counts[r.g], spread[r.g] = [r[c] for c in cols], r.n, r.s
    return means, counts, spread


def step(df: DataFrame, centroids: np.ndarray, prefix: str = "z") -> tuple[np.ndarray, float]:
    """New centroids (empty clusters keep theirs) and the WCSS of the old ones."""
    means, _, spread = cluster_means(assign(df, centroids, prefix), len(centroids), prefix)
    return np.where(np.isnan(means), centroids, means), float(spread.sum())


def run(df: DataFrame, centroids: np.ndarray, max_iter: int = 20, tol: float = 1e-4, prefix: str = "z") -> tuple[np.ndarray, list[float]]:
    """One pass per step; the plan never grows, as centroids come back as literals."""
    history = []
    for _ in range(max_iter):
        new, value = step(df, centroids, prefix)
        history.append(value)
        moved, centroids = float(np.linalg.norm(new - centroids)), new
        if moved <= tol:
            break
    return centroids, history
