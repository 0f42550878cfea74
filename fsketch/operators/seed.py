"""Seeds by k-means on standardised points, on all of them or on a hash sample."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from ..functions.hashing import py_uniform
from ..functions.vectors import feature_names
from . import lloyd, sample

POOL = 4096


def initial(df: DataFrame, k: int, init: str = "hash", seed: int = 42, prefix: str = "z", n: int | None = None) -> np.ndarray:
    """First k distinct rows by hash, k-means++ on a hash sample of ``POOL`` rows, or MLlib's parallel initialisation."""
    cols = feature_names(df, prefix)
    if init == "mllib":
        from pyspark.ml.clustering import KMeans
        from pyspark.ml.feature import VectorAssembler

        rows = VectorAssembler(inputCols=cols, outputCol="features").transform(df).select("features")
        return np.array(KMeans(k=k, maxIter=1, seed=seed, initMode="k-means||").fit(rows).clusterCenters())
    pool = np.array([[r[c] for c in cols] for r in sample.shared(df, POOL if init == "plusplus" else 8 * k, seed, n).collect()], float).reshape(-1, len(cols))
    if not len(pool):
        raise ValueError("no rows to seed from")
    _, first = np.unique(pool, axis=0, return_index=True)
    distinct = pool[np.sort(first)]
    if init == "hash" or len(distinct) <= k:
        return np.array([distinct[i % len(distinct)] for i in range(k)])
    chosen = [distinct[0]]
    for i in range(1, k):
        d2 = np.min([((distinct - c) ** 2).sum(axis=1) for c in chosen], axis=0)
        chosen.append(distinct[int(np.searchsorted(np.cumsum(d2), py_uniform("pp", seed, i) * d2.sum()))])
    return np.array(chosen)


def kmeans(df: DataFrame, k: int, on: str = "full", init: str = "hash", iters: int = 20, seed: int = 42, sample_rows: int = 10_000, prefix: str = "z", n: int | None = None) -> np.ndarray:
    """Centroids in standardised space, ordered by coordinates."""
    first = initial(df, k, init, seed, prefix, n)
    if on == "sample":
        rows = sample.shared(df, sample_rows, seed, n).persist()  # ``sample_rows`` rows, read in every step
        centroids, _ = lloyd.run(rows, first, iters, prefix=prefix)
        rows.unpersist()
    else:
        centroids, _ = lloyd.run(df, first, iters, prefix=prefix)
    return centroids[np.lexsort(centroids.T[::-1])]
