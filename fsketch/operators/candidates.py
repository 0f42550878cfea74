"""Candidate centroids around seeds or incumbents. Sets may differ in size; index 0 is the incumbent if it is kept."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..functions.hashing import py_normal

Sets = list[np.ndarray]


def around(centroids: np.ndarray, d_per_group: int = 4, jitter: float = 0.2, decay: float = 0.7, step: int = 0, seed: int = 42, keep: bool = True) -> Sets:
    """Gaussian jitter of scale ``jitter * decay**step`` in standardised units; ``keep`` makes the centroid itself candidate 0."""
    if d_per_group < 1:
        raise ValueError("each group needs a candidate")
    scale = jitter * decay**step
    out = []
    for g, c in enumerate(np.asarray(centroids, float)):
        rows = [c + scale * np.array([py_normal("c", seed, step, g, r, i) for i in range(len(c))]) for r in range(d_per_group)]
        out.append(np.array([c, *rows[1:]] if keep else rows))
    return out


def from_frame(df: DataFrame) -> Sets:
    """User-given sets: columns g, r, c (array of coordinates)."""
    rows = sorted(df.select("g", "r", "c").collect())
    groups = sorted({r.g for r in rows})
    return [np.array([r.c for r in rows if r.g == g], float) for g in groups]


def to_frame(spark: SparkSession, sets: Sets, kept: bool = True) -> DataFrame:
    rows = [(g, r, [float(v) for v in c], kept and r == 0) for g, s in enumerate(sets) for r, c in enumerate(s)]
    return spark.createDataFrame(rows, "g int, r int, c array<double>, is_incumbent boolean")


def chosen(sets: Sets, selection: list[int]) -> np.ndarray:
    return np.array([s[r] for s, r in zip(sets, selection, strict=True)])
