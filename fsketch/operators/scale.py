"""Standardisation with population moments, and random projection."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import py_normal
from ..functions.vectors import dot, feature_names


@dataclass(frozen=True)
class Scaler:
    cols: tuple[str, ...]
    mean: np.ndarray
    std: np.ndarray
    n: int
    dropped: int = 0

    @property
    def divisor(self) -> np.ndarray:
        return np.where(self.std > 0, self.std, 1.0)

    def transform(self, df: DataFrame) -> DataFrame:
        """Adds z0, z1, ... beside the original columns."""
        return df.withColumns({f"z{i}": (F.col(c) - float(m)) / float(s) for i, (c, m, s) in enumerate(zip(self.cols, self.mean, self.divisor, strict=True))})

    def forward(self, points: np.ndarray) -> np.ndarray:
        return (np.asarray(points, float) - self.mean) / self.divisor

    def inverse(self, points: np.ndarray) -> np.ndarray:
        return np.asarray(points, float) * self.divisor + self.mean


def valid(df: DataFrame, cols: list[str]) -> DataFrame:
    """Rows whose features are all finite numbers."""
    for c in cols:
        df = df.where(F.col(c).isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf")))
    return df


def fit(df: DataFrame, cols: list[str] | None = None, on_invalid: str = "drop") -> Scaler:
    """One pass. A column without variance is divided by 1. Rows with null, NaN or infinite features are dropped and
    counted, or refused with ``on_invalid='error'``."""
    cols = cols or feature_names(df)
    fine = F.lit(True)
    for c in cols:
        fine = fine & F.col(c).isNotNull() & ~F.isnan(F.col(c)) & (F.abs(F.col(c)) < float("inf"))
    pick = lambda c: F.when(fine, F.col(c).cast("double"))
    row = df.agg(F.count(F.lit(1)), F.count_if(fine), *[F.avg(pick(c)) for c in cols], *[F.stddev_pop(pick(c)) for c in cols]).first()
    if row[0] != row[1] and on_invalid == "error":
        raise ValueError(f"{row[0] - row[1]} of {row[0]} rows have features that are not finite numbers")
    d = len(cols)
    mean, std = (np.array([v if v is not None else 0.0 for v in part]) for part in (row[2 : 2 + d], row[2 + d :]))
    return Scaler(tuple(cols), mean, std, row[1], row[0] - row[1])


def prepare(df: DataFrame, cols: list[str] | None = None, on_invalid: str = "drop") -> tuple[DataFrame, Scaler]:
    """Valid rows with standardised columns, and the scaler."""
    scaler = fit(df, cols, on_invalid)
    return scaler.transform(valid(df, list(scaler.cols)) if scaler.dropped else df), scaler


def project(df: DataFrame, d_out: int, seed: int = 42, prefix: str = "z") -> DataFrame:
    """Gaussian random projection of the standardised columns to p0, p1, ... (entries of variance 1 / d_out)."""
    cols = feature_names(df, prefix)
    rows = [[py_normal("proj", seed, i, c) / d_out**0.5 for c in range(len(cols))] for i in range(d_out)]
    return df.withColumns({f"p{i}": dot(cols, r) for i, r in enumerate(rows)})
