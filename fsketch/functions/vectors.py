"""Expressions over the feature columns of a point table; constants become literals, so they stay in generated code."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def feature_names(df: DataFrame, prefix: str = "x") -> list[str]:
    names = [c for c in df.columns if c[: len(prefix)] == prefix and c[len(prefix) :].isdigit()]
    return sorted(names, key=lambda c: int(c[len(prefix) :]))


def total(terms: list[Column]) -> Column:
    """Sum as a balanced tree: hundreds of terms stay shallow."""
    while len(terms) > 1:
        terms = [terms[i] + terms[i + 1] if i + 1 < len(terms) else terms[i] for i in range(0, len(terms), 2)]
    return terms[0]


def dot(cols: list[str], weights) -> Column:
    return total([F.col(c) * float(w) for c, w in zip(cols, weights, strict=True)])


def squared_distance(cols: list[str], centre) -> Column:
    return total([(F.col(c) - float(v)) * (F.col(c) - float(v)) for c, v in zip(cols, centre, strict=True)])


def nearest(cols: list[str], centres: np.ndarray) -> tuple[Column, Column]:
    """(index, squared distance) of the nearest centre, the smallest index on ties."""
    d2 = F.array(*[squared_distance(cols, c) for c in centres])
    return (F.array_position(d2, F.array_min(d2)) - 1).cast("int"), F.array_min(d2)
