"""Gaussian frequency vectors."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import normal, py_normal


def default_m(k: int, d: int) -> int:
    return 4 * k * d


def matrix(m: int, d: int, sigma: float = 1.0, seed: int = 42) -> np.ndarray:
    """m x d on the driver: its size does not depend on the data."""
    return np.array([[sigma * py_normal("w", seed, j, c) for c in range(d)] for j in range(m)]).reshape(m, d)


def draw(spark: SparkSession, m: int, d: int, sigma: float = 1.0, seed: int = 42) -> DataFrame:
    """The same frequencies as a table (j, w)."""
    return numbered(spark.range(m), "id", d, sigma, seed).withColumn("j", F.col("j").cast("int"))


def numbered(rows: DataFrame, number: str, d: int, sigma: float = 1.0, seed: int = 42) -> DataFrame:
    """A frequency for each row, (j, w): that of the row's number."""
    w = F.array(*[sigma * normal("w", seed, F.col(number), c) for c in range(d)])
    return rows.select(F.col(number).alias("j"), w.alias("w"))


def to_frame(spark: SparkSession, w: np.ndarray) -> DataFrame:
    """Given frequencies as a table (j, w)."""
    return spark.createDataFrame([(j, [float(x) for x in row]) for j, row in enumerate(w)], "j int, w array<double>")
