"""Resource counts of the circuits."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .hadamard import register


def peak(d: int, b: int) -> int:
    """Qubits of the larger of the two circuits: D for a group's selection, index register and ancilla for a phase test."""
    return max(d, register(b)[0] + 1)


def joint(k: int, d: int) -> int:
    """Qubits if all groups were selected at once."""
    return k * d


def gates(p: int, d: int, nonzero: int | None = None, per_edge: int = 2) -> dict[str, int]:
    """Two-qubit gates of one group's circuit: mixers on the ring's edges and cost phases on non-zero couplings."""
    nonzero = d * (d - 1) // 2 if nonzero is None else nonzero
    edges = d if d > 2 else d - 1
    return {"mixer": per_edge * p * edges, "cost": per_edge * p * nonzero}


def assignment_qubits(k: int) -> int:
    """One bit per cluster for a point's one-hot assignment problem."""
    return k


def noisy_means_qubits(n: int) -> int:
    return math.ceil(math.log2(n)) + 2


def overlap_qubits() -> int:
    return 5


def grid(spark: SparkSession, ks: list[int], ds: list[int], bs: list[int] | DataFrame, ps: list[int]) -> DataFrame:
    """(k, d, b, p, peak_qubits, joint_qubits, mixer_gates, cost_gates) for all combinations, by expressions. ``bs`` may be a table (b)."""
    rows = spark.createDataFrame([(b,) for b in bs], "b int") if isinstance(bs, list) else bs
    for name, values in (("k", ks), ("d", ds), ("p", ps)):
        rows = rows.withColumn(name, F.explode(F.array(*[F.lit(v) for v in values])))
    index = F.length(F.bin(F.col("b").cast("long") - 1))  # exact where a logarithm may not be
    edges = F.when(F.col("d") > 2, F.col("d")).otherwise(F.col("d") - 1)
    return rows.select(
        "k", "d", "b", "p", F.greatest(F.col("d"), index + 1).alias("peak_qubits"), (F.col("k") * F.col("d")).alias("joint_qubits"),
        (2 * F.col("p") * edges).alias("mixer_gates"), (2 * F.col("p") * F.expr("d * (d - 1) div 2")).cast("int").alias("cost_gates"),
    )
