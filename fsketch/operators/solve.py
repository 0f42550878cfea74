"""Exact solvers: per group, over all products of groups, over all bits; and annealing.

Enumerations run over ``range(number of states)`` in Spark, a state being its index in mixed radix. Beyond a budget of
states the answer is no solution, a result of its own.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.vectors import feature_names, squared_distance
from ..session import ship
from .candidates import Sets
from .qubo import Model

BUDGET = 100_000_000


@dataclass
class Solution:
    selection: list[int] | None
    value: float | None
    states: int
    status: str = "solved"


def grouped_exact(costs: list[np.ndarray]) -> Solution:
    """The least cost in each group, the smallest index on ties."""
    pick = [int(np.argmin(c)) for c in costs]
    return Solution(pick, float(sum(c[r] for c, r in zip(costs, pick, strict=True))), sum(map(len, costs)))


def digits(index: np.ndarray, sizes: list[int]) -> np.ndarray:
    """Mixed-radix digits of state numbers, the first group varying slowest."""
    out = np.empty((len(index), len(sizes)), np.int64)
    for g in range(len(sizes) - 1, -1, -1):
        out[:, g] = index % sizes[g]
        index = index // sizes[g]
    return out


def _least_state(spark: SparkSession, n: int, score) -> tuple[int, float]:
    """The state number of least score over range(n); tasks send one row each."""
    ship(spark)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = None
        for b in batches:
            ids = b.column("id").to_numpy()
            for at in range(0, len(ids), 65536):
                part = ids[at : at + 65536]
                v = score(part)
                i = int(np.argmin(v))
                if best is None or (v[i], part[i]) < best:
                    best = (float(v[i]), int(part[i]))
        if best:
            yield pa.RecordBatch.from_arrays([pa.array([best[1]]), pa.array([best[0]])], names=["state", "value"])

    row = spark.range(n).mapInArrow(work, "state long, value double").agg(F.min(F.struct("value", "state"))).first()[0]
    return row.state, row.value


def coupled(spark: SparkSession, model: Model, budget: int = BUDGET) -> Solution:
    """Least joint energy over all products of candidates."""
    sizes = model.sizes
    n = prod(sizes)
    if n > budget:
        return Solution(None, None, n, "no_solution")
    first = np.cumsum([0, *sizes[:-1]])
    linear, quadratic, offset = model.linear, model.quadratic, model.offset

    def score(ids: np.ndarray) -> np.ndarray:
        at = digits(ids, sizes) + first
        return offset + linear[at].sum(axis=1) + quadratic[at[:, :, None], at[:, None, :]].sum(axis=(1, 2))

    state, value = _least_state(spark, n, score)
    return Solution(digits(np.array([state]), sizes)[0].tolist(), value, n)


def bits(spark: SparkSession, model: Model, penalty: float, most: int = 20) -> Solution:
    """Least total energy over all bit strings, feasible or not; the selection is None if the winner is not one-hot."""
    n = len(model.linear)
    if n > most:
        return Solution(None, None, 1 << n, "no_solution")

    def score(ids: np.ndarray) -> np.ndarray:
        return model.energy((ids[:, None] >> np.arange(n)) & 1, penalty)

    state, value = _least_state(spark, 1 << n, score)
    y = (state >> np.arange(n)) & 1
    ok = not model.one_hot_violation(y)[0]
    return Solution([int(np.flatnonzero(y[model.group == g])[0]) for g in range(len(model.sizes))] if ok else None, value, 1 << n, "solved" if ok else "infeasible")


def exhaustive(points: DataFrame, sets: Sets, by: str = "wcss", model: Model | None = None, budget: int = 20_000, prefix: str = "z") -> Solution:
    """All products of candidates scored by the points' squared distances (one pass, all states at once) or by the sketch."""
    if by == "sketch":
        return coupled(points.sparkSession, model, budget)
    sizes = [len(s) for s in sets]
    n = prod(sizes)
    if n > budget:
        return Solution(None, None, n, "no_solution")
    cols = feature_names(points, prefix)
    flat = np.concatenate(sets)
    first = np.cumsum([0, *sizes[:-1]])
    at = digits(np.arange(n), sizes) + first

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(n)
        for b in batches:
            x = np.stack([b.column(c).to_numpy(zero_copy_only=False) for c in cols], axis=1)
            for i in range(0, len(x), 256):
                d2 = ((x[i : i + 256, None, :] - flat[None, :, :]) ** 2).sum(axis=2)
                for s in range(0, n, 4096):
                    total[s : s + 4096] += d2[:, at[s : s + 4096]].min(axis=2).sum(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()])], names=["sums"])

    total = np.zeros(n)
    for part in points.select(*cols).mapInArrow(work, "sums binary").toLocalIterator():
        total += np.frombuffer(part[0])
    best = int(np.argmin(total))
    return Solution(digits(np.array([best]), sizes)[0].tolist(), float(total[best]), n)


def wcss_of_states(points: DataFrame, sets: Sets, states: np.ndarray, prefix: str = "z") -> DataFrame:
    """(state, wcss) by expressions only, for a few states."""
    cols = feature_names(points, prefix)
    aggs = [F.sum(F.least(*[squared_distance(cols, s[r]) for s, r in zip(sets, st, strict=True)]) if len(sets) > 1 else squared_distance(cols, sets[0][st[0]])).alias(f"v{i}") for i, st in enumerate(states)]
    one = points.agg(*aggs)
    return one.select(F.explode(F.array(*[F.struct(F.lit(i).alias("state"), F.col(f"v{i}").alias("wcss")) for i in range(len(states))])).alias("s")).select("s.*")


def _walk(linear: np.ndarray, sym: np.ndarray, constant: float, sweeps: int, seed: tuple[int, int]) -> tuple[float, np.ndarray]:
    """One restart: single-bit Metropolis flips with a falling temperature, from a random state. The best state after any sweep counts."""
    n, rng = len(linear), np.random.Generator(np.random.PCG64(seed))
    top = np.abs(linear).max() + np.abs(sym).sum(axis=1).max()
    y = rng.integers(0, 2, n)
    value = constant + linear @ y + y @ sym @ y
    best, kept = np.inf, y
    for s in range(sweeps):
        heat = top * (1 - s / sweeps) ** 3 + 1e-9 * top + 1e-300
        for i in rng.permutation(n):
            step = (1 - 2 * y[i]) * (linear[i] + 2 * (sym[i] @ y - sym[i, i] * y[i])) + sym[i, i] * (1 - 2 * y[i])
            if step <= 0 or rng.random() < np.exp(-step / heat):
                y[i] ^= 1
                value += step
        if value < best - 1e-12:
            best, kept = value, y.copy()
    return float(best), kept


def anneal(model: Model, penalty: float, sweeps: int = 400, restarts: int = 8, seed: int = 42, spark: SparkSession | None = None) -> Solution:
    """The best of ``restarts`` annealing walks over the bits, the first of equals. With a session each walk is a row of a
    task; the result is the same."""
    linear, quadratic, constant = model.matrix_form(penalty)
    sym, n = (quadratic + quadratic.T) / 2, len(linear)
    if spark is None:
        found = [(value, r, y) for r in range(restarts) for value, y in [_walk(linear, sym, constant, sweeps, (seed, r))]]
    else:
        ship(spark)

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                ids = b.column("id").to_pylist()
                got = [_walk(linear, sym, constant, sweeps, (seed, r)) for r in ids]
                yield pa.RecordBatch.from_arrays([pa.array([v for v, _ in got], pa.float64()), pa.array(ids, pa.int64()), pa.array([y.tolist() for _, y in got], pa.list_(pa.int64()))], names=["value", "r", "y"])

        rows = spark.range(0, restarts, 1, restarts).mapInArrow(work, "value double, r long, y array<long>").collect()  # a row per restart
        found = [(row.value, row.r, np.array(row.y)) for row in rows]
    best, _, y = min(found, key=lambda e: (round(e[0], 12), e[1]))
    ok = not model.one_hot_violation(y)[0]
    return Solution([int(np.flatnonzero(y[model.group == g])[0]) for g in range(len(model.sizes))] if ok else None, best, restarts * sweeps * n, "solved" if ok else "infeasible")
