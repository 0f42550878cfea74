"""Documented classical stand-ins for the methods compared with; their originals' internals are not public here."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import normal, py_normal, py_uniform
from ..functions.vectors import feature_names, nearest, squared_distance
from ..session import ship
from . import lloyd
from . import seed as seeds
from .solve import Solution


def kmeans(df: DataFrame, k: int, restarts: int = 3, iters: int = 20, seed: int = 42, prefix: str = "z", init: str | None = None, tol: float = 1e-4) -> tuple[np.ndarray, float]:
    """Lloyd from several starts (by hash the first, then k-means++, or all by ``init``); the best WCSS in standardised space."""
    best = None
    for r in range(restarts):
        c, _ = lloyd.run(df, seeds.initial(df, k, init or ("plusplus" if r else "hash"), seed + r, prefix), iters, tol, prefix)
        value = lloyd.step(df, c, prefix)[1]
        if best is None or value < best[1]:
            best = (c, value)
    return best


def nonnegative_least_squares(a: np.ndarray, b: np.ndarray, rounds: int = 500) -> np.ndarray:
    """Projected gradient with momentum."""
    gram, rhs = a.T @ a, a.T @ b
    rate = 1.0 / max(np.linalg.eigvalsh(gram)[-1], 1e-12)
    x = y = np.zeros(a.shape[1])
    t = 1.0
    for _ in range(rounds):
        new = np.maximum(y - rate * (gram @ y - rhs), 0)
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y, x, t = new + (t - 1) / t2 * (new - x), new, t2
    return x


def _fit_once(z: np.ndarray, w: np.ndarray, k: int, low: np.ndarray, high: np.ndarray, weights: str, tag: int, rounds: int = 150) -> tuple[np.ndarray, np.ndarray, float]:
    atoms = lambda c: np.exp(1j * c @ w.T)
    stack = lambda v: np.concatenate([v.real, v.imag])

    def weigh(c: np.ndarray) -> np.ndarray:
        if weights == "uniform":
            return np.full(len(c), 1 / k)
        return nonnegative_least_squares(np.stack([stack(a) for a in atoms(c)], axis=1), stack(z))

    def loss_and_slope(c, a):
        f = atoms(c)
        r = (a[:, None] * f).sum(axis=0) - z
        return float((np.abs(r) ** 2).sum()), 2 * a[:, None] * ((np.conj(r)[None, :] * 1j * f).real @ w)

    def descend(c, a, n):
        rate = 0.05 * np.mean(high - low)
        value, slope = loss_and_slope(c, a)
        for _ in range(n):
            trial = np.clip(c - rate * slope / (np.linalg.norm(slope) + 1e-12), low, high)
            v, s = loss_and_slope(trial, a)
            if v < value:
                c, value, slope, rate = trial, v, s, rate * 1.2
            else:
                rate /= 2
                if rate < 1e-7:
                    break
        return c, value

    def best_atom(residual, t):
        starts = np.array([[low[i] + py_uniform("ckm", tag, t, s, i) * (high[i] - low[i]) for i in range(len(low))] for s in range(64)])
        c = starts[np.argmax((np.conj(residual)[None, :] * atoms(starts)).sum(axis=1).real)]
        rate = 0.1 * np.mean(high - low)
        for _ in range(60):
            slope = (np.conj(residual) * 1j * np.exp(1j * w @ c)).real @ w
            trial = np.clip(c + rate * slope / (np.linalg.norm(slope) + 1e-12), low, high)
            gain = (np.conj(residual) * (np.exp(1j * w @ trial) - np.exp(1j * w @ c))).sum().real
            c, rate = (trial, rate * 1.1) if gain > 0 else (c, rate / 2)
        return c

    c = np.zeros((0, len(low)))
    for t in range(2 * k):  # with replacement: half of the rounds add one too many and drop the lightest
        residual = z - (weigh(c)[:, None] * atoms(c)).sum(axis=0) if len(c) else z
        c = np.vstack([c, best_atom(residual, t)])
        if len(c) > k:
            a = nonnegative_least_squares(np.stack([stack(v) for v in atoms(c)], axis=1), stack(z))
            c = c[np.sort(np.argsort(-a, kind="stable")[:k])]
        c, _ = descend(c, weigh(c), 30)
    c, value = descend(c, weigh(c), rounds)
    a = weigh(c)
    return c, a, loss_and_slope(c, a)[0]


def compressive(spark: SparkSession, z: np.ndarray, w: np.ndarray, k: int, low: np.ndarray, high: np.ndarray, restarts: int = 4, weights: str = "uniform", seed: int = 42) -> tuple[np.ndarray, np.ndarray, float]:
    """Continuous centroids whose features match the data sketch: greedy pursuit with replacement, then joint descent.
    Restarts run in parallel; nothing here depends on the number of rows."""
    ship(spark)

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            for r in pdf.id:
                c, a, value = _fit_once(z, w, k, low, high, weights, seed + int(r))
                yield pd.DataFrame({"value": [value], "c": [c.ravel().tolist()], "a": [a.tolist()]})

    tries = spark.range(0, restarts, 1, restarts).mapInPandas(work, "value double, c array<double>, a array<double>")
    best = tries.orderBy("value").first()
    return np.array(best.c).reshape(k, -1), np.array(best.a), best.value


def pushes(k: int, d: int, delta: float, t: int, seed: int = 42) -> np.ndarray:
    """What moves the means in step t: random directions, at most delta / 2 long."""
    push = np.array([[py_normal("push", seed, t, g, i) for i in range(d)] for g in range(k)])
    return push * delta / 2 * np.array([[py_uniform("len", seed, t, g)] for g in range(k)]) / np.linalg.norm(push, axis=1, keepdims=True)


def noisy_kmeans(df: DataFrame, k: int, delta: float = 0.1, iters: int = 15, seed: int = 42, prefix: str = "z") -> tuple[np.ndarray, list[float]]:
    """k-means under bounded noise: any centroid within ``delta`` of the nearest squared distance may be taken (the one a hash
    prefers), and means are moved by at most ``delta / 2``."""
    cols, c, history = feature_names(df, prefix), seeds.initial(df, k, "hash", seed, prefix), []
    for t in range(iters):
        _, least = nearest(cols, c)
        from ..functions.hashing import uniform

        ranked = F.array(*[F.when(squared_distance(cols, v) <= F.col("d2") + delta, uniform("nm", seed, t, g, F.col("row_key"))).otherwise(F.lit(-1.0)) for g, v in enumerate(c)])
        labelled = df.withColumn("d2", least).withColumn("g", (F.array_position(ranked, F.array_max(ranked)) - 1).cast("int"))
        means, _, spread = lloyd.cluster_means(labelled, k, prefix)
        history.append(float(spread.sum()))
        c = np.where(np.isnan(means), c, means + pushes(k, len(cols), delta, t, seed))
    return c, history


def overlap_kmeans(df: DataFrame, k: int, n_shots: int = 1024, iters: int = 15, seed: int = 42, prefix: str = "z") -> tuple[np.ndarray, list[float]]:
    """k-means whose squared distances come from overlap tests: with Z = |x|^2 + |c|^2, d^2 / (2 Z) is the chance of a coin and
    its estimate over the shots gets binomial noise (moment-matched per row and centroid)."""
    cols, c, history = feature_names(df, prefix), seeds.initial(df, k, "hash", seed, prefix), []
    for t in range(iters):
        guesses = []
        for g, v in enumerate(c):
            z = sum((F.col(x) * F.col(x) for x in cols), F.lit(float((v**2).sum()) + 1e-12))
            chance = F.least(F.lit(1.0), F.greatest(F.lit(0.0), squared_distance(cols, v) / (2 * z)))
            guesses.append(2 * z * (chance + normal("ov", seed, t, g, F.col("row_key")) * F.sqrt(chance * (1 - chance) / n_shots)))
        all_ = F.array(*guesses)
        labelled = df.withColumn("g", (F.array_position(all_, F.array_min(all_)) - 1).cast("int"))
        labelled = labelled.withColumn("d2", F.element_at(F.array(*[squared_distance(cols, v) for v in c]), F.col("g") + 1))
        means, _, spread = lloyd.cluster_means(labelled, k, prefix)
        history.append(float(spread.sum()))
        c = np.where(np.isnan(means), c, means)
    return c, history


def assign_qubo(df: DataFrame, k: int, iters: int = 10, budget: int = 50_000_000, seed: int = 42, prefix: str = "z") -> tuple[np.ndarray | None, Solution]:
    """Hybrid: per row a one-hot problem of k bits, solved over its 2^k states, then means. Beyond the budget of states in all: no solution."""
    n = df.count()
    states = n * (1 << k) * iters
    if states > budget:
        return None, Solution(None, None, states, "no_solution")
    cols, c = feature_names(df, prefix), seeds.initial(df, k, "hash", seed, prefix)
    value = 0.0
    for _ in range(iters):
        # all states of a row are tried within the row: nothing moves
        d2 = F.array(*[squared_distance(cols, v) for v in c])
        rows = df.withColumn("_d", d2).withColumn("_pen", F.aggregate("_d", F.lit(1.0), lambda a, x: a + x))

        def energy(state):
            bit = lambda g: F.shiftright(state, g).bitwiseAND(F.lit(1))
            return sum((bit(g) * F.get("_d", g) for g in range(k)), F.lit(0.0)) + F.col("_pen") * F.pow(F.lit(1) - sum((bit(g) for g in range(k)), F.lit(0)), F.lit(2))

        tried = F.transform(F.sequence(F.lit(0), F.lit((1 << k) - 1)), lambda s: F.struct(energy(s).alias("e"), s.alias("state")))
        labelled = rows.withColumn("g", F.log2(F.array_min(tried)["state"].cast("double")).cast("int"))
        labelled = labelled.withColumn("d2", F.element_at("_d", F.col("g") + 1))
        means, _, spread = lloyd.cluster_means(labelled, k, prefix)
        new, value = np.where(np.isnan(means), c, means), float(spread.sum())
        if np.linalg.norm(new - c) <= 1e-6:
            break
        c = new
    return c, Solution([], value, states)
