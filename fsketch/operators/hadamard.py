"""Phase sampling: a sketch component from b sampled phases through simulated Hadamard tests.

The b phases are padded with zero phases to M = 2^n slots; the test's expectation is the mean over M slots, its real and
imaginary part show up as coin biases in two bases, and an affine rescaling takes the padding out again.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..functions.vectors import feature_names, total
from . import freq, sample, sketch


def register(b: int) -> tuple[int, int]:
    """(index qubits, slots): at least one qubit."""
    if b < 1:
        raise ValueError("b must be positive")
    n = max(1, math.ceil(math.log2(b)))
    return n, 1 << n


def expectation(sampled: DataFrame, frequencies: DataFrame, prefix: str = "z") -> DataFrame:
    """(j, b, slots, re, im): the padded mean per frequency. ``frequencies`` has m rows (j, w) and is broadcast."""
    cols = feature_names(sampled, prefix)
    joined = sampled.join(F.broadcast(frequencies), "j")
    t = total([F.col(c) * F.get("w", i) for i, c in enumerate(cols)])
    out = joined.groupBy("j").agg(F.count(F.lit(1)).alias("b"), F.sum(F.cos(t)).alias("c"), F.sum(F.sin(t)).alias("s"))
    slots = F.pow(F.lit(2.0), F.greatest(F.lit(1.0), F.ceil(F.log2(F.col("b").cast("double"))).cast("double")))
    out = out.withColumn("slots", slots)
    return out.select("j", "b", "slots", ((F.col("c") + F.col("slots") - F.col("b")) / F.col("slots")).alias("re"), (F.col("s") / F.col("slots")).alias("im"))


def shots(mu: DataFrame, n_shots: int | None, seed: int = 42, mode: str = "hash", contrast: float = 1.0, flip: float = 0.0, p2: float = 0.0) -> DataFrame:
    """mu with re and im replaced by averages of ``n_shots`` coins of +1 and -1 each; None means infinitely many.

    ``contrast`` shrinks the expectation (depolarisation of the ancilla), ``p2`` does so once for each of the index register's
    slots, ``flip`` is the chance that a coin is read wrong.
    """
    gates = F.pow(F.lit(1.0 - p2), F.col("slots")) if p2 else F.lit(1.0)
    bias = lambda c: contrast * (1 - 2 * flip) * gates * F.col(c)
    if n_shots is None:
        return mu.withColumns({"re": bias("re"), "im": bias("im")})
    chance = lambda c: F.greatest(F.lit(0.0), F.least(F.lit(1.0), (1 + bias(c)) / 2))
    if mode == "normal":  # moment-matched, O(m)
        from ..functions.hashing import normal

        draw = lambda c: 2 * F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.round((chance(c) * n_shots + normal("n", seed, c, F.col("j")) * F.sqrt(n_shots * chance(c) * (1 - chance(c))))) / n_shots)) - 1
        return mu.withColumns({"re": draw("re"), "im": draw("im")})
    coins = mu.withColumn("shot", F.explode(F.sequence(F.lit(0), F.lit(n_shots - 1))))
    up = lambda c: (2 * F.count_if(uniform("h", seed, c, F.col("j"), F.col("shot")) < chance(c)) / F.lit(float(n_shots)) - 1).alias(c)
    return coins.groupBy("j", "b", "slots").agg(up("re"), up("im"))


def rescale(mu: DataFrame) -> DataFrame:
    """(j, re, im, n): the padding's share taken out; it is a real constant."""
    stretch = F.col("slots") / F.col("b")
    return mu.select("j", (stretch * F.col("re") - (F.col("slots") - F.col("b")) / F.col("b")).alias("re"), (stretch * F.col("im")).alias("im"), F.col("b").alias("n"))


def estimate_sketch(df: DataFrame, m: int, b: int = 256, n_shots: int | None = 1024, sampling: str = "per_frequency", sigma: float = 1.0, seed: int = 42, mode: str = "hash", contrast: float = 1.0, flip: float = 0.0, p2: float = 0.0, prefix: str = "z", n: int | None = None) -> DataFrame:
    """(j, re, im, n): the data sketch by phase sampling; phases are computed for sampled rows only. ``n`` saves counting the rows."""
    spark, d = df.sparkSession, len(feature_names(df, prefix))
    if sampling == "exact":
        return sketch.exact(df, freq.matrix(m, d, sigma, seed), prefix=prefix)
    frequencies = freq.draw(spark, m, d, sigma, seed)
    if sampling == "shared":
        rows = sample.shared(df, b, seed, n).crossJoin(F.broadcast(frequencies.select("j")))
    else:
        rows = sample.per_frequency(df, b, m, seed, n=n)
    return rescale(shots(expectation(rows, frequencies, prefix), n_shots, seed, mode, contrast, flip, p2))


def _cluster_sums(assigned: DataFrame, w: np.ndarray, b: int, seed: int, sampling: str, sizes: dict, prefix: str) -> list:
    """Rows (g, j, s_re, s_im, n) over the sampled rows of each cluster; taken again without thresholds if these kept too few."""
    for given in (sizes, dict.fromkeys(sizes, 0)):  # a size of 0 puts the threshold at one
        if sampling == "per_frequency":
            frequencies = freq.to_frame(assigned.sparkSession, w)
            cols = feature_names(assigned, prefix)
            rows = sample.per_group_frequency(assigned, b, len(w), seed, sizes=sizes, sure=given is sizes)
            t = total([F.col(c) * F.get("w", i) for i, c in enumerate(cols)])
            got = rows.join(F.broadcast(frequencies), "j").groupBy("g", "j").agg(F.sum(F.cos(t)).alias("s_re"), F.sum(F.sin(t)).alias("s_im"), F.count(F.lit(1)).alias("n")).collect()  # m rows
        elif sampling == "shared":
            got = sketch.per_cluster(sample.per_group(assigned, b, seed, sizes=given, sure=True), w, prefix=prefix).collect()
        else:
            raise ValueError(f"unknown sampling {sampling}")
        if len(got) == len(sizes) * len(w) and all(r.n >= min(b, sizes[r.g]) for r in got):
            return got
    return got


def estimate_clusters(assigned: DataFrame, w: np.ndarray, b: int | None = 256, n_shots: int | None = 1024, seed: int = 42, contrast: float = 1.0, flip: float = 0.0, p2: float = 0.0, prefix: str = "z", sampling: str = "shared") -> tuple[np.ndarray, np.ndarray]:
    """(k x m sketches, k counts) on the driver: per cluster from min(b, size) rows, or from all with b None.

    ``sampling`` says whether a cluster's rows are drawn once for all frequencies (``shared``) or anew for each
    (``per_frequency``, which keeps the errors of the components apart). Two passes: the sizes, then the sampled rows.
    k is one more than the largest label. Coins are simulated as binomial draws: k m pairs of numbers.
    """
    if b is None:
        rows = sketch.per_cluster(assigned, w, prefix=prefix).collect()
        sizes = {r.g: r.n for r in rows}
    else:
        sizes = sample.sizes_of(assigned)
        rows = _cluster_sums(assigned, w, b, seed, sampling, sizes, prefix)
    k = 1 + max(sizes, default=-1)
    z, size, rng = np.zeros((k, len(w)), complex), np.zeros(k, np.int64), np.random.Generator(np.random.PCG64(seed))
    for g, n in sizes.items():
        size[g] = n
    for r in sorted(rows, key=lambda r: (r.g, r.j)):
        value = complex(r.s_re, r.s_im)
        if b is None or (n_shots is None and contrast == 1.0 and flip == 0.0 and p2 == 0.0):
            z[r.g, r.j] = value / r.n
            continue
        _, slots = register(r.n)
        mu = (value + slots - r.n) / slots * contrast * (1 - p2) ** slots * (1 - 2 * flip)
        if n_shots is not None:
            coin = lambda v: 2 * rng.binomial(n_shots, min(1.0, max(0.0, (1 + v) / 2))) / n_shots - 1
            mu = complex(coin(mu.real), coin(mu.imag))
        z[r.g, r.j] = slots / r.n * mu - (slots - r.n) / r.n
    return z, size


def statevector(phases: np.ndarray, imaginary: bool = False) -> float:
    """The test as a circuit on n + 1 qubits: P(0) - P(1) of the ancilla, for the real or the imaginary part."""
    n, slots = register(len(phases))
    theta = np.zeros(slots)
    theta[: len(phases)] = phases
    index = np.full(slots, slots**-0.5, complex)  # uniform superposition over the index register
    state = np.stack([index, index]) / np.sqrt(2)  # ancilla in (|0> + |1>) / sqrt 2
    if imaginary:
        state[1] *= -1j
    state[1] *= np.exp(1j * theta)  # phases controlled by the ancilla
    zero, one = (state[0] + state[1]) / np.sqrt(2), (state[0] - state[1]) / np.sqrt(2)
    return float((np.abs(zero) ** 2).sum() - (np.abs(one) ** 2).sum())


def to_frame(spark: SparkSession, z: np.ndarray) -> DataFrame:
    return sketch.to_frame(spark, z)
