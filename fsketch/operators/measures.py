"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time
from contextlib import contextmanager

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import feature_names, squared_distance, total
from . import freq, hadamard, lloyd, sketch
from .scale import Scaler


def wcss(assigned: DataFrame, centroids: np.ndarray, center: str = "centroid", prefix: str = "x") -> float:
    """Sum of squared distances in the columns of ``prefix``, to the returned centroids (given in that space) or to the clusters' means."""
    cols = feature_names(assigned, prefix)
    if center == "mean":
        n = F.count(F.lit(1))
        parts = assigned.groupBy("g").agg((total([F.var_pop(c) for c in cols]) * n).alias("s"))
    else:
        parts = assigned.groupBy("g").agg(F.sum(F.element_at(F.array(*[squared_distance(cols, c) for c in centroids]), F.col("g") + 1)).alias("s"))
    return float(parts.agg(F.sum("s")).first()[0] or 0.0)


def original_wcss(points: DataFrame, centroids: np.ndarray, scaler: Scaler, center: str = "centroid") -> float:
    """Assignment in standardised space, squared errors in original units."""
    return wcss(lloyd.assign(points, centroids), scaler.inverse(centroids), center)


def surrogates(z: np.ndarray, zg: np.ndarray, centroids: np.ndarray, w: np.ndarray) -> dict[str, float]:
    """The joint mismatch of the centroids' mean feature, and the sum over clusters of mismatches with their own sketches."""
    f = sketch.feature_matrix(centroids, w)
    return {"surrogate_global": sketch.mismatch(z, f.mean(axis=0)), "surrogate_grouped": float((np.abs(f - zg) ** 2).sum())}


def kernel_error(points: DataFrame, w: np.ndarray, sigma: float = 1.0, prefix: str = "z") -> DataFrame:
    """(a, b, approx, exact, error) over all pairs of a small table: inner products of features against the Gaussian kernel."""
    cols = feature_names(points, prefix)
    left, right = (points.select(F.col("row_key").alias(k), *[F.col(c).alias(f"{k}_{c}") for c in cols]) for k in ("a", "b"))
    pairs = left.join(right, F.col("a") < F.col("b"))
    diff = [F.col(f"a_{c}") - F.col(f"b_{c}") for c in cols]
    approx = total([F.cos(total([d * float(v) for d, v in zip(diff, row, strict=True)])) for row in w]) / len(w)
    exact = F.exp(-(sigma**2) * total([d * d for d in diff]) / 2)
    return pairs.select("a", "b", approx.alias("approx"), exact.alias("exact")).withColumn("error", F.abs(F.col("approx") - F.col("exact")))


def estimator_error(df: DataFrame, m: int, b: int, s: int | None, reps: int, seed: int = 1, prefix: str = "z") -> dict[str, float]:
    """Bias and mean squared error of phase sampling over repeats, with fixed frequencies (those of seed 42), per component."""
    from . import bounds, sample

    d = len(feature_names(df, prefix))
    w = freq.matrix(m, d)
    z = sketch.vector(sketch.exact(df, w, prefix=prefix), m)
    n = df.count()
    frequencies = freq.draw(df.sparkSession, m, d)
    errors = []
    for r in range(reps):
        rows = sample.per_frequency(df, b, m, seed + r, n=n)
        got = hadamard.rescale(hadamard.shots(hadamard.expectation(rows, frequencies, prefix), s, seed + r, "normal"))
        errors.append(sketch.vector(got, m) - z)
    e = np.array(errors)
    return {"bias": float(np.abs(e.mean(axis=0)).max()), "mse": float((np.abs(e) ** 2).mean()), "bound": float(np.mean([bounds.estimator_mse(n, b, s, v) for v in z]))}


def feasible_rate(counts: np.ndarray) -> float:
    """Share of one-hot strings in counts over all bit strings."""
    ones = np.array([bin(i).count("1") == 1 for i in range(len(counts))])
    return float(counts[ones].sum() / counts.sum())


def drift(ideal: float, noisy: float) -> float:
    return noisy / ideal if ideal else math.nan


def delta(costs: list[np.ndarray], selection: list[int]) -> list[float]:
    """How far each group's pick is above its optimum."""
    return [float(c[r] - c.min()) for c, r in zip(costs, selection, strict=True)]


def success_probability(probs: np.ndarray, costs: np.ndarray) -> float:
    return float(probs[np.asarray(costs) <= np.min(costs) + 1e-12].sum())


def compare(runs: DataFrame, baseline: str) -> DataFrame:
    """Adds to (dataset, k, solver, sse) the ratio to the baseline solver on the same data and k."""
    base = runs.where(F.col("solver") == baseline).select("dataset", "k", F.col("sse").alias("base_sse"))
    return runs.join(base, ["dataset", "k"], "left").withColumn("ratio", F.col("sse") / F.nullif("base_sse", F.lit(0.0)))


def agreement(labelled: DataFrame, found: str = "g", truth: str = "label") -> dict[str, float]:
    """Purity, adjusted Rand index and normalised mutual information from the contingency table (clusters x labels rows)."""
    rows = labelled.groupBy(found, truth).count().collect()
    a, b = sorted({r[0] for r in rows}), sorted({r[1] for r in rows})
    t = np.zeros((len(a), len(b)))
    for r in rows:
        t[a.index(r[0]), b.index(r[1])] = r["count"]
    n, pairs = t.sum(), lambda x: (x * (x - 1) / 2).sum()
    same, rows_, cols_ = pairs(t), pairs(t.sum(axis=1)), pairs(t.sum(axis=0))
    expected = rows_ * cols_ / (n * (n - 1) / 2) if n > 1 else 0.0
    ari = (same - expected) / ((rows_ + cols_) / 2 - expected) if (rows_ + cols_) / 2 != expected else 1.0
    p = t / n
    entropy = lambda q: -(q[q > 0] * np.log(q[q > 0])).sum()
    outer = p.sum(axis=1, keepdims=True) * p.sum(axis=0, keepdims=True)
    mutual = (p[p > 0] * np.log(p[p > 0] / outer[p > 0])).sum()
    norm = (entropy(p.sum(axis=1)) + entropy(p.sum(axis=0))) / 2
    return {"purity": float(t.max(axis=1).sum() / n), "ari": float(ari), "nmi": float(mutual / norm) if norm else 1.0}


@contextmanager
def timed():
    """``with timed() as t``: seconds in t['s'] afterwards."""
    out = {"s": math.nan}
    began = time.perf_counter()
    try:
        yield out
    finally:
        out["s"] = time.perf_counter() - began


def observed(df: DataFrame, name: str):
    """A DataFrame that counts its rows while it runs, and the Observation with ``rows``."""
    from pyspark.sql import Observation

    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows")), seen


def _nodes(plan):
    """Operators of a physical plan, through adaptive plans and their stages (which hide their children)."""
    yield plan
    inner = {"AdaptiveSparkPlanExec": "executedPlan", "ShuffleQueryStageExec": "plan", "BroadcastQueryStageExec": "plan", "TableCacheQueryStageExec": "plan", "ResultQueryStageExec": "plan"}.get(plan.getClass().getSimpleName())
    if inner:
        yield from _nodes(getattr(plan, inner)())
    children = plan.children()
    for i in range(children.size()):
        yield from _nodes(children.apply(i))


def io(df: DataFrame) -> dict[str, int]:
    """Runs ``df`` and returns what its plan counted: rows and bytes of files scanned, rows and bytes shuffled, rows out.

    Bytes scanned are the sizes of the files that were left after pruning partitions. Only sessions with a JVM of their own
    give plan metrics.
    """
    execution = df._jdf.queryExecution()
    out = {"rows_scanned": 0, "bytes_scanned": 0, "rows_shuffled": 0, "bytes_shuffled": 0, "rows_out": int(execution.toRdd().count())}
    metric = {"FileSourceScanExec": {"rows_scanned": "numOutputRows", "bytes_scanned": "filesSize"}, "ShuffleExchangeExec": {"rows_shuffled": "shuffleRecordsWritten", "bytes_shuffled": "shuffleBytesWritten"}}
    for node in _nodes(execution.executedPlan()):
        for name, key in metric.get(node.getClass().getSimpleName(), {}).items():
            found = node.metrics().get(key)
            if found.isDefined():
                out[name] += int(found.get().value())
    return out


def sketch_bytes(m: int) -> int:
    return 16 * m
