"""The whole run: standardise, draw frequencies, seed, select by sketches, refine, assign, measure."""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..operators import baselines, freq, hadamard, lloyd, measures, refine, resources, scale, sketch
from ..operators import seed as seeds
from ..operators.noise import Noise
from ..operators.refine import Settings


@dataclass
class Result:
    centroids: np.ndarray  # standardised
    scaler: scale.Scaler
    assignments: DataFrame
    history: list[dict]
    status: str
    sse: float
    sse_standardized: float
    seed_sse: float
    peak_qubits: int
    seconds: float
    params: dict = field(default_factory=dict)

    @property
    def centroids_original(self) -> np.ndarray:
        return self.scaler.inverse(self.centroids)

    def record(self, spark: SparkSession, dataset: str) -> DataFrame:
        row = (dataset, self.params["k"], self.params["m"], self.params["d"], self.params["b"], self.params["solver"], self.sse, self.peak_qubits, self.seconds, self.status, {k: str(v) for k, v in self.params.items()})
        return spark.createDataFrame([row], "dataset string, k int, m int, d int, b int, solver string, sse double, peak_qubits int, seconds double, status string, params map<string,string>")


def cluster(
    df: DataFrame, k: int, m: int | None = None, d: int = 4, p: int = 1, b: int | None = 256, shots_phase: int | None = 1024, shots_select: int = 10_000,
    sigma: float = 1.0, refine_steps: int = 0, solver: str = "circuit", noise: Noise | None = None, seed: int = 42, seed_on: str = "full", seed_init: str = "hash",
    seed_iters: int = 20, cache: bool = True, tol: float = 1e-4, **more,
) -> Result:
    """Points are (row_key, x0, x1, ...). ``refine_steps`` rounds follow the first selection. ``more`` goes to ``Settings``.

    With ``sampling="per_frequency"`` the sketch of all points is estimated by itself before seeding, and each component of a
    cluster's sketch from a subsample of its own.

    Passes over the points: one for the moments, one per seeding step, two per round, one for the result. With
    ``cache=False`` every pass reads the source again, which is what a table larger than the cluster's memory wants.
    """
    began = time.perf_counter()
    points, scaler = scale.prepare(df)
    if cache:
        points = points.persist()
    dim = len(scaler.cols)
    m = m or freq.default_m(k, dim)
    w = freq.matrix(m, dim, sigma, seed)
    settings = replace(Settings(d=d, p=p, b=b, shots_phase=shots_phase, shots_select=shots_select, solver=solver, noise=noise, seed=seed), **more)
    z = None
    if settings.sampling == "per_frequency" and b is not None:
        fault = noise.phase_test() if noise else {}
        z = sketch.vector(hadamard.estimate_sketch(points, m, b, shots_phase, "per_frequency", sigma, seed, "normal", n=scaler.n, **fault), m)
    first = seeds.kmeans(points, k, seed_on, seed_init, seed_iters, seed, n=scaler.n)
    centroids, history = refine.run(points, first, w, settings, 1 + refine_steps, tol, z=z)
    status = history[-1]["status"]
    assigned = lloyd.assign(points, centroids)
    sse = measures.original_wcss(points, centroids, scaler)
    standard = measures.wcss(assigned, centroids, prefix="z")
    seeded = measures.original_wcss(points, first, scaler)
    params = {"k": k, "m": m, "d": d, "p": p, "b": b or scaler.n, "sigma": sigma, "shots_phase": shots_phase, "shots_select": shots_select, "solver": solver, "noise": noise, "seed": seed, "refine_steps": refine_steps}
    qubits = {"coupled": k * d, "exhaustive": k * d, "exhaustive_sketch": k * d}.get(solver, resources.peak(d, b or 2))
    return Result(centroids, scaler, assigned.select("row_key", "g", "d2"), history, status, sse, standard, seeded, qubits, time.perf_counter() - began, params)


def compressive_baseline(df: DataFrame, k: int, m: int | None = None, weights: str = "uniform", restarts: int = 4, sigma: float = 1.0, seed: int = 42) -> tuple[np.ndarray, float]:
    """Centroids (standardised) by continuous sketch matching on the exact sketch, and the SSE in original units."""
    points, scaler = scale.prepare(df)
    dim = len(scaler.cols)
    m = m or freq.default_m(k, dim)
    w = freq.matrix(m, dim, sigma, seed)
    z = sketch.vector(sketch.exact(points, w), m)
    from pyspark.sql import functions as F

    box = points.agg(*[F.min(f"z{i}") for i in range(dim)], *[F.max(f"z{i}") for i in range(dim)]).first()
    c, _, _ = baselines.compressive(df.sparkSession, z, w, k, np.array(box[:dim]), np.array(box[dim:]), restarts, weights, seed)
    return c, measures.original_wcss(points, c, scaler)


def estimate(df: DataFrame, k: int, **settings) -> DataFrame:
    """The data sketch of standardised points by phase sampling."""
    points, scaler = scale.prepare(df)
    return hadamard.estimate_sketch(points, freq.default_m(k, len(scaler.cols)), **settings)
