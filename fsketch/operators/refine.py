"""Sketch-Lloyd: reassign, re-estimate cluster sketches, jitter around the incumbents, solve again."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame

from . import candidates, hadamard, lloyd, qubo, solve, variational
from .noise import Noise


@dataclass
class Settings:
    d: int = 4
    jitter: float = 0.2
    decay: float = 0.7
    keep: bool = True
    b: int | None = 256
    sampling: str = "shared"  # shared | per_frequency: a cluster's rows once for all frequencies, or anew for each
    shots_phase: int | None = 1024
    shots_select: int = 10_000
    p: int = 1
    solver: str = "circuit"  # circuit | grouped_exact | global | coupled | exhaustive | exhaustive_sketch
    decode: str = "mode"
    mixer: str = "ring_exact"
    init: str = "w"
    noise: Noise | None = None
    accept: str = "raw"  # raw | guard
    seed: int = 42
    budget: int = solve.BUDGET
    schedule: Callable[[int], tuple[int, int | None]] | None = None  # step -> (layers, shots per frequency)


@dataclass
class Step:
    centroids: np.ndarray
    selection: list[int] | None
    status: str
    sketches: np.ndarray
    counts: np.ndarray
    before: float
    after: float
    feasible: float = 1.0
    angles: list = field(default_factory=list)


def grouped_surrogate(zg: np.ndarray, counts: np.ndarray, centroids: np.ndarray, w: np.ndarray) -> float:
    """Over clusters that have rows."""
    f = np.abs(np.exp(1j * centroids @ w.T) - zg) ** 2
    return float(f[counts > 0].sum())


def step(points: DataFrame, centroids: np.ndarray, w: np.ndarray, s: Settings, t: int = 0, angles: list | None = None, z: np.ndarray | None = None) -> Step:
    """One round. Empty clusters keep their centroid. With ``guard`` a group changes only if its own mismatch falls. ``z`` is the
    sketch of all points, if it was estimated by itself; else the clusters' sketches make it up."""
    p, shots = s.schedule(t) if s.schedule else (s.p, s.shots_phase)
    k = len(centroids)
    assigned = lloyd.assign(points, centroids)
    contrast = s.noise.phase_test() if s.noise else {}
    zg, counts = hadamard.estimate_clusters(assigned, w, s.b, shots, s.seed + t, sampling=s.sampling, **contrast)
    zg = np.concatenate([zg, np.zeros((k - len(zg), len(w)), complex)])
    counts = np.concatenate([counts, np.zeros(k - len(counts), np.int64)])
    sets = candidates.around(centroids, s.d, s.jitter, s.decay, t, s.seed, s.keep)
    costs = qubo.grouped_costs(zg, sets, w)
    z = (counts[:, None] * zg).sum(axis=0) / max(counts.sum(), 1) if z is None else z
    status, feasible, used = "solved", 1.0, []
    if s.solver == "circuit":
        pick, used, feasible = variational.select(costs, p, s.decode, s.shots_select, s.mixer, s.init, s.seed + t, s.noise, angles)
    elif s.solver == "grouped_exact":
        pick = solve.grouped_exact(costs).selection
    elif s.solver == "global":
        pick = solve.grouped_exact(qubo.global_costs(qubo.joint(z, sets, w))).selection
    else:
        if s.solver == "coupled":
            got = solve.coupled(points.sparkSession, qubo.joint(z, sets, w), s.budget)
        elif s.solver == "exhaustive":
            got = solve.exhaustive(points, sets, "wcss", budget=min(s.budget, 20_000))
        elif s.solver == "exhaustive_sketch":
            got = solve.exhaustive(points, sets, "sketch", qubo.joint(z, sets, w), s.budget)
        else:
            raise ValueError(f"unknown solver {s.solver}")
        pick, status = got.selection, got.status
    before = grouped_surrogate(zg, counts, centroids, w)
    if pick is None:
        return Step(centroids, None, status, zg, counts, before, before)
    new = candidates.chosen(sets, pick)
    worse = (np.abs(np.exp(1j * new @ w.T) - zg) ** 2).sum(axis=1) > (np.abs(np.exp(1j * centroids @ w.T) - zg) ** 2).sum(axis=1) if s.accept == "guard" else np.zeros(k, bool)
    new = np.where(((counts == 0) | worse)[:, None], centroids, new)
    return Step(new, pick, status, zg, counts, before, grouped_surrogate(zg, counts, new, w), feasible, used)


def run(points: DataFrame, centroids: np.ndarray, w: np.ndarray, s: Settings, max_steps: int = 10, tol: float = 1e-4, transfer_angles: bool = False, z: np.ndarray | None = None) -> tuple[np.ndarray, list[dict]]:
    """Rounds until the centroids move by at most ``tol`` (Frobenius) or ``max_steps``; two passes over the points each, for the
    clusters' sizes and samples (one if all rows are taken)."""
    history, angles = [], None
    for t in range(max_steps):
        r = step(points, centroids, w, s, t, angles, z)
        move = float(np.linalg.norm(r.centroids - centroids))
        history.append({"step": t, "move": move, "before": r.before, "surrogate_grouped": r.after, "status": r.status, "feasible": r.feasible})
        centroids = r.centroids
        angles = r.angles if transfer_angles and r.angles else None
        if r.status == "no_solution" or (t and move <= tol):
            break
    return centroids, history
