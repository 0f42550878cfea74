"""Proved bounds: shot and subsample variance, their sum, sample sizes for a target error, and the cost of dropping cross-group terms."""

from __future__ import annotations

import math

import numpy as np

from .hadamard import register
from .qubo import Model, cross_blocks


def shot(b: int, s: int) -> float:
    """Variance of one rescaled real component from s coins at most."""
    return (register(b)[1] / b) ** 2 / s


def subsample(n: int, b: int, mean: complex) -> float:
    """Variance of the mean of b of n unit phases drawn without replacement, whose population mean is ``mean``."""
    if n <= 1 or b >= n:
        return 0.0
    return (1 - b / n) / b * n / (n - 1) * (1 - abs(mean) ** 2)


def estimator_mse(n: int, b: int, s: int | None, mean: complex) -> float:
    """Mean squared error of a complex component: subsampling and coins in two bases."""
    return subsample(n, b, mean) + (0.0 if s is None else 2 * shot(b, s))


def sizes(eps: float, constant: float = 2.0) -> tuple[int, int]:
    """Sample rows and shots that keep the mean squared error within a constant times eps^2."""
    return math.ceil(constant / eps**2), math.ceil(constant / eps**2)


def relaxation(model: Model) -> dict:
    """How much dropping the blocks between groups can cost: with m_gh the largest absolute coefficient between two groups, any
    selection's energy moves by at most 2 sum over pairs m_gh, and the optimum's by twice that."""
    m = cross_blocks(model)
    pairs = float(np.triu(np.maximum(m, m.T), 1).sum())
    rows = np.maximum(m, m.T).sum(axis=1)
    return {"pointwise": 2 * pairs, "gap": 4 * pairs, "row_sum_gap": 2 * len(m) * float(rows.max(initial=0.0)), "row_sum": float(rows.max(initial=0.0))}


def cross_energy(model: Model, y: np.ndarray) -> np.ndarray:
    """The energy that the dropped blocks contribute."""
    same = model.group[:, None] == model.group[None, :]
    y = np.atleast_2d(y).astype(float)
    return np.einsum("si,ij,sj->s", y, np.where(same, 0.0, model.quadratic), y)
