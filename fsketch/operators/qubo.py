"""The binary quadratic model of choosing one candidate per group, its scaling, penalty, grouping and Ising form.

States are bit vectors over all candidates, group after group. All sizes are constants of the run, so this is numpy on
the driver; ``frames`` gives the coefficients as tables.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from . import sketch
from .candidates import Sets


@dataclass
class Model:
    """Energy of bits y: offset + linear.y + y.quadratic.y; ``group[i]`` is the group of bit i."""

    linear: np.ndarray
    quadratic: np.ndarray
    group: np.ndarray
    offset: float = 0.0
    scale: float = 1.0

    @property
    def sizes(self) -> list[int]:
        return np.bincount(self.group).tolist()

    def fit_energy(self, y: np.ndarray) -> np.ndarray:
        y = np.atleast_2d(y).astype(float)
        return self.offset + y @ self.linear + np.einsum("si,ij,sj->s", y, self.quadratic, y)

    def one_hot_violation(self, y: np.ndarray) -> np.ndarray:
        y = np.atleast_2d(y)
        return sum((1 - y[:, self.group == g].sum(axis=1)) ** 2 for g in range(len(self.sizes)))

    def energy(self, y: np.ndarray, penalty: float) -> np.ndarray:
        return self.fit_energy(y) + penalty * self.one_hot_violation(y)

    def matrix_form(self, penalty: float) -> tuple[np.ndarray, np.ndarray, float]:
        """Linear part, quadratic part and constant of the total energy, the penalty included."""
        same = (self.group[:, None] == self.group[None, :]).astype(float)
        return self.linear - 2 * penalty, self.quadratic + penalty * same, self.offset + penalty * len(self.sizes)

    def bits(self, selection: list[int]) -> np.ndarray:
        y, at = np.zeros(len(self.group), int), 0
        for size, r in zip(self.sizes, selection, strict=True):
            y[at + r] = 1
            at += size
        return y


def joint(z: np.ndarray, sets: Sets, w: np.ndarray) -> Model:
    """Mismatch between the data sketch and the mean feature of the chosen candidates, without the constant |z|^2."""
    k = len(sets)
    v = np.concatenate([sketch.feature_matrix(s, w) for s in sets])
    group = np.repeat(np.arange(k), [len(s) for s in sets])
    return Model(-2 / k * (np.conj(z)[None, :] * v).sum(axis=1).real, (np.conj(v) @ v.T).real / k**2, group)


def grouped_costs(zg: np.ndarray, sets: Sets, w: np.ndarray) -> list[np.ndarray]:
    """Per group, the squared distance of each candidate's feature to the group's own sketch."""
    return [(np.abs(sketch.feature_matrix(s, w) - z) ** 2).sum(axis=1) for z, s in zip(zg, sets, strict=True)]


def global_costs(model: Model) -> list[np.ndarray]:
    """Per group, the energies of its candidates in the joint model without the blocks between groups."""
    diagonal = model.linear + np.diag(model.quadratic)
    return [diagonal[model.group == g] for g in range(len(model.sizes))]


def decouple(model: Model) -> Model:
    same = model.group[:, None] == model.group[None, :]
    return Model(model.linear, np.where(same, model.quadratic, 0.0), model.group, model.offset, model.scale)


def cross_blocks(model: Model) -> np.ndarray:
    """Largest absolute coefficient between each two groups (0 on the diagonal)."""
    k = len(model.sizes)
    out = np.zeros((k, k))
    for g in range(k):
        for h in range(k):
            if g != h:
                out[g, h] = np.abs(model.quadratic[np.ix_(model.group == g, model.group == h)]).max()
    return out


def normalise(model: Model) -> Model:
    """Divided by the sum of absolute coefficients (1 where that is zero); the minimiser stays."""
    s = np.abs(model.linear).sum() + np.abs(model.quadratic).sum() or 1.0
    return Model(model.linear / s, model.quadratic / s, model.group, model.offset / s, model.scale * s)


def penalty_weight(model: Model, eps: float = 1e-3) -> float:
    """More than all coefficients together, the diagonal included: no infeasible state can win. 1 + eps once scaled."""
    return float(np.abs(model.linear).sum() + np.abs(model.quadratic).sum()) + eps


def penalty_bound_off_diagonal(model: Model, eps: float = 1e-3) -> float:
    """The variant without the diagonal, for reports: it can fail (one candidate and a zero sketch)."""
    off = model.quadratic - np.diag(np.diag(model.quadratic))
    return float(np.abs(model.linear).sum() + np.abs(off).sum()) + eps


def ising(model: Model, penalty: float) -> tuple[np.ndarray, np.ndarray, float, int]:
    """Fields, couplings (upper triangle), offset and number of non-zero couplings, by y = (1 - s) / 2."""
    linear, quadratic, constant = model.matrix_form(penalty)
    sym = (quadratic + quadratic.T) / 2
    diagonal, off = np.diag(sym).copy(), sym - np.diag(np.diag(sym))
    fields = -(linear + diagonal) / 2 - off.sum(axis=1) / 2
    couplings = np.triu(off, 1) / 2
    offset = constant + (linear + diagonal).sum() / 2 + np.triu(off, 1).sum() / 2
    return fields, couplings, float(offset), int((np.abs(couplings) > 1e-15).sum())


def frames(spark: SparkSession, model: Model) -> tuple[DataFrame, DataFrame]:
    """(g, r, b) and (g, r, g2, r2, q)."""
    place = np.concatenate([np.arange(s) for s in model.sizes])
    label = [(int(g), int(r)) for g, r in zip(model.group, place, strict=True)]
    linear = [(*label[i], float(v)) for i, v in enumerate(model.linear)]
    quadratic = [(*label[i], *label[j], float(model.quadratic[i, j])) for i in range(len(label)) for j in range(len(label))]
    return spark.createDataFrame(linear, "g int, r int, b double"), spark.createDataFrame(quadratic, "g int, r int, g2 int, r2 int, q double")
