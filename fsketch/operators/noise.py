"""A noisy device: depolarisation of the register, errors per two-qubit gate and independent read-out flips. Levels are
parameters, not a calibration."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from . import resources
from .variational import sample_shots


@dataclass(frozen=True)
class Noise:
    depolarise: float = 0.02
    flip01: float = 0.01
    flip10: float = 0.02
    contrast: float = 0.98
    postselect: bool = True
    penalty: float = 10.0
    p2: float = 0.0  # chance that a two-qubit gate loses the state

    def lost(self, d: int, p: int = 1) -> float:
        """Depolarised share after p layers over d candidates: the flat share, and one error per two-qubit gate. A group's
        costs have no couplings on one-hot states, so these are the mixers' gates."""
        return 1 - (1 - self.depolarise) * (1 - self.p2) ** sum(resources.gates(p, d, 0).values())

    def phase_test(self) -> dict[str, float]:
        """What ``hadamard`` takes of the device."""
        return {"contrast": self.contrast, "flip": (self.flip01 + self.flip10) / 2, "p2": self.p2}

    def ancilla(self, slots: int) -> float:
        """Contrast of a phase test over an index register of ``slots`` states: one controlled phase each."""
        return self.contrast * (1 - self.p2) ** slots

    def outcomes(self, probs: np.ndarray, p: int = 1) -> np.ndarray:
        """Distribution over all bit strings, from one over candidates after p layers."""
        n = len(probs)
        if n > 12:
            raise ValueError("too many candidates to list all bit strings")
        lost = self.lost(n, p)
        out = np.full(1 << n, lost / (1 << n))
        out[1 << np.arange(n)] += (1 - lost) * probs
        table = out.reshape((2,) * n)
        read = np.array([[1 - self.flip01, self.flip10], [self.flip01, 1 - self.flip10]])
        for axis in range(n):
            table = np.moveaxis(np.tensordot(read, table, axes=(1, axis)), 0, axis)
        return table.reshape(-1)

    def pick(self, probs: np.ndarray, costs: np.ndarray, how: str, n_shots: int, tag: tuple, p: int = 1) -> tuple[int, float]:
        """Chosen candidate and the share of one-hot shots. Without post-selection, an infeasible string counts with the
        penalty and stands for its cheapest set bit."""
        n = len(probs)
        counts = sample_shots(self.outcomes(probs, p), n_shots, *tag)
        one_hot = counts[1 << np.arange(n)]
        share = float(one_hot.sum() / max(counts.sum(), 1))
        if self.postselect and one_hot.sum():
            if how == "best_sampled":
                seen = np.flatnonzero(one_hot)
                return int(seen[np.argmin(np.asarray(costs)[seen])]), share
            return int(np.argmax(one_hot)), share
        seen = np.flatnonzero(counts)
        bit = (seen[:, None] >> np.arange(n)) & 1
        energy = bit @ np.asarray(costs) + self.penalty * (1 - bit.sum(axis=1)) ** 2
        top = bit[int(np.argmin(energy)) if how == "best_sampled" else int(np.argmax(counts[seen]))]
        set_bits = np.flatnonzero(top) if top.any() else np.arange(n)
        return int(set_bits[np.argmin(np.asarray(costs)[set_bits])]), share
