"""The selection circuit, simulated exactly on its one-hot subspace (D amplitudes instead of 2^D).

Layers alternate a phase by the candidates' costs with a mixer that moves the excitation between candidates and thus
keeps one-hot states one-hot. Mixers: the whole ring at once (``ring_exact``), or pair gates on the even and then the odd
edges of the ring (``ring_pairs``) or of an open line (``line_pairs``). ``full`` runs the same circuit on all bit strings.

A ring of two has its edge twice, one of a single candidate has none.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from ..functions.hashing import py_uniform
from ..session import ship

MIXERS = ("ring_exact", "ring_pairs", "line_pairs")


def start(n: int, init: str = "w") -> np.ndarray:
    """All candidates alike, or candidate 0 only. From the latter one layer does not see the costs (a global phase)."""
    if init == "w":
        return np.full(n, n**-0.5, complex)
    return np.eye(n, dtype=complex)[0]


def edges(n: int, mixer: str) -> list[tuple[int, int]]:
    """Edges in the order in which pair gates apply: even ones, then odd ones."""
    line = [(i, i + 1) for i in range(n - 1)]
    closing = [(n - 1, 0)] if mixer != "line_pairs" and n > 1 else []
    return line[0::2] + line[1::2] + closing


def hopping(n: int) -> np.ndarray:
    """The ring mixer on one-hot states: strength 2 per edge."""
    h = np.zeros((n, n))
    for a, b in edges(n, "ring_exact"):
        h[a, b] += 2
        h[b, a] += 2
    return h


def mix(state: np.ndarray, beta: float, mixer: str) -> np.ndarray:
    n = len(state)
    if mixer == "ring_exact":
        values, vectors = np.linalg.eigh(hopping(n))
        return vectors @ (np.exp(-1j * beta * values) * (vectors.T @ state))
    out = state.copy()
    c, s = np.cos(2 * beta), -1j * np.sin(2 * beta)
    for a, b in edges(n, mixer):
        out[a], out[b] = c * out[a] + s * out[b], s * out[a] + c * out[b]
    return out


def simulate(costs: np.ndarray, gammas, betas, mixer: str = "ring_exact", init: str = "w") -> np.ndarray:
    """Probabilities of the candidates after len(gammas) layers."""
    state = start(len(costs), init)
    for gamma, beta in zip(gammas, betas, strict=True):
        state = mix(np.exp(-1j * gamma * np.asarray(costs)) * state, beta, mixer)
    return np.abs(state) ** 2


def p1(costs: np.ndarray, gammas: np.ndarray, betas: np.ndarray) -> np.ndarray:
    """One exact ring layer from the uniform start for all pairs of angles: (gammas, betas, candidates), by Fourier sums."""
    n = len(costs)
    phase = np.exp(-1j * np.asarray(gammas)[:, None] * np.asarray(costs)[None, :])
    if n == 1:
        return np.ones((len(gammas), len(betas), 1))
    q = np.arange(n)
    values = 4 * np.cos(2 * np.pi * q / n)
    fourier = np.fft.fft(phase, axis=1)[:, None, :] * np.exp(-1j * np.asarray(betas)[:, None] * values)[None, :, :]
    return np.abs(np.fft.ifft(fourier, axis=2)) ** 2 / n


def full(costs: np.ndarray, gammas, betas, mixer: str = "ring_exact", init: str = "w") -> np.ndarray:
    """Probabilities of all 2^D bit strings (bit r of the index is candidate r); D up to 10."""
    n = len(costs)
    if n > 10:
        raise ValueError("too many candidates for the full state")
    index = np.arange(1 << n)
    bit = (index[:, None] >> np.arange(n)) & 1
    state = np.zeros(1 << n, complex)
    state[1 << np.arange(n)] = start(n, init)
    pairs = edges(n, mixer)

    def exchange(a: int, b: int, beta: float, psi: np.ndarray) -> np.ndarray:
        out, swap = psi.copy(), index ^ (1 << a) ^ (1 << b)
        differ = bit[:, a] != bit[:, b]
        out[differ] = np.cos(2 * beta) * psi[differ] - 1j * np.sin(2 * beta) * psi[swap[differ]]
        return out

    if mixer == "ring_exact":
        h = np.zeros((1 << n, 1 << n))
        for a, b in pairs:
            differ = np.flatnonzero(bit[:, a] != bit[:, b])
            h[differ, differ ^ (1 << a) ^ (1 << b)] += 2
        values, vectors = np.linalg.eigh(h)
    for gamma, beta in zip(gammas, betas, strict=True):
        state = np.exp(-1j * gamma * (bit @ np.asarray(costs))) * state
        if mixer == "ring_exact":
            state = vectors @ (np.exp(-1j * beta * values) * (vectors.T @ state))
        else:
            for a, b in pairs:
                state = exchange(a, b, beta, state)
    return np.abs(state) ** 2


@dataclass
class Angles:
    gammas: np.ndarray
    betas: np.ndarray
    value: float


def optimise(costs: np.ndarray, p: int = 1, grid: int = 17, refine: int = 40, mixer: str = "ring_exact", init: str = "w", objective: str = "mean", init_angles: Angles | None = None) -> Angles:
    """Angles of least mean cost (or of the largest chance of the best candidate): a grid, then a shrinking pattern search.

    Gammas are searched in units of 1 / (largest - least cost). ``init_angles`` takes over those of another group or step
    and skips the grid.
    """
    c = np.asarray(costs, float)
    spread = np.ptp(c) or 1.0
    unit = (c - c.min()) / spread

    def value(a: np.ndarray) -> float:
        probs = simulate(unit, a[:p], a[p:], mixer, init)
        return float(probs @ unit) if objective == "mean" else -float(probs[unit <= 1e-12].sum())

    if init_angles is not None:
        a = np.concatenate([np.resize(init_angles.gammas * spread, p), np.resize(init_angles.betas, p)])
    else:
        g, b = np.linspace(0, 2 * np.pi, grid), np.linspace(0, np.pi / 2, grid)
        pairs = [(round(value(np.concatenate([np.full(p, x), np.full(p, y)])), 9), x, y) for x in g for y in b]  # ties by order
        _, x, y = min(pairs)
        a = np.concatenate([np.full(p, x), np.full(p, y)])
    best, step = value(a), np.concatenate([np.full(p, 2 * np.pi / grid), np.full(p, np.pi / 2 / grid)]) / 2
    for _ in range(refine):
        moved = False
        for i in range(2 * p):
            for sign in (1, -1):
                trial = a.copy()
                trial[i] += sign * step[i]
                v = value(trial)
                if v < best - 1e-12:
                    a, best, moved = trial, v, True
        if not moved:
            step /= 2
    return Angles(a[:p] / spread, a[p:], best)


def sample_shots(probs: np.ndarray, n_shots: int, *tag, hashed: bool = False) -> np.ndarray:
    """Counts per outcome, seeded by the tag: a multinomial draw, or with ``hashed`` one uniform per shot against the cumulative
    probabilities, which SQL can repeat."""
    if hashed:
        x = np.array([py_uniform("shots", *tag, t) for t in range(n_shots)])
        at = np.searchsorted(np.cumsum(probs), x)
        return np.bincount(np.minimum(at, len(probs) - 1), minlength=len(probs))
    rng = np.random.Generator(np.random.PCG64(int(py_uniform("shots", *tag) * (1 << 48))))
    return rng.multinomial(n_shots, probs / probs.sum())


def decode(probs: np.ndarray, costs: np.ndarray, how: str = "mode", n_shots: int = 10_000, tag: tuple = (), hashed: bool = False) -> int:
    """The most frequent outcome (``mode``), the cheapest one seen (``best_sampled``) or the most probable (``exact_prob``)."""
    if how == "exact_prob":
        return int(np.argmax(np.round(probs, 12)))
    counts = sample_shots(probs, n_shots, *tag, hashed=hashed)
    if how == "mode":
        return int(np.argmax(counts))
    seen = np.flatnonzero(counts)
    return int(seen[np.argmin(np.asarray(costs)[seen])])


def select(costs: list[np.ndarray], p: int = 1, how: str = "mode", n_shots: int = 10_000, mixer: str = "ring_exact", init: str = "w", seed: int = 42, noise=None, angles: list[Angles] | None = None) -> tuple[list[int], list[Angles], float]:
    """A candidate per group by the circuit; also the angles used and the share of shots that were one-hot."""
    picks, used, feasible = [], [], []
    for g, c in enumerate(costs):
        a = optimise(c, p, mixer=mixer, init=init, init_angles=angles[g] if angles else None)
        probs = simulate(c - c.min(), a.gammas, a.betas, mixer, init)
        if noise is not None:
            pick, share = noise.pick(probs, c, how, n_shots, ("noisy", seed, g), p)
            feasible.append(share)
        else:
            pick = decode(probs, c, how, n_shots, (seed, g))
            feasible.append(1.0)
        picks.append(pick)
        used.append(a)
    return picks, used, float(np.mean(feasible)) if feasible else 1.0


def select_frame(costs: DataFrame, p: int = 1, how: str = "mode", n_shots: int = 10_000, mixer: str = "ring_exact", init: str = "w", seed: int = 42) -> DataFrame:
    """(g, r, prob) from (g, r, cost): one group per call of the simulator, groups in parallel. A group has D rows."""
    ship(costs.sparkSession)

    def work(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("r")
        c = pdf.cost.to_numpy()
        a = optimise(c, p, mixer=mixer, init=init)
        probs = simulate(c - c.min(), a.gammas, a.betas, mixer, init)
        pick = decode(probs, c, how, n_shots, (seed, int(key[0])))
        return pd.DataFrame({"g": [int(key[0])], "r": [int(pdf.r.iloc[pick])], "prob": [float(probs[pick])]})

    return costs.groupBy("g").applyInPandas(work, "g int, r int, prob double")
