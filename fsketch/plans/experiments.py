"""The experiment grids: all shapes and tables by k, candidates, noise, solvers, frequencies and sample sizes.

``python -m fsketch.plans.experiments [SF_DIR] [GRID...]`` prints one JSON line per run.
"""

from __future__ import annotations

import json
import sys
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

from ..operators import baselines, freq, measures, resources, scale
from ..operators.noise import Noise
from ..sources.workloads import WORKLOADS, load
from .pipeline import cluster, compressive_baseline

SHAPES = ("W1", "W2", "W3", "W3b", "W4", "W5", "W6")
TABLES = ("W7", "W8", "W9", "W10", "W11", "W12", "W13", "W14", "W15")
KS = (3, 5, 10)
NOISY = Noise(p2=0.002)


def _row(grid: str, workload: str, k: int, solver: str, sse: float | None, **more) -> dict:
    return {"grid": grid, "dataset": WORKLOADS[workload][0], "k": k, "solver": solver, "sse": sse} | more


def _grouped(spark: SparkSession, sf: str, grid: str, w: str, k: int, label: str = "grouped", **settings) -> dict:
    r = cluster(load(spark, sf, w), k, **settings)
    return _row(grid, w, k, label, r.sse if r.status == "solved" else None, m=r.params["m"], d=r.params["d"], b=r.params["b"], qubits=r.peak_qubits, seconds=round(r.seconds, 2), over_seed=r.sse / r.seed_sse if r.seed_sse else None, status=r.status)


def shapes(spark: SparkSession, sf: str, ks=KS, budget: int = 5_000_000, workloads=SHAPES) -> Iterator[dict]:
    """Grouped selection beside the stand-ins for noisy means, overlap distances and the hybrid assignment, on planted shapes."""
    for w in workloads:
        for k in ks:
            yield _grouped(spark, sf, "shapes", w, k)
            points, scaler = scale.prepare(load(spark, sf, w))
            points = points.persist()
            n = points.count()
            for label, qubits, run in (
                ("noisy means", resources.noisy_means_qubits(n), lambda p=points, k=k: baselines.noisy_kmeans(p, k)[0]), ("overlap", resources.overlap_qubits(), lambda p=points, k=k: baselines.overlap_kmeans(p, k)[0]),
                ("hybrid", resources.assignment_qubits(k), lambda p=points, k=k: baselines.assign_qubo(p, k, budget=budget)[0]),
            ):
                with measures.timed() as t:
                    c = run()
                yield _row("shapes", w, k, label, None if c is None else measures.original_wcss(points, c, scaler), qubits=qubits, seconds=round(t["s"], 2), status="solved" if c is not None else "no_solution")
            points.unpersist()


def tables(spark: SparkSession, sf: str, ks=KS, ds=(4, 6), workloads=TABLES) -> Iterator[dict]:
    """k-means, continuous sketch matching, and grouped selection without and with noise."""
    for w in workloads:
        for k in ks:
            points, scaler = scale.prepare(load(spark, sf, w))
            points = points.persist()
            c, _ = baselines.kmeans(points, k)
            yield _row("tables", w, k, "k-means", measures.original_wcss(points, c, scaler))
            points.unpersist()
            _, sse = compressive_baseline(load(spark, sf, w), k)
            yield _row("tables", w, k, "compressive", sse, m=freq.default_m(k, WORKLOADS[w][1]))
            for d in ds:
                yield _grouped(spark, sf, "tables", w, k, d=d)
                yield _grouped(spark, sf, "tables", w, k, "grouped, noisy", d=d, noise=NOISY)


def ablation(spark: SparkSession, sf: str, ks=KS, workloads=("W7", "W8", "W9", "W10", "W11", "W13")) -> Iterator[dict]:
    """Grouped, coupled and exhaustive selection over the same candidates; k = 10 is beyond the budget."""
    for w in workloads:
        for k in ks:
            for solver in ("grouped_exact", "coupled", "exhaustive"):
                yield _grouped(spark, sf, "ablation", w, k, solver, solver=solver, budget=1_000_000)


def frequencies(spark: SparkSession, sf: str, k: int = 3, workloads=("W7", "W8", "W12")) -> Iterator[dict]:
    for w in workloads:
        d = WORKLOADS[w][1]
        for times in (1, 2, 4, 8):
            yield _grouped(spark, sf, "frequencies", w, k, m=times * k * d)


def qubits(spark: SparkSession, sf: str, k: int = 3, workloads=("W7", "W8", "W12")) -> Iterator[dict]:
    for w in workloads:
        for b in (128, 256, 512, 1024):
            yield _grouped(spark, sf, "qubits", w, k, b=b, d=8)


def convergence(spark: SparkSession, sf: str) -> Iterator[dict]:
    """Mean squared error of the estimator over sample rows and shots, beside its bound."""
    for w in ("W8", "W12"):
        points, _ = scale.prepare(load(spark, sf, w))
        points = points.persist()
        for b, s in ((16, 64), (32, 256), (64, 1024)):
            yield _row("convergence", w, 0, f"B={b}, S={s}", None) | measures.estimator_error(points, 4, b, s, 10)
        points.unpersist()


def markdown(rows: list[dict]) -> str:
    """Runs as a table."""
    names = ["grid", "dataset", "k", "solver", "m", "d", "b", "qubits", "sse", "over_seed", "status"]
    cell = lambda v: "" if v is None else f"{v:.5g}" if isinstance(v, float) else str(v)
    lines = ["| " + " | ".join(names) + " |", "| " + " | ".join("---" for _ in names) + " |"]
    return "\n".join([*lines, *["| " + " | ".join(cell(r.get(n)) for n in names) + " |" for r in rows]])


GRIDS = {f.__name__: f for f in (shapes, tables, ablation, frequencies, qubits, convergence)}


def as_frame(spark: SparkSession, rows: list[dict]) -> DataFrame:
    """Runs as a table (dataset, k, solver, sse), ready for ``measures.compare``."""
    return spark.createDataFrame([(r["dataset"], r["k"], r["solver"], r["sse"]) for r in rows], "dataset string, k int, solver string, sse double")


def main(args: list[str]) -> None:
    from ..session import local_session

    sf = args[0] if args else "/root/testdata/sf0.01"
    for name in args[1:] or GRIDS:
        for row in GRIDS[name](local_session(), sf):
            print(json.dumps(row), flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
