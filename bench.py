"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: one JSON line with the seconds of each."""

from __future__ import annotations

import json
import os
import time

from fsketch.operators import freq, lloyd, measures, scale, seed, sketch
from fsketch.operators.noise import Noise
from fsketch.plans.pipeline import cluster
from fsketch.session import local_session
from fsketch.sources.workloads import load


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session(os.environ.get("BENCH_CPUS"))
    load(spark, sf, "W8").count()  # starts the engine
    seconds: dict[str, float] = {}
    facts: dict[str, dict] = {}

    def timed(name, f):
        began = time.perf_counter()
        got = f()
        seconds[name] = round(time.perf_counter() - began, 3)
        return got

    for w in ("W11", "W12", "W14", "W15"):
        for k in (3, 10):
            r = timed(f"cluster_{w}_k{k}", lambda w=w, k=k: cluster(load(spark, sf, w), k, seed_on="sample", seed_iters=8))
            facts[f"cluster_{w}_k{k}"] = {"sse": r.sse, "over_seed": round(r.sse / r.seed_sse, 4), "peak_qubits": r.peak_qubits, "m": r.params["m"]}
    for name, w, settings in (
        ("cluster_W14_k5_full_seeding", "W14", {}), ("cluster_W14_k5_noisy", "W14", {"seed_on": "sample", "seed_iters": 8, "noise": Noise(p2=0.002)}),
        ("cluster_W14_k5_per_frequency", "W14", {"seed_on": "sample", "seed_iters": 8, "sampling": "per_frequency"}),
    ):
        r = timed(name, lambda w=w, s=settings, k=int(name.split("_k")[1][0]): cluster(load(spark, sf, w), k, **s))
        facts[name] = {"sse": r.sse, "over_seed": round(r.sse / r.seed_sse, 4), "peak_qubits": r.peak_qubits, "m": r.params["m"]}
    points, _ = timed("standardise_W14", lambda: scale.prepare(load(spark, sf, "W14")))
    timed("sketch_wide_m24", lambda: sketch.vector(sketch.exact(points, freq.matrix(24, 2), "wide"), 24))
    timed("sketch_arrow_m240", lambda: sketch.vector(sketch.exact(points, freq.matrix(240, 2), "arrow"), 240))
    c = timed("seeds_sample", lambda: seed.kmeans(points, 10, "sample", iters=5))
    timed("assign_wcss", lambda: measures.wcss(lloyd.assign(points, c), c, prefix="z"))
    r = timed("refine_W14_3_steps", lambda: cluster(load(spark, sf, "W14"), 5, refine_steps=3, seed_on="sample", seed_iters=5, accept="guard", decode="best_sampled"))
    facts["refine_W14_3_steps"] = {"sse": r.sse, "over_seed": round(r.sse / r.seed_sse, 4), "steps": len(r.history)}
    print(json.dumps({"metric": "seconds of the headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": sf, "facts": facts}))


if __name__ == "__main__":
    main()
