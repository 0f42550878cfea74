"""Temporary views of a model, for those who work in SQL: its tables, and the costs and selection that follow from them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from ..operators import candidates, freq, lloyd, sketch

VIEWS = ("points", "assignments", "centroids", "frequencies", "sketch", "cluster_sketch", "candidates", "features", "costs", "selection")


def register(points: DataFrame, centroids: np.ndarray, w: np.ndarray, sets: candidates.Sets, prefix: str = "fs_") -> dict[str, str]:
    """Creates or replaces the views and returns their names. ``points`` has row_key and standardised z columns.

    Nothing runs until a view is read. ``features``, ``costs`` and ``selection`` are SQL over the others, so a view that is
    replaced (by other candidates, say) changes what they show only once they are registered again. Clusters without rows
    have no sketch, hence no costs.
    """
    spark, names = points.sparkSession, {v: prefix + v for v in VIEWS}
    assigned = lloyd.assign(points, centroids)
    tables = {
        "points": points, "assignments": assigned.select("row_key", "g", "d2"),
        "centroids": spark.createDataFrame([(g, [float(x) for x in c]) for g, c in enumerate(centroids)], "g int, c array<double>"),
        "frequencies": freq.to_frame(spark, w), "sketch": sketch.exact(points, w),
        "cluster_sketch": sketch.means(sketch.per_cluster(assigned, w)), "candidates": candidates.to_frame(spark, sets),
    }
    for name, df in tables.items():
        df.createOrReplaceTempView(names[name])
    phase = "aggregate(zip_with(c, f.w, (a, b) -> a * b), 0D, (s, x) -> s + x)"
    texts = {
        "features": f"""select g, r, f.j, cos({phase}) as re, sin({phase}) as im
            from (select *, explode((select collect_list(struct(j, w)) from {names['frequencies']})) as f from {names['candidates']})""",
        "costs": f"""select v.g, v.r, sum((v.re - s.re) * (v.re - s.re) + (v.im - s.im) * (v.im - s.im)) as cost
            from {names['features']} v join {names['cluster_sketch']} s on s.g = v.g and s.j = v.j group by v.g, v.r""",
        "selection": f"select g, min(struct(cost, r)).r as r, min(cost) as cost from {names['costs']} group by g",
    }
    for name, text in texts.items():
        spark.sql(f"create or replace temporary view {names[name]} as {text}")
    return names
