"""Sketches: means of exp(i w.x) over points, clusters or centroids, exact and mergeable.

Two engines give the same sums. Up to ``WIDE`` frequencies an aggregate of cosines and sines stays in generated code;
beyond, partitions hand Arrow batches to numpy and send 2 m sums per cluster each. Either way no point is shuffled.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.vectors import dot, feature_names

WIDE = 48


def features(df: DataFrame, w: np.ndarray, prefix: str = "z", key: str = "row_key") -> DataFrame:
    """(key, j, re, im): the feature map, one row per point and frequency. For samples and small tables."""
    cols = feature_names(df, prefix)
    terms = [F.struct(F.lit(j).alias("j"), dot(cols, row).alias("t")) for j, row in enumerate(w)]
    return df.select(key, F.explode(F.array(*terms)).alias("f")).select(key, "f.j", F.cos("f.t").alias("re"), F.sin("f.t").alias("im"))


def _sums_wide(df: DataFrame, w: np.ndarray, cols: list[str], by: list[str]) -> DataFrame:
    aggs = []
    for j, row in enumerate(w):
        t = dot(cols, row)
        aggs += [F.sum(F.cos(t)).alias(f"c{j}"), F.sum(F.sin(t)).alias(f"s{j}")]
    one = df.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), *aggs)
    parts = [F.struct(F.lit(j).alias("j"), F.col(f"c{j}").alias("s_re"), F.col(f"s{j}").alias("s_im")) for j in range(len(w))]
    return one.select(*by, "n", F.explode(F.array(*parts)).alias("p")).select(*by, "p.j", "p.s_re", "p.s_im", "n")


def _sums_arrow(df: DataFrame, w: np.ndarray, cols: list[str], by: list[str]) -> DataFrame:
    label = F.col(by[0]).cast("int") if by else F.lit(0)
    m = len(w)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        counts: dict[int, int] = {}
        for batch in batches:
            g = batch.column("_g").to_numpy(zero_copy_only=False)
            x = np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in cols], axis=1)
            for at in range(0, len(x), 4096):
                t = x[at : at + 4096] @ w.T
                both = np.concatenate([np.cos(t), np.sin(t)], axis=1)
                for v in np.unique(g[at : at + 4096]):
                    hit = g[at : at + 4096] == v
                    sums[int(v)] = sums.get(int(v), 0.0) + both[hit].sum(axis=0)
                    counts[int(v)] = counts.get(int(v), 0) + int(hit.sum())
        for v, s in sums.items():
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(m, v, np.int32)), pa.array(np.arange(m, dtype=np.int32)), pa.array(s[:m]), pa.array(s[m:]), pa.array(np.full(m, counts[v], np.int64))],
                names=["_g", "j", "s_re", "s_im", "n"],
            )

    parts = df.select(label.alias("_g"), *cols).mapInArrow(work, "_g int, j int, s_re double, s_im double, n long")
    out = parts.groupBy("_g", "j").agg(F.sum("s_re").alias("s_re"), F.sum("s_im").alias("s_im"), F.sum("n").alias("n"))
    return out.select(*([F.col("_g").alias(by[0])] if by else []), "j", "s_re", "s_im", "n")


def sums(df: DataFrame, w: np.ndarray, by: str | None = None, engine: str = "auto", prefix: str = "z") -> DataFrame:
    """([g,] j, s_re, s_im, n): sums that merge by addition."""
    cols = feature_names(df, prefix)
    if w.shape[1] != len(cols):
        raise ValueError(f"frequencies have {w.shape[1]} columns, points {len(cols)}")
    if engine == "auto":
        engine = "wide" if len(w) <= WIDE else "arrow"
    return {"wide": _sums_wide, "arrow": _sums_arrow}[engine](df, w, cols, [by] if by else [])


def means(parts: DataFrame) -> DataFrame:
    by = [c for c in parts.columns if c not in ("j", "s_re", "s_im", "n")]
    n = F.nullif("n", F.lit(0))
    return parts.select(*by, "j", (F.col("s_re") / n).alias("re"), (F.col("s_im") / n).alias("im"), "n")


def exact(df: DataFrame, w: np.ndarray, engine: str = "auto", prefix: str = "z") -> DataFrame:
    """(j, re, im, n): the data sketch over all rows."""
    return means(sums(df, w, None, engine, prefix))


def per_cluster(assigned: DataFrame, w: np.ndarray, engine: str = "auto", prefix: str = "z", by: str = "g") -> DataFrame:
    """(g, j, s_re, s_im, n) per label of an assigned table."""
    return sums(assigned, w, by, engine, prefix)


def merge(*parts: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """The sketch sums of the union of disjoint tables."""
    union = parts[0]
    for p in parts[1:]:
        union = union.unionByName(p)
    return union.groupBy(*by, "j").agg(F.sum("s_re").alias("s_re"), F.sum("s_im").alias("s_im"), F.sum("n").alias("n"))


def subtract(whole: DataFrame, part: DataFrame) -> DataFrame:
    """The sketch sums of what is left when ``part`` is taken out of ``whole``."""
    return merge(whole, part.select("j", (-F.col("s_re")).alias("s_re"), (-F.col("s_im")).alias("s_im"), (-F.col("n")).alias("n")))


def vector(z: DataFrame, m: int) -> np.ndarray:
    """A sketch as a complex vector on the driver: m numbers."""
    out = np.zeros(m, complex)
    for r in z.select("j", "re", "im").collect():
        out[r.j] = complex(r.re, r.im)
    return out


def cluster_vectors(parts: DataFrame, k: int, m: int) -> tuple[np.ndarray, np.ndarray]:
    """(k x m means, k counts) on the driver; clusters without rows have count 0 and a zero sketch."""
    z, n = np.zeros((k, m), complex), np.zeros(k, np.int64)
    for r in parts.collect():
        if r.n:
            z[r.g, r.j] = complex(r.s_re, r.s_im) / r.n
            n[r.g] = r.n
    return z, n


def feature_matrix(points: np.ndarray, w: np.ndarray) -> np.ndarray:
    """exp(i w.x) of points on the driver (centroids, candidates): len(points) x m."""
    return np.exp(1j * np.asarray(points, float) @ w.T)


def of_centroids(centroids: np.ndarray, w: np.ndarray, weights=None) -> np.ndarray:
    """Mean of the centroids' features, weighted if asked."""
    f = feature_matrix(centroids, w)
    return f.mean(axis=0) if weights is None else (np.asarray(weights)[:, None] * f).sum(axis=0) / np.sum(weights)


def mismatch(z: np.ndarray, other: np.ndarray) -> float:
    return float((np.abs(z - other) ** 2).sum())


def to_frame(spark: SparkSession, z: np.ndarray) -> DataFrame:
    return spark.createDataFrame([(j, float(v.real), float(v.imag)) for j, v in enumerate(z)], "j int, re double, im double")
