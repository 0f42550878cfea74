"""Quality classifier: random Fourier features over document statistics, ridge scores, isotonic calibration.

Statistics of each whole text (shares of character classes, word and line figures) are standardised and mapped to
random cosine features, whose inner products approximate a Gaussian kernel. Ridge weights solve the normal
equations, which are summed per partition; scores of rows that did not take part are calibrated to label rates by
isotonic regression. Labels, language, source and id are never inputs.

The classifier is fitted on at most ``max_rows`` labelled ids (those of least hash), four fifths of them for the weights
and the rest for the calibration; every row is scored.

Defined cases: null and empty texts get the statistics of a text without words, and a score like any other; labels other
than 0 and 1, unlabelled ids and null ids are not used; repeated labels of an id count once (the larger one); of several texts of a labelled id the one of least hash takes part in the fit; without labels of
both classes every score is the share of label 1 among those there are (0.5 if none); an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrow import slices, text_bytes
from .store import materialise, ship
from .words import buffer_of, mix, word_hashes, word_places

MAX_ROWS = 50_000
FEATURES = 256
RIDGE = 1e-2
THRESHOLD = 0.3


def _mask(values) -> np.ndarray:
    out = np.zeros(256, dtype=bool)
    out[list(values)] = True
    return out


_CLASSES = {
    "upper": _mask(range(0x41, 0x5B)),
    "lower": _mask(range(0x61, 0x7B)),
    "digit": _mask(range(0x30, 0x3A)),
    "symbol": _mask(b"#*$%&|<>{}[]=_\\/@^~`+"),
    "stop": _mask(b".,;:?"),
    "shout": _mask(b"!"),
    "wide": _mask(range(0x80, 0x100)),
    "newline": _mask(b"\n"),
}
_NOT_NEWLINE = _mask(b"\n")
STATISTICS = [*[f"{c}_share" for c in _CLASSES], "log_words", "mean_word", "spread_word", "distinct_words", "capital_words", "marked_words", "short_words", "distinct_lines", "words_per_line", "longest_run"]


def statistics(texts: pa.Array) -> np.ndarray:
    """One row of statistics per text of a binary column."""
    buf, offsets = buffer_of(texts)
    n = len(texts)
    size = np.maximum(np.diff(offsets), 1).astype(float)

    def per_text(values: np.ndarray) -> np.ndarray:
        run = np.zeros(len(values) + 1, np.int64)
        np.cumsum(values, out=run[1:])
        return np.diff(run[offsets]).astype(float)

    shares = [per_text(m[buf]) / size for m in _CLASSES.values()]
    starts, ends, owner = word_places(buf, offsets)
    words = np.bincount(owner, minlength=n).astype(float)
    some = np.maximum(words, 1)
    length = (ends - starts).astype(float)
    mean = np.bincount(owner, weights=length, minlength=n) / some
    spread = np.sqrt(np.maximum(np.bincount(owner, weights=length**2, minlength=n) / some - mean**2, 0))

    def distinct(hashes: np.ndarray, of: np.ndarray) -> np.ndarray:
        key = np.sort((mix(hashes + mix(of.astype(np.uint64))) >> np.uint64(22)) | (of.astype(np.uint64) << np.uint64(42)))
        head = np.ones(len(key), bool)
        head[1:] = key[1:] != key[:-1]
        return np.bincount((key[head] >> np.uint64(42)).astype(np.int64), minlength=n)

    hashes = word_hashes(buf, starts, ends)
    first, last = (buf[starts], buf[ends - 1]) if len(starts) else (buf[:0], buf[:0])
    share = lambda flag: np.bincount(owner, weights=flag, minlength=n) / some
    line_starts, line_ends, line_owner = word_places(buf, offsets, _NOT_NEWLINE)
    lines = np.maximum(np.bincount(line_owner, minlength=n), 1)
    same = np.zeros(len(owner))
    if len(owner) > 1:
        same[1:] = (hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1])
    rows = [
        *shares, np.log1p(words), mean, spread, distinct(hashes, owner) / some, share(_CLASSES["upper"][first]),
        share(_CLASSES["symbol"][last] | _CLASSES["shout"][last]), share(length <= 3),
        np.where(words > 0, distinct(word_hashes(buf, line_starts, line_ends), line_owner) / lines, 1.0), np.log1p(words / lines), share(same),
    ]
    return np.stack(rows, axis=1)


def document_statistics(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, stats): one array of doubles per row."""
    ship(docs.sparkSession)
    rows = docs.select(docs[id_col].alias(id_col), docs[text_col].alias("_text"))
    schema = T.StructType([rows.schema[id_col], T.StructField("stats", T.ArrayType(T.DoubleType()))])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "_text"):
                got = statistics(text_bytes(batch.column("_text")))
                at = np.arange(0, got.size + 1, got.shape[1], dtype=np.int32)
                yield pa.RecordBatch.from_arrays([batch.column(id_col), pa.ListArray.from_arrays(pa.array(at), pa.array(got.ravel()))], names=schema.names)

    return rows.mapInArrow(work, schema)


@dataclass
class Model:
    mean: np.ndarray
    scale: np.ndarray
    frequencies: np.ndarray
    phases: np.ndarray
    weights: np.ndarray
    steps: np.ndarray  # ridge scores at which the calibrated rate changes
    rates: np.ndarray

    def map(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -8, 8)
        return np.sqrt(2 / len(self.phases)) * np.cos(z @ self.frequencies + self.phases)

    def raw(self, x: np.ndarray) -> np.ndarray:
        return np.concatenate([self.map(x), np.ones((len(x), 1))], axis=1) @ self.weights

    def score(self, x: np.ndarray) -> np.ndarray:
        return np.clip(np.interp(self.raw(x), self.steps, self.rates), 0.0, 1.0)


def isotonic(scores: np.ndarray, labels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Non-decreasing label rates that fit best, by pooling neighbours that are out of order."""
    levels, at, counts = np.unique(scores, return_inverse=True, return_counts=True)  # equal scores are one point from the start
    means = np.bincount(at, weights=labels, minlength=len(levels)) / counts
    pools: list[list[float]] = []  # rate, weight, first score, last score
    for s, y, n in zip(levels.tolist(), means.tolist(), counts.tolist(), strict=True):
        pools.append([y, n, s, s])
        while len(pools) > 1 and pools[-2][0] >= pools[-1][0]:
            rate, weight, _, last = pools.pop()
            top = pools[-1]
            top[0] = (top[0] * top[1] + rate * weight) / (top[1] + weight)
            top[1] += weight
            top[3] = last
    return np.array([v for p in pools for v in (p[2], p[3])]), np.array([p[0] for p in pools for _ in range(2)])


def fit(rows: DataFrame, features: int = FEATURES, bandwidth: float | None = None, ridge: float = RIDGE, seed: int = 11) -> Model:
    """From a bounded DataFrame (stats, label, calibrate); partitions send their moments and normal equations only."""
    d = len(STATISTICS)
    cols = [F.get("stats", i) for i in range(d)]
    moments = rows.agg(*[F.avg(c) for c in cols], *[F.stddev_pop(c) for c in cols]).first()
    mean, scale = (np.array([v or 0.0 for v in part]) for part in (moments[:d], moments[d:]))
    rng = np.random.Generator(np.random.PCG64(seed))
    freq = rng.standard_normal((d, features)) / (bandwidth or np.sqrt(d))
    model = Model(mean, np.where(scale > 1e-12, scale, 1.0), freq, rng.uniform(0, 2 * np.pi, features), np.zeros(features + 1), np.array([0.0]), np.array([0.5]))
    width = features + 1

    def normal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((width, width + 1))
        for b in batches:
            x = model.map(np.array(b.column("stats").to_pylist()).reshape(-1, d))
            x = np.concatenate([x, np.ones((len(x), 1))], axis=1)
            total[:, :width] += x.T @ x
            total[:, width] += x.T @ b.column("label").to_numpy()
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()])], names=["sums"])

    parts = rows.where("not calibrate").select("stats", F.col("label").cast("double").alias("label")).mapInArrow(normal, "sums binary").collect()
    total = sum((np.frombuffer(p[0]).reshape(width, width + 1) for p in parts), np.zeros((width, width + 1)))
    n = max(total[-1, width - 1], 1.0)
    penalty = ridge * n / features * np.eye(width)
    penalty[-1, -1] = 1e-9 * n
    model.weights = np.linalg.solve(total[:, :width] + penalty, total[:, width])
    held = rows.where("calibrate").select("stats", "label").toPandas()
    if len(held):
        model.steps, model.rates = isotonic(model.raw(np.array(held.stats.tolist())), held.label.to_numpy(dtype=float))
    return model


def remainder(id_col: str) -> Column:
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit(""))) % 5


def fit_classifier(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", max_rows: int = MAX_ROWS, **settings) -> Model | float:
    """Fitted on labelled rows whose id's CRC is not divisible by five; a constant where there are not both classes."""
    usable = labels.select(F.col(id_col).alias("_id"), F.col(label_col).cast("int").alias("label"))
    usable = usable.where("_id is not null and label in (0, 1)").where(remainder("_id") != 0)
    # ids of least hash; the two classes are taken as they come. A threshold leaves hardly more than are wanted before any row moves.
    n = usable.agg(F.approx_count_distinct("_id", 0.02)).first()[0]
    usable = usable.withColumn("_h", F.xxhash64(F.lit(5), "_id"))
    share = 1.2 * max_rows / max(n, 1)  # the count is within some percent
    if share < 1:
        usable = usable.where(F.col("_h") < int((2 * share - 1) * (1 << 63)))
    chosen = usable.groupBy("_id", "_h").agg(F.max("label").alias("label")).orderBy("_h", "_id").limit(max_rows)
    chosen = materialise(chosen, "classifier-labels")
    labelled = docs.select(docs[id_col].alias("_doc"), docs[text_col].alias("_text")).join(F.broadcast(chosen), F.col("_doc") == F.col("_id"))  # at most max_rows narrow rows
    stats = document_statistics(labelled.select(F.struct("_id", "label", "_h", F.xxhash64("_text").alias("_t")).alias("key"), "_text"), "key", "_text").select("key.*", "stats")
    one = stats.groupBy("_id", "_h", "label").agg(F.min_by("stats", "_t").alias("stats"))
    train = materialise(one.select("stats", "label", (F.pmod("_h", F.lit(5)) == 0).alias("calibrate")), "classifier-rows")
    seen = train.groupBy("calibrate", "label").count().collect()
    ones, everything = sum(r["count"] for r in seen if r.label == 1), sum(r["count"] for r in seen)
    if any(len({r.label for r in seen if r.calibrate == c}) < 2 for c in (False, True)):
        return ones / everything if everything else 0.5
    return fit(train, **settings)


def score_rows(docs: DataFrame, model: Model | float, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The kept columns and the score, per row."""
    ship(docs.sparkSession)
    rows = docs.select(*keep, docs[text_col].alias("_text"))
    if not isinstance(model, Model):
        return rows.select(*keep, F.lit(float(model)).alias("score"))
    schema = T.StructType([*[rows.schema[c] for c in keep], T.StructField("score", T.DoubleType())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "_text"):
                score = model.score(statistics(text_bytes(batch.column("_text"))))
                yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in keep], pa.array(score)], names=[*keep, "score"])

    return rows.mapInArrow(work, schema)


def classify(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", **settings) -> DataFrame:
    """(id, score) per row."""
    return score_rows(docs, fit_classifier(docs, labels, id_col, text_col, **settings), text_col, (id_col,))


def op5_quality_classifier(spark, sf_dir: str) -> DataFrame:
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    out = classify(docs, labels)
    return out.select("doc_id", (remainder("doc_id") == 0).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
