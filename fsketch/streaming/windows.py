"""Windowed sketches of a stream: the sketch is a sum, so it is ordinary incremental state.

``events.ts`` has no time zone; it is read as UTC before watermarks apply.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import py_normal, py_uniform
from ..session import ship
from ..sources.io import drop, scratch

EVENTS = T.StructType([
    T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()),
    T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType()),
])


def events(spark: SparkSession, path: str, watermark: str = "1 day", **options) -> DataFrame:
    rows = source(spark, path, EVENTS, **options)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def source(spark: SparkSession, path: str, schema: T.StructType, **options) -> DataFrame:
    """A file stream over a folder, or over one file by way of its folder and its name."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    if p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isFile():
        options["pathGlobFilter"], path = p.getName(), p.getParent().toString()
    return spark.readStream.schema(schema).options(**options).parquet(path)


def frequencies(m: int, seed: int = 42) -> list[float]:
    return [py_normal("w", seed, j, 0) for j in range(m)]


def sketch_aggregates(value: Column, w: list[float]) -> list[Column]:
    out = [F.count(F.lit(1)).alias("n")]
    for j, f in enumerate(w):
        out += [F.avg(F.cos(value * f)).alias(f"re{j}"), F.avg(F.sin(value * f)).alias(f"im{j}")]
    return out


def windowed(rows: DataFrame, w: list[float], length: str = "1 day", slide: str | None = None, scale: float = 100.0) -> DataFrame:
    """Sketch of value / scale per tumbling (or sliding) window."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    return rows.groupBy(window.alias("w")).agg(*sketch_aggregates(F.col("value") / scale, w)).select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), *_names(w))


def sessions(rows: DataFrame, gap: str = "30 minutes") -> DataFrame:
    s = F.session_window("ts", gap).alias("w")
    return rows.groupBy(s, "user_id").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def deduplicated(rows: DataFrame) -> DataFrame:
    """Each event id once within the watermark."""
    return rows.dropDuplicatesWithinWatermark(["event_id"])


def _names(w: list[float]) -> list[str]:
    return ["n", *[f"{c}{j}" for j in range(len(w)) for c in ("re", "im")]]


def run_to_memory(rows: DataFrame, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Everything that is there now, into a table of the driver; for results of a bounded number of windows."""
    name = f"stream_{uuid.uuid4().hex[:10]}"
    writer = rows.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    writer.start().awaitTermination()
    return rows.sparkSession.table(name)


@contextmanager
def _state_on_disk(spark: SparkSession) -> Iterator[None]:
    """Streams that start meanwhile keep their state in RocksDB, outside of the heap."""
    name, kind = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
    before = spark.conf.get(name)
    spark.conf.set(name, kind)
    try:
        yield
    finally:
        spark.conf.set(name, before)


def run_to_table(rows: DataFrame, mode: str = "append") -> DataFrame:
    """Everything that is there now, as a Parquet table that the tasks write to the shared folder; for results that grow with the
    rows. In complete mode each batch writes the whole result, and the last one's is returned."""
    spark = rows.sparkSession
    path, checkpoint, last = scratch(spark, "stream"), scratch(spark, "stream-state"), [""]

    def whole(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        last[0] = f"/{number}"

    with _state_on_disk(spark):
        if mode == "complete":
            writer = rows.writeStream.foreachBatch(whole).outputMode(mode)
        else:
            writer = rows.writeStream.format("parquet").option("path", path).outputMode(mode)
        query = writer.option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    drop(spark, checkpoint)
    return spark.read.schema(rows.schema).parquet(path + last[0]) if mode != "complete" or last[0] else spark.createDataFrame([], rows.schema)


def run_to_files(rows: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    rows.writeStream.outputMode(mode).format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def run_batches(rows: DataFrame, each: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    """``foreachBatch``: each micro-batch with its number, e.g. to track centroids."""
    rows.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


class CentroidTracker:
    """Follows one-dimensional-feature centroids through micro-batches by running means with a forgetting factor."""

    def __init__(self, centroids: np.ndarray, columns: list[str], keep: float = 0.9):
        self.centroids, self.columns, self.keep, self.weights = np.asarray(centroids, float), columns, keep, np.zeros(len(centroids))

    def __call__(self, batch: DataFrame, number: int) -> None:
        from ..operators import lloyd

        points = batch.select(*[F.col(c).cast("double").alias(f"z{i}") for i, c in enumerate(self.columns)]).dropna()
        means, counts, _ = lloyd.cluster_means(lloyd.assign(points, self.centroids), len(self.centroids))
        for g, n in enumerate(counts):
            if n:
                old = self.keep * self.weights[g]
                self.centroids[g] = (old * self.centroids[g] + n * means[g]) / (old + n)
                self.weights[g] = old + n


def drift(windows: DataFrame, w: list[float]) -> DataFrame:
    """Mismatch of each window's sketch with the one before it."""
    from pyspark.sql.window import Window

    order = Window.orderBy("start")  # one row per window of time
    terms = [(F.col(c) - F.lag(c).over(order)) ** 2 for c in _names(w)[1:]]
    return windows.select("start", sum(terms[1:], terms[0]).alias("mismatch"))


def bottom_sample(rows: DataFrame, b: int, seed: int = 42, length_hours: int = 24) -> DataFrame:
    """A uniform sample of b events per window of time, in stateful batches: the state is the b least hashes seen."""
    ship(rows.sparkSession)
    schema = "hour_bucket long, event_id long, h double"
    state = "ids array<long>, hs array<double>"

    def work(key, frames, saved):
        ids, hs = (list(v) for v in saved.get) if saved.exists else ([], [])
        for pdf in frames:
            for e in pdf.event_id:
                h = py_uniform("s", seed, int(e))
                ids.append(int(e))
                hs.append(h)
        order = sorted(set(zip(hs, ids, strict=True)))[:b]
        saved.update(([i for _, i in order], [h for h, _ in order]))
        yield pd.DataFrame({"hour_bucket": [int(key[0])] * len(order), "event_id": [i for _, i in order], "h": [h for h, _ in order]})

    bucket = F.floor(F.unix_timestamp("ts") / (3600 * length_hours)).cast("long")
    keyed = rows.withColumn("hour_bucket", bucket).groupBy("hour_bucket")
    return keyed.applyInPandasWithState(work, schema, state, "update", "NoTimeout")
