"""Readers and writers. Schemas are given, never inferred, for everything but Parquet and ORC."""

from __future__ import annotations

import atexit
import json
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

FORMATS = ("parquet", "orc", "json", "csv", "text")


_scratch: list[tuple[SparkSession, str]] = []


def scratch(spark: SparkSession, tag: str) -> str:
    """A new path in the folder that driver and executors share, deleted when the driver ends. A local master that names no such
    folder gets one of its own."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        one_process = spark.sparkContext.master.split("[")[0] == "local"
        root = "file://" + tempfile.mkdtemp(prefix="fsketch-") if one_process else spark.conf.get("spark.sql.warehouse.dir")
    path = f"{root}/fsketch-{uuid.uuid4().hex[:12]}-{tag}"
    _scratch.append((spark, path))
    return path


def drop(spark: SparkSession, path: str) -> None:
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _drop_all() -> None:
    while _scratch:
        try:
            drop(*_scratch.pop())
        except Exception:  # noqa: BLE001  the session may have ended already
            return


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema=None, **options) -> DataFrame:
    if kind not in FORMATS:
        raise ValueError(f"format must be one of {FORMATS}")
    reader = spark.read.options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    elif kind in ("json", "csv"):
        raise ValueError("json and csv need a schema: inferring it would read the data twice")
    return reader.format(kind).load(path)


def stream(spark: SparkSession, path: str, schema, kind: str = "parquet", **options) -> DataFrame:
    return spark.readStream.schema(schema).options(**options).format(kind).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "errorifexists", **options) -> None:
    writer = df.write.mode(mode).options(**options).format(kind)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_model(spark: SparkSession, path: str, result) -> None:
    """Centroids, scaling and settings of a run as one JSON line, through Spark's own file systems."""
    card = {
        "centroids": result.centroids.tolist(), "centroids_original": result.centroids_original.tolist(), "columns": list(result.scaler.cols),
        "mean": result.scaler.mean.tolist(), "std": result.scaler.std.tolist(), "sse": result.sse, "params": {k: str(v) for k, v in result.params.items()},
    }
    spark.createDataFrame([(json.dumps(card),)], "value string").coalesce(1).write.text(path)


def read_model(spark: SparkSession, path: str) -> dict:
    return json.loads(spark.read.text(path).first()[0])
