"""Tables written to the folder that the cluster shares, and the places of it.

Intermediate results that are read more than once are written as Parquet under ``spark.checkpoint.dir``; they
survive the loss of an executor and cut the lineage of what follows.
"""

from __future__ import annotations

import atexit
import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

from ..session import ship  # noqa: F401  for the operators

_written: list[tuple[SparkSession, str]] = []
_places: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """URI of the folder in ``spark.checkpoint.dir``. Where that is unset, a local master gets a folder of its own; on a cluster,
    whose machines would not see each other's files there, it is an error."""
    app = spark.sparkContext.applicationId
    if app not in _places:
        there = spark.conf.get("spark.checkpoint.dir", None)
        if not there:
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
            there = "file://" + tempfile.mkdtemp(prefix="fsketch-")
            spark.sparkContext.setCheckpointDir(there)
        path = spark._jvm.org.apache.hadoop.fs.Path(there)
        uri = path.getFileSystem(spark._jsc.hadoopConfiguration()).makeQualified(path).toUri().toString().rstrip("/")
        _places[app] = "file:///" + uri[6:].lstrip("/") if uri.startswith("file:/") else uri
    return _places[app]


def new_path(spark: SparkSession, tag: str) -> str:
    path = f"{shared_dir(spark)}/fsketch-{uuid.uuid4().hex[:12]}-{tag}"
    _written.append((spark, path))
    return path


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` once to the shared folder and return the table read back.

    The driver then collects its garbage, so that Spark drops the shuffle files of what has just been written.
    """
    spark = df.sparkSession
    path = new_path(spark, tag)
    df.write.option("compression", "zstd").parquet(path)
    schema = df.schema
    del df
    gc.collect()
    spark._jvm.System.gc()
    return spark.read.schema(schema).parquet(path)


def release() -> None:
    """Delete the tables written so far; call it when no DataFrame over them is needed any more."""
    while _written:
        spark, path = _written.pop()
        try:
            target = spark._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
        except Exception:  # noqa: BLE001  the session may have ended already
            return


atexit.register(release)
