"""Tables that cut lineage: written once to the folder that the cluster shares, and read again."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_roots: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """A folder of this application below spark.checkpoint.dir. Where that is unset, a local one for a local master (tests),
    and an error on a cluster, whose executors could not read it."""
    app = spark.sparkContext.applicationId
    if app not in _roots:
        base = spark.conf.get("spark.checkpoint.dir", "") or ""
        if not base:
            held = spark.sparkContext._jsc.sc().getCheckpointDir()
            if not held.isDefined() and not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            base = held.get() if held.isDefined() else f"file://{tempfile.mkdtemp(prefix='progressive-runs-')}"
        _roots[app] = f"{base.rstrip('/')}/progressive-runs-{app}"
        atexit.register(_drop, spark, _roots[app])
    return _roots[app]


def _drop(spark: SparkSession, path: str) -> None:
    try:
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session may have ended before the interpreter does
        pass


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"


def saved(df: DataFrame, name: str, partition_by: str | None = None, options: dict[str, str] | None = None) -> DataFrame:
    path = new_path(df.sparkSession, name)
    writer = df.write.options(**(options or {}))
    (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
