"""Shared scratch storage: where iterative plans cut their lineage.

Executors may be lost at any time, so intermediate results that later jobs depend on are
written as Parquet to the folder the cluster names in ``spark.checkpoint.dir``; a lost
executor then costs a task retry, never a failed read.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_LOCAL_DEFAULT: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared scratch folder; a temporary one only in local mode, where none is configured.

    A cluster without the setting is an error: its executors do not share a machine's temporary folder.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir names no shared folder")
    app = spark.sparkContext.applicationId
    if app not in _LOCAL_DEFAULT:
        _LOCAL_DEFAULT[app] = "file://" + tempfile.mkdtemp(prefix="groupflow-")
    return _LOCAL_DEFAULT[app]


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str = "stage") -> DataFrame:
    """Write ``df`` once to shared storage and return a scan of it (lineage is cut)."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.mode("overwrite").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


_LISTED = 2_000_000


def listed(ids: DataFrame, most: int = _LISTED) -> DataFrame:
    """Distinct ``ids``, a table on storage, as the side of a semi or anti join that is sent to the other one, so that rows with whole
    texts stay where they are. Over ``most`` of them the join moves both sides, with the same result."""
    return F.broadcast(ids) if ids.limit(most + 1).count() <= most else ids


def release_path(spark: SparkSession, path: str) -> None:
    """Delete a folder of shared storage, if it is there."""
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def release(*frames: DataFrame | None) -> None:
    """Delete scratch tables made by :func:`materialize` that no later plan reads."""
    for df in frames:
        path = getattr(df, "_scratch_path", None)
        if path:
            release_path(df.sparkSession, path)
