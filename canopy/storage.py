"""Tables written to the folder that the driver and all executors share.

Iterative and reused results are cut from their lineage by writing them as
Parquet there. Such files outlive executors, unlike cached blocks.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

_written: dict[str, list[str]] = {}
_kept: dict[tuple, tuple] = {}


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session, or a folder in its warehouse, which all executors share as well."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    return (folder or f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_canopy").rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    _written.setdefault(spark.sparkContext.applicationId, []).append(path)
    return path


def stage(df: DataFrame, name: str = "stage", compression: str = "snappy") -> DataFrame:
    """Write ``df`` to the shared folder and return the table read back."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.option("compression", compression).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.staged_at = path
    return out


def stored_bytes(df: DataFrame) -> int:
    """The size of a table that ``stage`` has written; 0 for any other."""
    path = getattr(df, "staged_at", None)
    if path is None:
        return 0
    target = df.sparkSession.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return int(target.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).getContentSummary(target).getLength())


def changed_at(spark: SparkSession, path: str) -> int:
    """When a file or folder was last changed."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(target).getModificationTime()


def kept(spark: SparkSession, name: str, sources: list[str], make: Callable[[], DataFrame]) -> DataFrame:
    """``make()`` as a written table, made once for an application and the same unchanged sources."""
    key = (spark.sparkContext.applicationId, name, tuple((s, changed_at(spark, s)) for s in sources))
    if key not in _kept:
        df = make()
        path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        df.write.parquet(path)
        _kept[key] = (path, df.schema)
    path, schema = _kept[key]
    return spark.read.schema(schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def clear(spark: SparkSession) -> int:
    """Delete every folder this application has staged; call once results are out. Kept tables stay."""
    paths = _written.pop(spark.sparkContext.applicationId, [])
    for path in paths:
        remove(spark, path)
    return len(paths)
