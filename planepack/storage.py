"""Intermediate tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows that a broadcast side may have; beyond it the join shuffles.
BROADCAST_ROWS = 1_000_000
#: Paths written by this process and not yet deleted.
_made: list[str] = []


def scratch(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``, or the one set on the context.

    Without either a session on one machine (tests) gets a folder of its own, deleted when the process ends; a cluster has to name one.
    """
    sc = spark.sparkContext
    where = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not where:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        where = tempfile.mkdtemp(prefix="planepack-")
        atexit.register(shutil.rmtree, where, True)
        sc.setCheckpointDir(where)
    return where.rstrip("/")


def fresh(spark: SparkSession, what: str) -> str:
    path = f"{scratch(spark)}/pp-{what}-{uuid.uuid4().hex}"
    _made.append(path)
    return path


def written(df: DataFrame, what: str) -> DataFrame:
    """Write as Parquet and read back: computed once, lineage cut, survives lost executors."""
    path = fresh(df.sparkSession, what)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._pp_path = path
    return out


def delete(spark: SparkSession, path: str) -> None:
    """Delete a folder on whatever file system it is."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    with contextlib.suppress(ValueError):
        _made.remove(path)


def forget(df: DataFrame) -> None:
    """Delete the files behind a table made by :func:`written`."""
    delete(df.sparkSession, df._pp_path)


@contextlib.contextmanager
def passing(spark: SparkSession, keep: list[str]):
    """Delete, at the end, all that was written inside, but for the paths in ``keep``."""
    before = set(_made)
    yield
    for path in [p for p in _made if p not in before and p not in keep]:
        delete(spark, path)


def clear(spark: SparkSession) -> None:
    """Delete everything this process has written to the shared folder; results that are still lazy lose their input."""
    for path in list(_made):
        delete(spark, path)


def small(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast hint behind a check of the row count; otherwise a shuffle join is left to Catalyst."""
    return F.broadcast(df) if rows <= limit else df
