"""Intermediate tables in the folder that all executors share.

Lineage is cut by writing a table under ``spark.checkpoint.dir`` and reading it back, so a lost
executor costs a re-read and nothing more. The folder is set here only where the session has none.
"""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_written: list[tuple[SparkSession, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """The session's shared folder; a local one only where none is configured (tests, one machine)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        found = f"file://{tempfile.mkdtemp(prefix='geoherald-')}"
        spark.sparkContext.setCheckpointDir(found)
    return found


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _sweep() -> None:
    while _written:
        spark, path = _written.pop()
        try:
            _remove(spark, path)
        except Exception:  # the session may be gone by now; the folder is then the cluster's to clean
            return


def store(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as a compressed table in the shared folder and return a DataFrame that reads it."""
    return stored(df, label)[0]


def stored(df: DataFrame, label: str) -> tuple[DataFrame, str]:
    """As :func:`store`, with the path, for tables that :func:`discard` removes early."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/scratch-{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path), path


def discard(spark: SparkSession, *paths: str) -> None:
    """Remove tables that nothing reads any more."""
    for path in paths:
        _remove(spark, path)
        _written[:] = [x for x in _written if x[1] != path]


def unused(name: str, columns: list[str]) -> str:
    """``name``, made longer until it is none of ``columns``, whatever their case."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name += "_"
    return name


def join_frequent(rows: DataFrame, table: DataFrame, key: str, frequent: Column) -> DataFrame:
    """``rows`` joined with ``table``, which has one row per key; the rows of ``table`` that are ``frequent``, of
    which there must be a bounded number, are broadcast, so that a hot key's rows stay where they are."""
    hot = F.broadcast(table.filter(frequent))
    return rows.join(hot, key).union(rows.join(hot, key, "left_anti").join(table.filter(~frequent), key))
