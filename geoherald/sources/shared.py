"""Tables written to the folder that all executors share, to cut lineage."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``; a folder of this machine only where it names none, as in tests."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        folder = f"file://{tempfile.mkdtemp(prefix='geoherald-')}"
        spark.sparkContext.setCheckpointDir(folder)
    return folder


#: Spark's setting by which the shuffle files of a query go when it ends, and not when the driver collects its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def settle(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` in the shared folder and return a DataFrame that reads it. Nothing reads the shuffle files of the
    write again, so they go with it."""
    return settle_parts([df], label)


def settle_parts(parts: Iterable[DataFrame], label: str) -> DataFrame:
    """Write parts with the same columns one after another to one table, as :func:`settle`: the shuffle files of a part
    go before those of the next come."""
    path, df = None, None
    for df in parts:
        spark = df.sparkSession
        path = path or f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
        before = spark.conf.get(CLEANUP)
        spark.conf.set(CLEANUP, "true")
        try:
            df.write.mode("append").option("compression", "zstd").parquet(path)
        finally:
            spark.conf.set(CLEANUP, before)
    return df.sparkSession.read.schema(df.schema).parquet(path)
