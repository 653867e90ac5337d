"""Tables written once to the shared folder, where lineage has to be cut."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_STAGED: list[tuple[SparkSession, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; a temporary folder only on a single machine where none is set."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="winsub-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def staged_folder(spark: SparkSession) -> str:
    """A new folder's path below the shared folder; ``drop_staged`` deletes it."""
    path = f"{shared_folder(spark)}/winsub-{uuid.uuid4().hex}"
    _STAGED.append((spark, path))
    return path


def staged(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` below the shared folder and scan what was written."""
    path = f"{staged_folder(df.sparkSession)}/{tag}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop_staged() -> None:
    """Delete every staged folder of this process (also at exit)."""
    while _STAGED:
        spark, path = _STAGED.pop()
        try:
            target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
        except Exception:  # the JVM is already gone
            return


atexit.register(drop_staged)
