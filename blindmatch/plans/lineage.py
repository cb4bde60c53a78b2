"""Written tables in the cluster's shared folder: they cut lineage between rounds."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_FALLBACK: list[str] = []


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path below ``spark.checkpoint.dir``; below a temporary folder only where that is unset and one process has driver and executors."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        if not _FALLBACK:
            _FALLBACK.append("file://" + tempfile.mkdtemp(prefix="blindmatch-"))
        root = _FALLBACK[0]
    return f"{root.rstrip('/')}/linkage/{name}-{uuid.uuid4().hex[:12]}"


def cut(df: DataFrame, name: str = "round") -> DataFrame:
    """Write ``df`` and read it back; a lost executor then costs the tasks after this point only."""
    path = shared_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
