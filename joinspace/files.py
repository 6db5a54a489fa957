"""Where written tables go that cut lineage."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import SparkSession


def written_folder(spark: SparkSession, kind: str) -> str:
    """A new path below spark.checkpoint.dir, which all executors see. Only a local master may go without that setting: elsewhere a folder
    of this machine would not be seen by others."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors see")
        base = tempfile.gettempdir()
    return f"{base.rstrip('/')}/{kind}-{uuid.uuid4().hex}"
