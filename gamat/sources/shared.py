"""The folder for intermediate tables and checkpoints that all executors share."""

from __future__ import annotations

import re
import tempfile

from pyspark.sql import SparkSession


class NoSharedFolder(RuntimeError):
    """A cluster that names no folder which all of its executors share."""


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir. Where it is unset, a temporary folder serves a local master (tests); a cluster is refused."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        master = spark.conf.get("spark.master", "")
        if not re.fullmatch(r"local(\[.*\])?", master):
            raise NoSharedFolder(f"set spark.checkpoint.dir to a folder that all executors of {master} share")
        folder = shared_folder.__dict__.setdefault("own", "file://" + tempfile.mkdtemp(prefix="gamat-"))
    return folder.rstrip("/")


def reliable(df):
    """Checkpoint in the shared folder."""
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint()
