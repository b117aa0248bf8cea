"""Session helpers that work with the session as given."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def ship(spark: SparkSession) -> None:
    """Send this package to the Python workers, once a context, so that they need no copy of it."""
    sc = spark.sparkContext
    if getattr(sc, "_vecrag_shipped", False):
        return
    top = Path(__file__).resolve().parent
    target = os.path.join(tempfile.mkdtemp(prefix="vecrag"), "vecrag.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for f in sorted(top.rglob("*.py")):
            z.write(f, str(Path("vecrag") / f.relative_to(top)))
    sc.addPyFile(target)
    sc._vecrag_shipped = True


def checkpoint_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir. Where that is unset, a single machine gets one of its own; a cluster must name one."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not sc.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="ckpt"))
    return sc.getCheckpointDir()


def shared_folder(spark: SparkSession) -> str:
    """A new folder in the shared one, for tables that a job writes and reads again."""
    return f"{checkpoint_folder(spark)}/{uuid.uuid4().hex}"


def checkpointed(df: DataFrame) -> DataFrame:
    """Make a small, often used table once: its rows go to the shared folder of spark.checkpoint.dir."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint(eager=True)
