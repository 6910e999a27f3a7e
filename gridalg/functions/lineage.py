"""Cuts of lineage that outlive lost executors, for loops and for codes that must not change between two reads."""

from __future__ import annotations

import atexit
import shutil
import tempfile

from pyspark.sql import DataFrame


def cut(df: DataFrame) -> DataFrame:
    """df written to the shared checkpoint folder and read back.

    The folder is the session's spark.checkpoint.dir. Only a local session without one gets a folder of its own, which
    goes when the driver ends; on a cluster that is an error, as executors would not see each other's files.
    """
    sc = df.sparkSession.sparkContext
    if not sc.getConf().get("spark.checkpoint.dir") and sc._jsc.sc().getCheckpointDir().isEmpty():
        if not sc.master.startswith("local[") and sc.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        own = tempfile.mkdtemp(prefix="checkpoints-")
        atexit.register(shutil.rmtree, own, ignore_errors=True)
        sc.setCheckpointDir(own)
    return df.checkpoint()
