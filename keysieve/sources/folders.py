"""Where the cluster shares files."""

from __future__ import annotations

import uuid

from pyspark.sql import SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder that the session names in spark.checkpoint.dir or by its checkpoint directory.

    A folder of one machine would be lost with it and is read by no other, so it is taken only where all tasks
    run inside the driver.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        option = spark.sparkContext._jsc.sc().getCheckpointDir()
        if option.isDefined():
            return option.get().rstrip("/")
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the cluster shares")
        import tempfile

        found = tempfile.mkdtemp(prefix="keysieve-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def shared_dir(spark: SparkSession) -> str:
    """A new folder in the shared one."""
    return f"{shared_root(spark)}/keysieve/{uuid.uuid4().hex}"
