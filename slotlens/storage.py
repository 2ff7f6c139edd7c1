"""Shared storage of the session, used to cut lineage of loops."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame


def written(df: DataFrame) -> DataFrame:
    """Writes to the folder of spark.checkpoint.dir and reads back; an own folder only where none is set and all runs in one process."""
    spark = df.sparkSession
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        if current.isDefined():
            folder = current.get()
        elif not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        else:
            folder = f"file://{tempfile.mkdtemp(prefix='slotlens-')}"
            spark.sparkContext.setCheckpointDir(folder)
    path = f"{folder}/slotlens/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
