"""Tables that a plan writes on its way, in the folder that all executors share."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession, kind: str = "stream") -> str:
    """A new folder under the one that the session names for checkpoints.

    If it names none, a session on one machine gets a temporary folder and any
    other a folder of the warehouse, which all executors share.
    """
    base = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        local = spark.sparkContext.master.startswith("local")
        base = os.path.join(tempfile.gettempdir() if local else spark.conf.get("spark.sql.warehouse.dir"), "warpspan-tables")
    return f"{base.rstrip('/')}/{kind}-{uuid.uuid4().hex}"


def stored(frame: DataFrame) -> DataFrame:
    """The same rows, written once and read again: a lost executor computes none of them anew."""
    place = shared_folder(frame.sparkSession, "table")
    frame.write.parquet(place)
    return frame.sparkSession.read.schema(frame.schema).parquet(place)
