"""Cutting lineage between the rounds of iterative plans, and sizes that decide how a plan is built."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def ready(spark: SparkSession) -> SparkSession:
    """Set the checkpoint folder: the cluster's ``spark.checkpoint.dir``, or a temporary one in local tests."""
    if spark.sparkContext.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not spark.sparkContext.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
            folder = tempfile.mkdtemp(prefix="dagframe-")
        spark.sparkContext.setCheckpointDir(folder)
    return spark


def cut(frame: DataFrame) -> DataFrame:
    """The same rows behind a reliable checkpoint, which survives lost executors."""
    ready(frame.sparkSession)
    return frame.checkpoint()


def small(frame: DataFrame, most: int) -> DataFrame:
    """``frame`` with a broadcast hint if it has at most ``most`` rows (counted), else as it is."""
    return F.broadcast(frame) if frame.limit(most + 1).count() <= most else frame
