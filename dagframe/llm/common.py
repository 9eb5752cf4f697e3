"""Small helpers that the operators of this subpackage share."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, the only characters at which the operators split words or trim lines.
ASCII_SPACE = " \t\n\x0b\x0c\r"
BATCH_ROWS = 1000
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, through Spark's own reader (the folder may be remote)."""
    return with_checkpoints(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def with_checkpoints(spark: SparkSession) -> SparkSession:
    """Make ``checkpoint()`` usable: the cluster's shared folder, or a temporary one in local tests only.

    Rows here are whole documents, so the batches that go to Python are kept to BATCH_ROWS rows (a session setting).
    """
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "10000")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not context.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
            folder = tempfile.mkdtemp(prefix="dagframe-checkpoints-")
        context.setCheckpointDir(folder)
    return spark


def partitions_of(spark: SparkSession) -> int:
    """The session's number of shuffle partitions, which the cluster's owner sizes for the data."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only; every other character stays, so no locale or Unicode version matters."""
    return F.translate(text, UPPER, UPPER.lower())


def same_spans(x: np.ndarray, at: np.ndarray, y: np.ndarray, there: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether ``x[at : at + size]`` equals ``y[there : there + size]``, for each of many spans."""
    total, whole = int(size.sum()), np.ones(len(size), dtype=bool)
    if not total:
        return whole
    past = np.cumsum(size) - size
    step = np.arange(total) - np.repeat(past, size)
    differ = x[np.repeat(at, size) + step] != y[np.repeat(there, size) + step]
    if differ.any():
        whole[np.repeat(np.arange(len(size)), size)[differ]] = False
    return whole


def release() -> None:
    """Hand a Python worker's unused memory back to its executor, at the end of a task: workers stay, and share a limit."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # only where the C library has it
        ctypes.CDLL(None).malloc_trim(0)


def fresh(name: str, taken: list[str]) -> str:
    """A column name that is not in use, for helper columns beside a caller's own ones."""
    low = {x.lower() for x in taken}
    while name.lower() in low:
        name += "_"
    return name
