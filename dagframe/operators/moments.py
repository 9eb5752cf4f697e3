"""Second moments of sample matrices: one pass over the data, then learning without it.

``MOMENTS(a, b, c)`` with a <= b holds means of products. Partial sums are made where the rows are; what is shuffled has the
size of the result, not of the data.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def from_wide(frame: DataFrame, columns: list[str]) -> DataFrame:
    """``(a, b, c)`` of up to some dozens of double columns, as one aggregate."""
    pairs = [(i, j) for i in range(len(columns)) for j in range(i, len(columns))]
    sums = frame.agg(*[F.avg(F.col(columns[i]) * F.col(columns[j])).alias(f"m{i}_{j}") for i, j in pairs])
    return sums.select(F.explode(F.array(*[F.struct(F.lit(i).alias("a"), F.lit(j).alias("b"), F.col(f"m{i}_{j}").alias("c")) for i, j in pairs])).alias("x")).select("x.*")


def from_cells(cells: DataFrame, n: int | None = None, chunk: int = 256) -> DataFrame:
    """``(a, b, c)`` of ``CELLS(sample_id, node_id, x)``; absent cells are zero; n: number of samples (default: those with cells).

    Cells of a sample meet in pairs of chunks, so one very long sample is spread over many rows and tasks.
    """
    total = n if n is not None else cells.select("sample_id").distinct().count()
    part = F.pmod(F.hash("node_id"), F.lit(16))
    sizes = cells.groupBy("sample_id").agg(F.count("*").alias("k"))
    dealt = cells.join(sizes, "sample_id").withColumn("part", F.when(F.col("k") > chunk, part).otherwise(F.lit(0))).select("sample_id", "part", "node_id", "x", (F.col("k") > chunk).alias("cut"))
    left = dealt.select("sample_id", F.col("part").alias("p"), F.explode(F.when(F.col("cut"), F.sequence(F.lit(0), F.lit(15))).otherwise(F.array(F.lit(0)))).alias("q"), F.col("node_id").alias("a"), F.col("x").alias("xa"))
    right = dealt.select("sample_id", F.explode(F.when(F.col("cut"), F.sequence(F.lit(0), F.lit(15))).otherwise(F.array(F.lit(0)))).alias("p"), F.col("part").alias("q"), F.col("node_id").alias("b"), F.col("x").alias("xb"))
    both = left.join(right, ["sample_id", "p", "q"]).where("a <= b")
    return both.groupBy("a", "b").agg((F.sum(F.col("xa") * F.col("xb")) / F.lit(float(max(1, total)))).alias("c"))


def from_vectors(frame: DataFrame, vector: str, block: int = 512) -> DataFrame:
    """``(a, b, c)`` of array columns, by partial matrix products per task and a grouped sum of blocks."""

    def partial(batches):
        total, n = None, 0
        for b in batches:
            x = np.array(b.column(0).to_pylist(), dtype=np.float64)
            if len(x):
                total = x.T @ x if total is None else total + x.T @ x
                n += len(x)
        if total is not None:
            d = len(total)
            for i in range(0, d, block):
                for j in range(i, d, block):
                    part = total[i : i + block, j : j + block]
                    yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([j], pa.int32()), pa.array([part.shape[1]], pa.int32()), pa.array([n], pa.int64()), pa.array([part.ravel().tolist()], pa.list_(pa.float64()))], ["i", "j", "w", "n", "v"])

    blocks = frame.where(F.col(vector).isNotNull()).select(vector).mapInArrow(partial, "i int, j int, w int, n long, v array<double>")
    cells = blocks.select("i", "j", "w", "n", F.posexplode("v").alias("p", "v")).select((F.col("i") + F.floor(F.col("p") / F.col("w"))).cast("int").alias("a"), (F.col("j") + F.col("p") % F.col("w")).cast("int").alias("b"), "v", "n").where("a <= b")
    return cells.groupBy("a", "b").agg((F.sum("v") / F.sum("n")).alias("c"))


def by_pane(records: DataFrame, pane: str = "pane", active: str = "active") -> DataFrame:
    """``(pane, a, b, s)``: sums of products of indicators, pane by pane; ``active`` is each record's array of nodes."""
    return records.select(pane, F.explode(active).alias("a"), F.col(active)).select(pane, "a", F.explode(active).alias("b")).where("a <= b").groupBy(pane, "a", "b").agg(F.count("*").cast("double").alias("s"))


def to_matrix(moments: DataFrame, d: int) -> np.ndarray:
    """A symmetric matrix on the driver; for d up to a few thousand."""
    if d > 5000:
        raise ValueError("too many nodes for one matrix")
    c = np.zeros((d, d))
    rows = moments.select(F.col("a").cast("int"), F.col("b").cast("int"), "c").toArrow()
    a, b, v = (rows.column(k).to_numpy() for k in range(3))
    c[a, b] = v
    c[b, a] = v
    return c
