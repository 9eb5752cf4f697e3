"""Reading runs out over a grid of stop tolerances and filters, the best cell, and summaries of replicates."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dagframe.operators import metrics


def read_out(snapshots: DataFrame, truth: DataFrame, d: int, taus: tuple[float, ...] = (0.1, 0.2, 0.3, 0.4, 0.5)) -> DataFrame:
    """``(eps, tau, counts and measures)`` of ``snapshots(eps, src, dst, w)`` against truth, every filter at once.

    Cells in which nothing is predicted are there too.
    """
    spark = snapshots.sparkSession
    tau = spark.createDataFrame([(t,) for t in taus], "tau double")
    kept = snapshots.join(F.broadcast(tau), F.abs("w") >= F.col("tau")).select("eps", "tau", "src", "dst", "w")
    cells = snapshots.select("eps").distinct().join(F.broadcast(tau))
    return metrics.measures(metrics.edge_confusion(cells.join(truth.select("src", "dst")), kept, "eps", "tau").withColumn("d", F.lit(d)))


def best_cell(results: DataFrame, *by: str) -> DataFrame:
    """The row with the highest F1 of each group; of equals the loosest tolerance and the smallest filter."""
    order = Window.partitionBy(*by).orderBy(F.desc("f1"), F.desc("eps"), "tau")
    return results.withColumn("nth_", F.row_number().over(order)).where("nth_ = 1").drop("nth_")


def summarise(results: DataFrame, *by: str, measures: tuple[str, ...] = ("f1", "shd")) -> DataFrame:
    """Mean and deviation of each measure over replicates."""
    return results.groupBy(*by).agg(F.count("*").alias("runs"), *[x for m in measures for x in (F.avg(m).alias(f"{m}_mean"), F.stddev_pop(m).alias(f"{m}_dev"))])


def cube(results: DataFrame, *by: str, measure: str = "f1") -> DataFrame:
    """Means over every combination of the groups, with totals as nulls."""
    return results.cube(*by).agg(F.avg(measure).alias(f"{measure}_mean"), F.count("*").alias("runs"))
