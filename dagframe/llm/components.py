"""Connected components of a graph given as an edge table, by alternating stars.

Each round joins every node with the smallest node it can see, first for its larger, then for its smaller
neighbours; the edges shrink towards one star per component. A hub's neighbours are never gathered in one row:
each half round is a grouped minimum (partial sums before the shuffle) and a join that adaptive execution may split.
Rounds grow with the logarithm of the longest path, each ends in ``checkpoint()``, so lost executors cost one round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dagframe.llm.common import with_checkpoints


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.join(least, "u").where("v > u and v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v"))).distinct()


def _state(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.sum(F.col("v").cast("decimal(38,0)"))).first())


def components(edges: DataFrame, a: str = "a", b: str = "b", rounds: int = 60) -> DataFrame:
    """Component of every node that has an edge: ``(id, component)``, the component being its smallest id.

    Loops, repeated edges, either direction and nulls (dropped) are allowed; no edges give an empty table.
    """
    spark = with_checkpoints(edges.sparkSession)
    now = (
        edges.where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col(a) != F.col(b)))
        .select(F.greatest(a, b).cast("long").alias("u"), F.least(a, b).cast("long").alias("v"))
        .distinct()
        .checkpoint()
    )
    before = _state(now)
    for _ in range(rounds if before[0] else 0):
        now = _small_star(_large_star(now)).checkpoint()
        state = _state(now)
        if state == before:
            break
        before = state
    else:
        if before[0]:
            raise RuntimeError(f"components still move after {rounds} rounds")
    return now.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(now.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())
