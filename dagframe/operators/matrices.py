"""Sample matrices from tables: ``CELLS(sample_id, node_id, x)`` with absent cells as zero, and ``NODES(node_id, label, kind)``."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dagframe.plans.lineage import cut


def consolidate(cells: DataFrame, how: str = "sum") -> DataFrame:
    """One row per sample and node: the sum or mean of repeated cells."""
    if how not in ("sum", "avg"):
        raise ValueError("how is sum or avg")
    return cells.groupBy("sample_id", "node_id").agg((F.sum if how == "sum" else F.avg)("x").alias("x"))


def centre_by_sample(cells: DataFrame) -> DataFrame:
    """Every value less its sample's mean over its own cells; samples are one shuffle."""
    return cells.withColumn("x", F.col("x") - F.avg("x").over(Window.partitionBy("sample_id")))


def standardise(frame: DataFrame, columns: list[str], with_mean: bool = True, with_std: bool = True) -> DataFrame:
    """Wide columns with mean 0 and deviation 1; a constant column becomes 0. One row of statistics goes to all tasks."""
    stats = frame.agg(*[f(c).alias(f"{n}_{c}_") for c in columns for n, f in (("mean", F.avg), ("dev", F.stddev_pop))])
    value = lambda c: (F.col(c) - (F.col(f"mean_{c}_") if with_mean else F.lit(0.0))) / (F.when(F.col(f"dev_{c}_") > 0, F.col(f"dev_{c}_")).otherwise(1.0) if with_std else F.lit(1.0))
    return frame.crossJoin(F.broadcast(stats)).select(*[value(c).alias(c) if c in columns else F.col(c) for c in frame.columns])


def long_of(frame: DataFrame, sample_id: str, columns: list[str]) -> DataFrame:
    """CELLS of wide columns, numbered in the order given; zeros and nulls are left out."""
    each = F.explode(F.array(*[F.struct(F.lit(i).alias("node_id"), F.col(c).cast("double").alias("x")) for i, c in enumerate(columns)])).alias("c")
    return frame.select(F.col(sample_id).alias("sample_id"), each).select("sample_id", "c.node_id", "c.x").where("x <> 0")


def from_arrays(frame: DataFrame, sample_id: str, vector: str) -> DataFrame:
    """CELLS of an array column."""
    return frame.select(F.col(sample_id).alias("sample_id"), F.posexplode(vector).alias("node_id", "v")).select("sample_id", "node_id", F.col("v").cast("double").alias("x")).where("x <> 0")


def dictionary(labels: DataFrame, kind: str, min_support: int = 1, max_support: int | None = None, once: bool = False) -> DataFrame:
    """NODES of ``(sample_id, label)``, each label counted once a sample, numbered by label; ``once``: no row is there twice, so
    counts alone are shuffled.

    Numbers come from counts by hash range, so no task sees all labels.
    """
    own = labels.select("sample_id", "label")
    n = (own if once else own.distinct()).groupBy("label").agg(F.count("*").alias("support"))
    kept = n.where((F.col("support") >= min_support) & (F.col("support") <= max_support if max_support else F.lit(True)))
    return numbered(kept.select("label", "support"), "label").withColumn("kind", F.lit(kind)).select(F.col("number").alias("node_id"), "label", "kind", "support")


def numbered(frame: DataFrame, order: str, ranges: int = 64) -> DataFrame:
    """``frame`` with ``number`` from 0 in the order of a column: rows are numbered within ranges, ranges by their sizes."""
    frame = cut(frame)
    n = frame.count()
    if n <= 100_000:
        return frame.withColumn("number", (F.row_number().over(Window.orderBy(order)) - 1).cast("int"))
    cuts = [r[order] for r in frame.select(order).orderBy(F.xxhash64(order)).limit(ranges * 32).orderBy(order).collect()][16::32]
    bounds = F.array(*[F.lit(c) for c in cuts])
    part = frame.withColumn("part_", F.size(F.filter(bounds, lambda c: c <= F.col(order))))
    sizes = part.groupBy("part_").agg(F.count("*").alias("n_")).withColumn("before_", F.sum("n_").over(Window.orderBy("part_")) - F.col("n_")).drop("n_")
    own = F.row_number().over(Window.partitionBy("part_").orderBy(order)) - 1
    return part.withColumn("own_", own).join(F.broadcast(sizes), "part_").withColumn("number", (F.col("own_") + F.col("before_")).cast("int")).drop("part_", "own_", "before_")


def indicators(frame: DataFrame, sample_id: str, columns: dict[str, str], min_support: int = 1) -> tuple[DataFrame, DataFrame]:
    """(CELLS of ones, NODES) of categorical columns: ``columns`` maps a column to its prefix; nulls are no node."""
    each = F.explode(F.array(*[F.struct(F.concat(F.lit(prefix + "="), F.col(c).cast("string")).alias("label"), F.lit(prefix).alias("kind")) for c, prefix in columns.items()])).alias("x")
    labels = frame.select(F.col(sample_id).alias("sample_id"), each).select("sample_id", "x.label", "x.kind").where("label is not null")
    nodes = dictionary(labels, "", min_support).withColumn("kind", F.substring_index("label", "=", 1))
    cells = labels.join(nodes.select("label", "node_id"), "label").select("sample_id", "node_id", F.lit(1.0).alias("x")).distinct()
    return cells, nodes


def tokens(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``(sample_id, label)``: the distinct white-space words of each text."""
    return docs.select(F.col(doc_id).alias("sample_id"), F.explode(F.array_distinct(F.split(F.trim(text), r"\s+"))).alias("label")).where("label <> ''")


def union_nodes(*parts: tuple[DataFrame, DataFrame]) -> tuple[DataFrame, DataFrame]:
    """(CELLS, NODES) of several ones over the same samples, labels told apart by kind and numbered anew."""
    named = None
    for cells, nodes in parts:
        one = cells.join(nodes.select("node_id", F.concat_ws("=", "kind", "label").alias("label"), "kind"), "node_id").select("sample_id", "label", "kind", "x")
        named = one if named is None else named.unionByName(one)
    nodes = numbered(named.select("label", "kind").distinct(), "label").select(F.col("number").alias("node_id"), "label", "kind")
    return named.join(nodes.select("label", "node_id"), "label").select("sample_id", "node_id", "x"), nodes
