"""Least-squares loss with an L1 term, its gradient, and the Gaussian likelihood, from samples or from moments."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def both_ways(moments: DataFrame) -> DataFrame:
    """Moments for either order of a pair."""
    return moments.select("a", "b", "c").unionByName(moments.where("a <> b").select(F.col("b").alias("a"), F.col("a").alias("b"), "c"))


def residuals(cells: DataFrame, edges: DataFrame) -> DataFrame:
    """``(sample_id, node_id, r)``: each value less its parents' combination; absent cells are zero."""
    predicted = cells.join(edges, cells["node_id"] == edges["src"]).groupBy("sample_id", F.col("dst").alias("node_id")).agg(F.sum(F.col("x") * F.col("w")).alias("y"))
    return cells.join(predicted, ["sample_id", "node_id"], "full").select("sample_id", "node_id", (F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0))).alias("r"))


def from_samples(cells: DataFrame, edges: DataFrame, n: int, lam: float = 0.1) -> DataFrame:
    """``(fit, penalty, loss)`` in one row; fit is the sum of squared residuals over n."""
    fit = residuals(cells, edges).agg((F.coalesce(F.sum(F.col("r") * F.col("r")), F.lit(0.0)) / n).alias("fit"))
    penalty = edges.agg((lam * F.coalesce(F.sum(F.abs("w")), F.lit(0.0))).alias("penalty"))
    return fit.crossJoin(penalty).withColumn("loss", F.col("fit") + F.col("penalty"))  # one row each


def gradient_from_samples(cells: DataFrame, edges: DataFrame, n: int, lam: float = 0.1) -> DataFrame:
    """``(src, dst, w, g)`` on existing edges."""
    left = residuals(cells, edges).select("sample_id", F.col("node_id").alias("dst"), "r")
    own = cells.select("sample_id", F.col("node_id").alias("src"), "x").join(edges, "src").join(left, ["sample_id", "dst"])
    summed = own.groupBy("src", "dst").agg(F.sum(F.col("x") * F.col("r")).alias("v"))
    return edges.join(summed, ["src", "dst"], "left").select("src", "dst", "w", (-2.0 / n * F.coalesce("v", F.lit(0.0)) + lam * F.signum("w")).alias("g"))


def _through_parents(moments: DataFrame, edges: DataFrame) -> DataFrame:
    """``(src, dst, w, q)``: q is the moment of src with the parents' combination of dst."""
    c = both_ways(moments)
    other = edges.select(F.col("src").alias("other"), "dst", F.col("w").alias("v"))
    pairs = edges.join(other, "dst").join(c, (F.col("src") == F.col("a")) & (F.col("other") == F.col("b")))
    return pairs.groupBy("src", "dst", "w").agg(F.sum(F.col("c") * F.col("v")).alias("q"))


def _with_target(moments: DataFrame, edges: DataFrame) -> DataFrame:
    """``(src, dst, w, q, t)``: t is the moment of src with dst itself."""
    through = _through_parents(moments, edges)
    target = both_ways(moments).select(F.col("a").alias("src"), F.col("b").alias("dst"), F.col("c").alias("t"))
    full = edges.select("src", "dst", "w").join(through.select("src", "dst", "q"), ["src", "dst"], "left").join(target, ["src", "dst"], "left")
    return full.select("src", "dst", "w", F.coalesce("q", F.lit(0.0)).alias("q"), F.coalesce("t", F.lit(0.0)).alias("t"))


def per_node(moments: DataFrame, edges: DataFrame) -> DataFrame:
    """``(node, fit)``: every node's own part of the fit."""
    gain = _with_target(moments, edges).groupBy(F.col("dst").alias("node")).agg(F.sum(F.col("w") * (F.col("q") - 2 * F.col("t"))).alias("v"))
    own = moments.where("a = b").select(F.col("a").alias("node"), "c")
    return own.join(gain, "node", "left").select("node", (F.col("c") + F.coalesce("v", F.lit(0.0))).alias("fit"))


def from_moments(moments: DataFrame, edges: DataFrame, lam: float = 0.1) -> DataFrame:
    """The same row as ``from_samples``, without the samples."""
    fit = per_node(moments, edges).agg(F.sum("fit").alias("fit"))
    penalty = edges.agg((lam * F.coalesce(F.sum(F.abs("w")), F.lit(0.0))).alias("penalty"))
    return fit.crossJoin(penalty).withColumn("loss", F.col("fit") + F.col("penalty"))  # one row each


def gradient_from_moments(moments: DataFrame, edges: DataFrame, lam: float = 0.1) -> DataFrame:
    """``(src, dst, w, g)`` on existing edges."""
    return _with_target(moments, edges).select("src", "dst", "w", (2 * (F.col("q") - F.col("t")) + lam * F.signum("w")).alias("g"))


def neg_log_likelihood(moments: DataFrame, edges: DataFrame, n: int, equal_variance: bool = False) -> DataFrame:
    """``(nll)`` of Gaussian noise at the best variances: one for each node, or one for all."""
    fit = per_node(moments, edges)
    if equal_variance:
        return fit.agg((n / 2.0 * F.count("*") * (F.log(F.sum("fit") / F.count("*")) + F.lit(1 + 1.8378770664093453))).alias("nll"))
    return fit.agg((n / 2.0 * F.sum(F.log("fit") + F.lit(1 + 1.8378770664093453))).alias("nll"))
