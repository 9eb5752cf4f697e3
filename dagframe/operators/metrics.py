"""Accuracy and cost measures of learned graphs, as grouped plans over edge tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dagframe.plans.lineage import cut


def edge_confusion(truth: DataFrame, predicted: DataFrame, *by: str) -> DataFrame:
    """``(by..., predicted, true, tp, reversed, extra, missing)``.

    A predicted edge is right, reversed (only its opposite is true) or extra; a true edge is missing if neither it nor its opposite
    is predicted. A pair with both directions predicted, one of them true, counts one right and one extra.
    """
    keys = [*by, "src", "dst"]
    t = truth.select(*keys).distinct().withColumn("in_t", F.lit(1))
    p = predicted.where("w <> 0").select(*keys).distinct().withColumn("in_p", F.lit(1))
    both = t.join(p, keys, "full").select(*keys, F.coalesce("in_t", F.lit(0)).alias("in_t"), F.coalesce("in_p", F.lit(0)).alias("in_p"))
    pair = both.select(*by, F.least("src", "dst").alias("lo"), F.greatest("src", "dst").alias("hi"), F.when(F.col("src") < F.col("dst"), F.col("in_t")).alias("t1"), F.when(F.col("src") > F.col("dst"), F.col("in_t")).alias("t2"), F.when(F.col("src") < F.col("dst"), F.col("in_p")).alias("p1"), F.when(F.col("src") > F.col("dst"), F.col("in_p")).alias("p2"))
    one = pair.groupBy(*by, "lo", "hi").agg(*[F.coalesce(F.max(c), F.lit(0)).alias(c) for c in ("t1", "t2", "p1", "p2")])
    tp = F.col("t1") * F.col("p1") + F.col("t2") * F.col("p2")
    turned = F.when((tp == 0) & (F.col("t1") * F.col("p2") + F.col("t2") * F.col("p1") > 0), 1).otherwise(0)
    each = one.select(*by, (F.col("p1") + F.col("p2")).alias("p"), (F.col("t1") + F.col("t2")).alias("t"), tp.alias("tp"), turned.alias("r"))
    total = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("long")
    return each.groupBy(*by).agg(
        total("p").alias("predicted"), total("t").alias("true"), total("tp").alias("tp"), total("r").alias("reversed"),
        total(F.col("p") - F.col("tp") - F.col("r")).alias("extra"), total(F.greatest(F.col("t") - F.col("tp") - F.col("r"), F.lit(0))).alias("missing"),
    )


def _ratio(a: Column, b: Column) -> Column:
    return F.when(b > 0, a / b).otherwise(0.0)


def f1() -> Column:
    return _ratio(2.0 * F.col("tp"), F.col("predicted") + F.col("true"))


def shd() -> Column:
    """Edge changes from one graph to the other; a reversed edge is one."""
    return F.col("extra") + F.col("missing") + F.col("reversed")


def fdr(kind: str = "direction") -> Column:
    """The share of predicted edges that are reversed; with ``kind="discovery"`` reversed or extra."""
    wrong = F.col("reversed") if kind == "direction" else F.col("reversed") + F.col("extra")
    return _ratio(wrong * 1.0, F.col("predicted"))


def tpr() -> Column:
    return _ratio(F.col("tp") * 1.0, F.col("true"))


def fpr() -> Column:
    """Wrong edges by the pairs of nodes that truth leaves apart; needs ``d``."""
    d = F.col("d").cast("double")
    return _ratio((F.col("reversed") + F.col("extra")) * 1.0, d * (d - 1) / 2 - F.col("true"))


def measures(confusion: DataFrame) -> DataFrame:
    """``confusion``, with a column ``d``, and all measures from its counts."""
    return confusion.withColumns({"f1": f1(), "shd": shd(), "fdr": fdr(), "tpr": tpr(), "fpr": fpr()})


def roc_auc(truth: DataFrame, scored: DataFrame, d: int) -> DataFrame:
    """``(auc)`` of |w| as a score for truth over all ordered pairs of d nodes; ties count half.

    Pairs without an edge have score 0 and are counted, not made.
    """
    t = truth.select("src", "dst").distinct().withColumn("pos", F.lit(1))
    s = scored.select("src", "dst", F.abs("w").alias("v"))
    rows = s.join(t, ["src", "dst"], "full").select(F.coalesce("v", F.lit(0.0)).alias("v"), F.coalesce("pos", F.lit(0)).alias("pos"))
    level = rows.groupBy("v").agg(F.sum("pos").alias("p"), F.sum(1 - F.col("pos")).alias("n"))
    listed = level.agg(F.sum(F.col("p") + F.col("n")).alias("seen"), F.sum("p").alias("all_p"), F.coalesce(F.max(F.when(F.col("v") == 0, F.col("p"))), F.lit(0)).alias("p0"), F.coalesce(F.max(F.when(F.col("v") == 0, F.col("n"))), F.lit(0)).alias("n0"))
    # negatives below each level: inside ranges of levels, and in the ranges before; no task sees all levels
    ranged = cut(level.where("v > 0").repartitionByRange("v").withColumn("part", F.spark_partition_id()))
    before = ranged.groupBy("part").agg(F.sum("n").alias("in_part")).withColumn("before", F.sum("in_part").over(Window.orderBy("part")) - F.col("in_part")).drop("in_part")  # one row a range
    inside = F.coalesce(F.sum("n").over(Window.partitionBy("part").orderBy("v").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    below = ranged.withColumn("inside", inside).join(F.broadcast(before), "part").withColumn("under", F.col("inside") + F.col("before"))
    wins = below.agg(F.coalesce(F.sum(F.col("p") * (F.coalesce("under", F.lit(0)) + F.col("n") / 2.0)), F.lit(0.0)).alias("wins"), F.coalesce(F.sum("p"), F.lit(0)).alias("p_up"))
    pairs = float(d * (d - 1))
    zeros = F.col("n0") + (pairs - F.col("seen"))
    negatives = pairs - F.col("all_p")
    return wins.crossJoin(listed).select(((F.col("wins") + F.col("p_up") * zeros + F.col("p0") * zeros / 2) / (F.col("all_p") * negatives)).alias("auc"))  # one row each


def trace_correlation(trace: DataFrame, *by: str) -> DataFrame:
    """Pearson correlation of the bound and the exponential trace along runs."""
    return trace.groupBy(*by).agg(F.corr("bound", "trexp").alias("corr"), F.count("*").alias("n"))


def speedup(results: DataFrame, baseline: str, method: str, *by: str) -> DataFrame:
    """Seconds of ``baseline`` by seconds of ``method`` for each cell."""
    side = lambda name, out: results.where(F.col("method") == name).groupBy(*by).agg(F.avg("seconds").alias(out))
    return side(baseline, "slow").join(side(method, "fast"), list(by)).select(*by, "slow", "fast", (F.col("slow") / F.col("fast")).alias("speedup"))


def cost_model(edges: DataFrame, k: int = 5) -> DataFrame:
    """Non-zeros, nodes, bytes in coordinate form, and edges that a bound of depth k touches."""
    nodes = edges.select(F.explode(F.array("src", "dst")).alias("node")).agg(F.countDistinct("node").alias("d"))
    return edges.agg(F.count("*").alias("s")).crossJoin(nodes).select("s", "d", (F.col("s") * 16).alias("bytes"), (F.col("s") * (2 * k + 1)).alias("touched"))


def compare(a: DataFrame, b: DataFrame, truth: DataFrame) -> DataFrame:
    """How two predictions differ against truth: ``(only_a, only_b, right_a, right_b)``."""
    k = ["src", "dst"]
    n = lambda frame, name: frame.agg(F.count("*").alias(name))
    x, y, t = (f.select(*k).distinct() for f in (a, b, truth))
    return n(x.join(y, k, "left_anti"), "only_a").crossJoin(n(y.join(x, k, "left_anti"), "only_b")).crossJoin(n(x.join(t, k, "left_semi"), "right_a")).crossJoin(n(y.join(t, k, "left_semi"), "right_b"))


def audit_constraint(trace: DataFrame, eps: float, d: int) -> DataFrame:
    """Design-rule report of a run's trace: does the bound stay consistent with the trace measure, and how closely do they move."""
    safe = F.col("trexp") <= d * F.expm1("bound") + 1e-9
    return trace.agg(F.min(safe.cast("int")).alias("consistent"), F.corr("bound", "trexp").alias("corr"), F.max("nnz").alias("most_edges"), F.min(((F.col("bound") > F.log1p(F.lit(eps / d))) | (F.col("trexp") <= eps)).cast("int")).alias("threshold_holds"))
