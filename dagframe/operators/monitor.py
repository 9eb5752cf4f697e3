"""Root-cause monitoring: windows of logs, paths into error nodes, their evidence and its significance."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dagframe.functions.columns import normal_tail
from dagframe.operators.learner import LearnerParams, fit_many
from dagframe.plans.lineage import cut

PANE_SECONDS = 1800
PANES = 48


def pane_of(ts: Column) -> Column:
    """The half hour of a timestamp, counted from 1970."""
    return F.floor(F.unix_timestamp(ts.cast("timestamp")) / PANE_SECONDS)


def windows(events: DataFrame, ts: str = "ts", length: str = "24 hours", slide: str = "30 minutes") -> DataFrame:
    """Every event in each of its windows, as Spark's own window operator gives them: ``window`` and all columns."""
    return events.withColumn("window", F.window(F.col(ts).cast("timestamp"), length, slide))


def pane_windows(counts: DataFrame, keys: list[str], value: str = "n", panes: int = PANES) -> DataFrame:
    """Sums over the last ``panes`` panes of pane counts ``(pane, keys..., value)``, for each pane that has a count.

    Counts of panes are added, so an event is never copied into its windows. Also ``prev``: the window before it.
    """
    w = Window.partitionBy(*keys).orderBy("pane")
    return counts.withColumns({"now": F.sum(value).over(w.rangeBetween(-(panes - 1), 0)), "prev": F.coalesce(F.sum(value).over(w.rangeBetween(-(2 * panes - 1), -panes)), F.lit(0))})


def combine_panes(moments: DataFrame, ends: DataFrame, panes: int = PANES) -> DataFrame:
    """``(end, a, b, s)``: pane moments summed over the windows that end with the panes ``ends(end)``."""
    reach = ends.select("end", F.explode(F.sequence(F.col("end") - (panes - 1), F.col("end"))).alias("pane"))
    return moments.join(reach, "pane").groupBy("end", "a", "b").agg(F.sum("s").alias("s"))


def learn_windows(moments: DataFrame, totals: DataFrame, d: int, p: LearnerParams, tau: float = 0.1, indicators: bool = False) -> DataFrame:
    """EDGES of each window, from ``(end, a, b, s)`` and ``(end, n)``; models are learnt in parallel tasks, from covariances if all nodes are ``indicators``."""
    scaled = moments.join(totals, "end").select("end", "a", "b", (F.col("s") / F.col("n")).alias("c"))
    tasks = 2 * scaled.sparkSession.sparkContext.defaultParallelism  # a model costs far more than its rows, by which tasks would be merged
    return fit_many(scaled.repartition(tasks, "end"), d, p, "end", tau, indicators)


def root_paths(edges: DataFrame, targets: DataFrame, max_len: int = 8, max_paths: int = 1_000_000, every: bool = False) -> DataFrame:
    """``(target, path, edge_w, ended)``: every path into a target that starts at a node without parents, root first; with ``every``
    also the paths that start on the way, since a fault can lie at a node that has causes.

    Paths grow backwards, one edge a round, without a repeated node; those that reach ``max_len`` nodes come out with ``ended``
    false. More than ``max_paths`` paths are an error, not a cut.
    """
    e = edges.select("src", "dst", "w")
    parents = e.select(F.col("dst").alias("head")).distinct().withColumn("has", F.lit(True))
    now, done = targets.select(F.col("node_id").alias("target"), F.array("node_id").alias("path"), F.array().cast("array<double>").alias("edge_w")), None
    for n in range(1, max_len + 1):
        open_ = cut(now.withColumn("head", F.col("path")[0]).join(parents, "head", "left"))
        if open_.count() > max_paths:
            raise ValueError(f"more than {max_paths} paths")
        grown = open_.join(e, F.col("head") == F.col("dst")).where(~F.array_contains("path", F.col("src"))).select("target", F.concat(F.array("src"), "path").alias("path"), F.concat(F.array("w"), "edge_w").alias("edge_w"))
        ended = open_.where("has is null" if n < max_len and not every else "true").select("target", "path", "edge_w", F.col("has").isNull().alias("ended")).where(F.size("path") > 1)
        done = ended if done is None else done.unionByName(ended)
        now = grown
    return done


def path_support(paths: DataFrame, active: DataFrame, totals: DataFrame) -> DataFrame:
    """``paths`` with ``n_now``, ``n_prev``, ``total_now``, ``total_prev``.

    A record supports a path if all its nodes are active in it. ``active(period, record_id, node_id)``: period is ``now`` or
    ``prev``; ``totals(period, n)`` counts all records.
    """
    key = paths.select("path").distinct().select(F.xxhash64("path").alias("pid"), "path")
    steps = key.select("pid", F.size("path").alias("size"), F.explode("path").alias("node_id"))
    hits = active.join(steps, "node_id").groupBy("period", "record_id", "pid").agg(F.count("*").alias("k"), F.max("size").alias("size")).where("k = size")
    n = hits.groupBy("pid").agg(F.count(F.when(F.col("period") == "now", 1)).alias("n_now"), F.count(F.when(F.col("period") == "prev", 1)).alias("n_prev"))
    t = totals.agg(F.coalesce(F.sum(F.when(F.col("period") == "now", F.col("n"))), F.lit(0)).alias("total_now"), F.coalesce(F.sum(F.when(F.col("period") == "prev", F.col("n"))), F.lit(0)).alias("total_prev"))
    found = paths.withColumn("pid", F.xxhash64("path")).join(n, "pid", "left").drop("pid")
    return found.withColumns({c: F.coalesce(c, F.lit(0)) for c in ("n_now", "n_prev")}).crossJoin(F.broadcast(t))  # one row


def two_prop_p() -> Column:
    """One-sided: is the share now larger than before."""
    a, b, x, y = (F.col(c).cast("double") for c in ("total_now", "total_prev", "n_now", "n_prev"))
    pool = (x + y) / (a + b)
    dev = F.sqrt(pool * (1 - pool) * (1 / a + 1 / b))
    return F.when((a > 0) & (b > 0) & (dev > 0), normal_tail((x / a - y / b) / dev)).otherwise(1.0)


def chi2_p() -> Column:
    """Two-sided, one degree of freedom, without continuity correction."""
    a, b, x, y = (F.col(c).cast("double") for c in ("total_now", "total_prev", "n_now", "n_prev"))
    pool = (x + y) / (a + b)
    dev = F.sqrt(pool * (1 - pool) * (1 / a + 1 / b))
    return F.when((a > 0) & (b > 0) & (dev > 0), 2 * normal_tail(F.abs(x / a - y / b) / dev)).otherwise(1.0)


def _log_factorial(n: str) -> str:
    """ln n! as SQL: exact sums below 16, from there a series whose error is below 1e-11; no cost that grows with n."""
    x = f"cast({n} as double)"
    low = "array(" + ", ".join(f"{sum(math.log(i) for i in range(1, k + 1))!r}D" for k in range(16)) + ")"
    series = f"({x} * ln({x}) - {x} + 0.5 * ln(2 * pi() * {x}) + 1 / (12 * {x}) - 1 / (360 * pow({x}, 3)) + 1 / (1260 * pow({x}, 5)))"
    return f"if({n} < 16, element_at({low}, cast(greatest({n}, 0) as int) + 1), {series})"


def fisher_p(frame: DataFrame) -> DataFrame:
    """``frame`` with ``p``, the exact one-sided hypergeometric tail.

    Terms further than fifty deviations (and a hundred) from the mode are below 1e-300 and left out, so the sum's length grows
    with the root of the counts only.
    """
    k, a, b = "(n_now + n_prev)", "total_now", "total_prev"
    fixed = {"lx_": k, "ly_": f"({a} + {b} - n_now - n_prev)", "la_": a, "lb_": b, "ln_": f"({a} + {b})"}
    logs = frame.withColumns({name: F.expr(_log_factorial(n)) for name, n in fixed.items()})
    mode = f"{k} * ({a} / greatest({a} + {b}, 1))"
    wide = f"(50 * sqrt({mode} * ({b} / greatest({a} + {b}, 1))) + 100)"
    ranged = logs.withColumns({"from_": F.expr(f"cast(greatest(n_now, {k} - {b}, floor({mode} - {wide})) as long)"), "to_": F.expr(f"cast(least({k}, {a}, greatest(n_now + 100, ceil({mode} + {wide}))) as long)")})
    term = f"exp(lx_ + ly_ + la_ + lb_ - ln_ - {_log_factorial('i')} - {_log_factorial(f'({k} - i)')} - {_log_factorial(f'({a} - i)')} - {_log_factorial(f'({b} - {k} + i)')})"
    tail = f"if(from_ > to_, 0D, aggregate(sequence(from_, to_), 0D, (acc, i) -> acc + {term}))"
    return ranged.withColumn("p", F.least(F.lit(1.0), F.expr(tail))).drop(*fixed, "from_", "to_")


def path_test(paths: DataFrame, test: str = "two_prop_z") -> DataFrame:
    """``paths`` with ``p``: ``two_prop_z`` and ``fisher`` for a rise, ``chi2`` for any change."""
    if test == "fisher":
        return fisher_p(paths)
    return paths.withColumn("p", {"two_prop_z": two_prop_p, "chi2": chi2_p}[test]())


def report(paths: DataFrame, p_max: float = 0.01, correction: str | None = None) -> DataFrame:
    """Paths with a small p and their probable root. ``correction="bh"`` limits the false discovery rate instead."""
    if correction == "bh":
        w = Window.orderBy("p")  # over paths, which are bounded by root_paths
        ranked = paths.withColumn("i_", F.row_number().over(w)).crossJoin(paths.agg(F.count("*").alias("m_")))
        top = ranked.where(F.col("p") <= p_max * F.col("i_") / F.col("m_")).agg(F.coalesce(F.max("i_"), F.lit(0)).alias("top_"))
        kept = ranked.crossJoin(top).where("i_ <= top_").drop("i_", "m_", "top_")
    elif correction is None:
        kept = paths.where(F.col("p") <= p_max)
    else:
        raise ValueError("correction is bh or None")
    return kept.withColumn("root", F.col("path")[0]).withColumn("reported", F.lit(True))


def graph_drift(now: DataFrame, prev: DataFrame, targets: DataFrame) -> DataFrame:
    """``(src, dst, w_now, w_prev, change, kind)`` of links into targets: new, gone, or changed."""
    a, b = now.select("src", "dst", F.col("w").alias("w_now")), prev.select("src", "dst", F.col("w").alias("w_prev"))
    both = a.join(b, ["src", "dst"], "full").join(targets.select(F.col("node_id").alias("dst")).distinct(), "dst", "left_semi")
    kind = F.when(F.col("w_prev").isNull(), "new").when(F.col("w_now").isNull(), "gone").otherwise("changed")
    return both.select("src", "dst", "w_now", "w_prev", (F.coalesce("w_now", F.lit(0.0)) - F.coalesce("w_prev", F.lit(0.0))).alias("change"), kind.alias("kind"))


def error_spikes(panes: DataFrame, key: str = "step", value: str = "n", factor: float = 2.0, min_count: int = 3, back: int = PANES) -> DataFrame:
    """Panes in which a count is at least ``factor`` times its mean over the ``back`` panes before: with ``mean`` and ``lift``."""
    w = Window.partitionBy(key).orderBy("pane").rangeBetween(-back, -1)
    mean = F.coalesce(F.sum(value).over(w), F.lit(0)) / F.lit(float(back))
    return panes.withColumn("mean", mean).where((F.col(value) >= min_count) & (F.col("mean") > 0) & (F.col(value) >= factor * F.col("mean"))).withColumn("lift", F.col(value) / F.col("mean"))


def alarm_breakdown(labelled: DataFrame) -> DataFrame:
    """``(category, n, share)`` of alarms by cause, and ``true_share``, all but false alarms."""
    n = labelled.groupBy("category").agg(F.count("*").alias("n"))
    t = n.agg(F.sum("n").alias("all_"), F.coalesce(F.sum(F.when(F.col("category") != "false alarm", F.col("n"))), F.lit(0)).alias("true_"))
    return n.crossJoin(F.broadcast(t)).select("category", "n", (F.col("n") / F.col("all_")).alias("share"), (F.col("true_") / F.col("all_")).alias("true_share"))


def first_attempt_rate(frame: DataFrame, keys: list[str], order: list[str], ok: Column) -> DataFrame:
    """``(groups, rate)``: the share of groups whose first row is a success; the first row is an aggregate, not a sort."""
    first = frame.groupBy(*keys).agg(F.min(F.struct(*order, ok.cast("int").alias("ok_"))).alias("f"))
    return first.agg(F.count("*").alias("groups"), F.avg("f.ok_").alias("rate"))
