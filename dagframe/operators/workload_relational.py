"""Queries of the relational operators around the methods: approximate counts, subtotals, reshaping, maps, variants, paired windows,
alarms beside expert labels."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dagframe.functions.columns import stable
from dagframe.operators import baseline, recommend
from dagframe.operators import workload_frames as base
from dagframe.operators import workload_learning as learning
from dagframe.sources.tables import table


def distinct_counts(cells: DataFrame, rsd: float = 0.01) -> DataFrame:
    """``(samples, nodes, samples_close, nodes_close)``: exact numbers, and whether the sketches' are within five deviations.

    The exact counts shuffle every distinct value, the sketches a few kilobytes a task; use the latter to size a run.
    """
    exact = [F.count_distinct(c).alias(n) for c, n in (("sample_id", "samples"), ("node_id", "nodes"))]
    sketch = [F.approx_count_distinct(c, rsd).alias(f"{n}_about") for c, n in (("sample_id", "samples"), ("node_id", "nodes"))]
    close = [(F.abs(F.col(f"{n}_about") - F.col(n)) <= 5 * rsd * F.col(n)).alias(f"{n}_close") for n in ("samples", "nodes")]
    return cells.agg(*exact, *sketch).select("samples", "nodes", *close)


def alarm_subtotals(log: DataFrame) -> DataFrame:
    """Errors by step and airline, by step, and in all; ``level`` tells which columns are summed over."""
    return log.where("step is not null").rollup("step", "airline").agg(F.count("*").alias("n"), F.grouping_id().cast("long").alias("level"))


def alarm_margins(log: DataFrame) -> DataFrame:
    """Errors by step and fare source, and by airport: two groupings of one scan."""
    wanted = [[F.col("step"), F.col("fare")], [F.col("airport")]]
    return log.where("step is not null").groupingSets(wanted, F.col("step"), F.col("fare"), F.col("airport")).agg(F.count("*").alias("n"))


def steps_long(log: DataFrame) -> DataFrame:
    """Errors of each fare source, one column a step, turned back into rows; absent steps come out as zero."""
    wide = log.where("step is not null").groupBy("fare").pivot("step", [0, 1, 2, 3]).agg(F.count("event_id"))
    return wide.na.fill(0).unpivot(["fare"], ["0", "1", "2", "3"], "step", "n").select("fare", F.col("step").cast("int").alias("step"), "n")


def variant_numbers(events: DataFrame) -> DataFrame:
    """Events by type with the sum of a number that their JSON holds, read as a variant; broken JSON counts as absent."""
    k = F.try_variant_get(F.try_parse_json("props"), "$.k", "long")
    return events.groupBy("event_type").agg(F.sum(k).alias("total"), F.count(k).alias("held"))


def paired_windows(now: DataFrame, before: DataFrame, key: str = "step") -> DataFrame:
    """``(key, n_now, n_before)`` of two windows' counts side by side; a key of one window only has zero in the other.

    Groups are pre-aggregated, so a key's group is one row a side.
    """
    n = lambda frame: frame.select(F.col(key).alias("key")).groupBy("key").agg(F.count("*").alias("n"))  # noqa: E731; the alias keeps two sides of one table apart

    def both(k: tuple, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({key: [k[0]], "n_now": [int(a["n"].sum())], "n_before": [int(b["n"].sum())]})

    return n(now).groupBy("key").cogroup(n(before).groupBy("key")).applyInPandas(both, f"{key} int, n_now long, n_before long")


def _paired(s, d) -> DataFrame:
    log = base.log(s, d).where("step is not null").crossJoin(F.broadcast(base.log(s, d).agg(F.max("pane").alias("last"))))
    return paired_windows(log.where("last - pane < 48"), log.where("last - pane >= 48 and last - pane < 96"))


def _maps(s, d) -> DataFrame:
    """For each customer and brand, how many items speak for it and the strength of all; from maps of parts."""
    held = recommend.explain_map(learning._ratings(s, d), learning._links(s, d))
    for_it = F.map_filter("parts", lambda _, x: F.round(x, 9) > 0)
    sizes = F.map_values(F.transform_values("parts", lambda _, x: F.abs(x)))
    return held.select("sample_id", "node_id", F.size("parts").cast("long").alias("items"), F.size(for_it).cast("long").alias("speak_for"), stable(F.aggregate(sizes, F.lit(0.0), lambda a, x: a + x), 4).alias("strength"))


def _experts(s, d) -> DataFrame:
    """Alarms (orders with a returned line) beside expert categories (order priorities of finished orders), counted."""
    alarms = table(s, d, "lineitem").where("l_returnflag = 'R'").select(F.col("l_orderkey").alias("report_id")).distinct()
    expert = table(s, d, "orders").where("o_orderstatus = 'F'").select(F.col("o_orderkey").alias("report_id"), F.col("o_orderpriority").alias("category"))
    return baseline.expert_agreement(alarms, expert).groupBy("category").agg(F.count("*").alias("n"))


def queries() -> dict:
    return {
        "distinct_counts": lambda s, d: distinct_counts(base.ratings(s, d, "part")),
        "alarm_subtotals": lambda s, d: alarm_subtotals(base.log(s, d)),
        "alarm_margins": lambda s, d: alarm_margins(base.log(s, d)),
        "unpivot_steps": lambda s, d: steps_long(base.log(s, d)),
        "variant_numbers": lambda s, d: variant_numbers(table(s, d, "events")),
        "paired_windows": _paired,
        "explain_maps": _maps,
        "expert_agreement": _experts,
    }


def oracle_sql() -> dict[str, str]:
    log, errors = base.log_sql, "FROM log WHERE step IS NOT NULL"
    ago = "(SELECT max(pane) FROM log) - pane"
    return {
        "distinct_counts": "SELECT count(DISTINCT o_custkey)::BIGINT AS samples, count(DISTINCT l_partkey)::BIGINT AS nodes, true AS samples_close, true AS nodes_close FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
        "alarm_subtotals": log().then(f"SELECT step, airline, count(*)::BIGINT AS n, grouping_id(step, airline)::BIGINT AS level {errors} GROUP BY ROLLUP (step, airline)"),
        "alarm_margins": log().then(f"SELECT step, fare, airport, count(*)::BIGINT AS n {errors} GROUP BY GROUPING SETS ((step, fare), (airport))"),
        "unpivot_steps": log().then(f"SELECT f.fare, i::INTEGER AS step, count(l.step)::BIGINT AS n FROM (SELECT DISTINCT fare {errors}) f CROSS JOIN range(4) r(i) LEFT JOIN log l ON l.fare = f.fare AND l.step = r.i GROUP BY 1, 2"),
        "variant_numbers": "SELECT event_type, sum((props->>'k')::BIGINT)::BIGINT AS total, count(props->>'k')::BIGINT AS held FROM events GROUP BY 1",
        "paired_windows": log().then(f"SELECT step, count(*) FILTER ({ago} < 48)::BIGINT AS n_now, count(*) FILTER ({ago} >= 48)::BIGINT AS n_before {errors} AND {ago} < 96 GROUP BY 1"),
        "explain_maps": learning.links_sql().then("SELECT sample_id, dst AS node_id, count(*)::BIGINT AS items, count(*) FILTER (round(x * w, 9) > 0)::BIGINT AS speak_for, round(sum(abs(x * w)), 4) + 0.0 AS strength FROM cells JOIN links ON node_id = src GROUP BY 1, 2"),
        "expert_agreement": "SELECT coalesce(o_orderpriority, 'unlabelled') AS category, count(*)::BIGINT AS n FROM (SELECT DISTINCT l_orderkey FROM lineitem WHERE l_returnflag = 'R') LEFT JOIN orders ON l_orderkey = o_orderkey AND o_orderstatus = 'F' GROUP BY 1",
    }
