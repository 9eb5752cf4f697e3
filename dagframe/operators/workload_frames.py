"""Frames that the workloads start from, each with the SQL that makes the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.operators import matrices
from dagframe.plans.sqlgen import Ctes
from dagframe.sources.tables import events as read_events
from dagframe.sources.tables import table

BRAND_SQL = "regexp_extract(p_brand, '[0-9]+')::INTEGER"


def brand(column: str = "p_brand"):
    return F.regexp_extract(column, "[0-9]+", 0).cast("int")


def order_sequence(spark: SparkSession, d: str) -> DataFrame:
    """EDGES of brands: the share of orders that hold a line of src before a line of dst, by the largest share.

    Lines of an order and brand are first reduced to their first and last number, so the self-join is of brands, not lines.
    """
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber").join(table(spark, d, "part").select("p_partkey", brand().alias("b")), F.col("l_partkey") == F.col("p_partkey"))
    span = lines.groupBy("l_orderkey", "b").agg(F.min("l_linenumber").alias("lo"), F.max("l_linenumber").alias("hi"))
    x = span.select("l_orderkey", F.col("b").alias("src"), "lo")
    y = span.select("l_orderkey", F.col("b").alias("dst"), "hi")
    n = x.join(y, "l_orderkey").where("src <> dst and lo < hi").groupBy("src", "dst").agg(F.count("*").alias("n"))
    return n.crossJoin(F.broadcast(n.agg(F.max("n").alias("top")))).select("src", "dst", (F.col("n") / F.col("top")).alias("w"))


def order_sequence_sql() -> Ctes:
    return Ctes(
        ("span_", f"SELECT l_orderkey AS o, {BRAND_SQL} AS b, min(l_linenumber) AS lo, max(l_linenumber) AS hi FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2"),
        ("cnt_", "SELECT x.b AS src, y.b AS dst, count(*) AS n FROM span_ x JOIN span_ y ON x.o = y.o WHERE x.b <> y.b AND x.lo < y.hi GROUP BY 1, 2"),
        ("edges", "SELECT src, dst, n::DOUBLE / (SELECT max(n) FROM cnt_) AS w FROM cnt_"),
    )


def net_flow(spark: SparkSession, d: str) -> DataFrame:
    """EDGES of brands: how much stronger one order is than the other."""
    e = order_sequence(spark, d)
    back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("w").alias("v"))
    return e.join(back, ["src", "dst"], "left").where("w > coalesce(v, 0)").select("src", "dst", (F.col("w") - F.coalesce("v", F.lit(0.0))).alias("w"))


def net_flow_sql() -> Ctes:
    return order_sequence_sql().add("flow", "SELECT e.src, e.dst, e.w - coalesce(r.w, 0) AS w FROM edges e LEFT JOIN edges r ON e.src = r.dst AND e.dst = r.src WHERE e.w > coalesce(r.w, 0)")


NUMERIC = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "o_totalprice", "p_size", "p_retailprice", "c_acctbal"]


def numerics(spark: SparkSession, d: str) -> DataFrame:
    """Eight numeric columns of joined rows, standardised."""
    t = lambda n: table(spark, d, n)
    joined = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    return matrices.standardise(joined.select(*[F.col(c).cast("double").alias(c) for c in NUMERIC]), NUMERIC)


def numerics_sql() -> Ctes:
    raw = ", ".join(f"{c}::DOUBLE AS {c}" for c in NUMERIC)
    std = ", ".join(f"({c} - avg({c}) OVER ()) / stddev_pop({c}) OVER () AS x{i}" for i, c in enumerate(NUMERIC))
    pairs = " UNION ALL ".join(f"SELECT {i} AS a, {j} AS b, avg(x{i} * x{j}) AS c FROM std_" for i in range(8) for j in range(i, 8))
    return Ctes(("raw_", f"SELECT {raw} FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN customer ON o_custkey = c_custkey"), ("std_", f"SELECT {std} FROM raw_"), ("moments", pairs))


#: A small graph on the eight numeric columns, with a cycle, for checks of single steps.
PROBE = [(0, 1, 0.8), (1, 4, 0.3), (6, 1, 0.5), (4, 0, -0.2), (5, 6, 0.1), (7, 4, 0.05), (2, 3, -0.4)]


def probe(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(PROBE, "src int, dst int, w double")


PROBE_SQL = "SELECT * FROM (VALUES " + ", ".join(f"({s}, {t}, {w}::DOUBLE)" for s, t, w in PROBE) + ") v(src, dst, w)"


#: A small graph on brands, with a cycle, for checks of mini-batch steps.
BRAND_PROBE = [(11, 12, 0.3), (12, 13, -0.2), (13, 11, 0.1), (21, 22, 0.4), (33, 45, -0.3), (45, 51, 0.2)]
BRAND_PROBE_SQL = "SELECT * FROM (VALUES " + ", ".join(f"({s}, {t}, {w}::DOUBLE)" for s, t, w in BRAND_PROBE) + ") v(src, dst, w)"


def brand_probe(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(BRAND_PROBE, "src int, dst int, w double")


def ratings(spark: SparkSession, d: str, item: str = "brand") -> DataFrame:
    """CELLS: customers by brands (or parts), the mean quantity, centred by customer."""
    t = lambda n: table(spark, d, n)
    lines = t("lineitem").select("l_orderkey", "l_partkey", "l_quantity").join(t("orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    if item == "brand":
        lines = lines.join(t("part").select("p_partkey", brand().alias("node_id")), F.col("l_partkey") == F.col("p_partkey"))
    else:
        lines = lines.withColumn("node_id", F.col("l_partkey").cast("int"))
    return matrices.centre_by_sample(lines.groupBy(F.col("o_custkey").alias("sample_id"), "node_id").agg(F.avg("l_quantity").alias("x")))


def ratings_sql() -> Ctes:
    return Ctes(
        ("mean_", f"SELECT o_custkey AS sample_id, {BRAND_SQL} AS node_id, avg(l_quantity) AS x FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2"),
        ("cells", "SELECT sample_id, node_id, x - avg(x) OVER (PARTITION BY sample_id) AS x FROM mean_"),
    )


#: Nodes of the log: four error steps, ten airlines, ten fare sources, seven airports.
STEP, AIRLINE, FARE, AIRPORT, LOG_NODES = 0, 4, 14, 24, 31


def log(spark: SparkSession, d: str) -> DataFrame:
    """Records ``(event_id, pane, step, airline, fare, airport)``; step is null for what is no error."""
    e = read_events(spark, d)
    pane = F.datediff(F.to_date("ts"), F.lit("1970-01-01").cast("date")) * 48 + F.hour("ts") * 2 + F.floor(F.minute("ts") / 30).cast("int")
    return e.select(
        "event_id", pane.cast("long").alias("pane"),
        F.when(F.col("event_type") == "error", (STEP + F.floor(F.col("k") / 25)).cast("int")).alias("step"),
        (AIRLINE + F.col("user_id") % 10).cast("int").alias("airline"), (FARE + F.floor(F.col("k") / 10)).cast("int").alias("fare"), (AIRPORT + F.col("user_id") % 7).cast("int").alias("airport"),
    )


def log_sql() -> Ctes:
    k = "(props->>'k')::INTEGER"
    return Ctes(("log", f"SELECT event_id, floor(epoch(ts) / 1800)::BIGINT AS pane, CASE WHEN event_type = 'error' THEN ({STEP} + {k} // 25)::INTEGER END AS step, ({AIRLINE} + user_id % 10)::INTEGER AS airline, ({FARE} + {k} // 10)::INTEGER AS fare, ({AIRPORT} + user_id % 7)::INTEGER AS airport FROM events"))


BURST_FARE, BURST_STEP = FARE + 3, STEP + 2


def burst(records: DataFrame, column: str = "fare", node: int = BURST_FARE, step: int = BURST_STEP) -> DataFrame:
    """The log with an injected fault: in the last window every event of one fare source (or airline, or airport) fails in one step."""
    last = records.agg(F.max("pane").alias("last"))
    hit = (F.col(column) == node) & (F.col("pane") > F.col("last") - 48)
    return records.crossJoin(F.broadcast(last)).withColumn("step", F.when(hit, F.lit(step)).otherwise(F.col("step"))).drop("last")


BURST_SQL = f"SELECT event_id, pane, CASE WHEN fare = {BURST_FARE} AND pane > (SELECT max(pane) FROM log) - 48 THEN {BURST_STEP} ELSE step END AS step, airline, fare, airport FROM log"


def with_active(records: DataFrame) -> DataFrame:
    """Records with ``active``, the array of their nodes."""
    return records.withColumn("active", F.array_compact(F.array("step", "airline", "fare", "airport")))


def log_graph(records: DataFrame) -> DataFrame:
    """EDGES by shares: airline to fare source (share of the airline's records), fare source to error step."""
    pair = lambda a, b, low: records.where(f"{b} is not null").groupBy(F.col(a).alias("src"), F.col(b).alias("dst")).agg(F.count("*").alias("n")).join(records.groupBy(F.col(a).alias("src")).agg(F.count("*").alias("t")), "src").select("src", "dst", (F.col("n") / F.col("t")).alias("w")).where(F.col("w") > low)
    return pair("airline", "fare", 0.25).unionByName(pair("fare", "step", 0.05))


def log_graph_sql(log_name: str = "log") -> str:
    pair = lambda a, b, low: f"SELECT src, dst, w FROM (SELECT p.src, p.dst, p.n::DOUBLE / t.t AS w FROM (SELECT {a} AS src, {b} AS dst, count(*) AS n FROM {log_name} WHERE {b} IS NOT NULL GROUP BY 1, 2) p JOIN (SELECT {a} AS src, count(*) AS t FROM {log_name} GROUP BY 1) t ON p.src = t.src) WHERE w > {low}"
    return pair("airline", "fare", 0.25) + " UNION ALL " + pair("fare", "step", 0.05)
