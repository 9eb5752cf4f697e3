"""Queries on logs: windows, paths into errors, their evidence, reports, drift, and the relational operators around them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dagframe.functions.columns import normal_tail_sql, stable
from dagframe.operators import learner, matrices, moments, monitor
from dagframe.operators import workload_frames as base
from dagframe.plans.lineage import cut, ready
from dagframe.plans.sqlgen import Ctes
from dagframe.sources.tables import event_stream, events, table
from dagframe.streaming import monitoring
from dagframe.streaming.monitoring import interval_causes, user_sessions


def _log(s, d) -> DataFrame:
    return cut(base.log(s, d))


def _steps(s, d) -> DataFrame:
    """Counts of the error steps by pane."""
    return base.log(s, d).where("step is not null").groupBy("pane", "step").agg(F.count("*").alias("n"))


def _targets(s) -> DataFrame:
    return s.range(base.STEP, base.STEP + 4).select(F.col("id").cast("int").alias("node_id"))


def _last_day(records: DataFrame) -> DataFrame:
    return records.crossJoin(F.broadcast(records.agg(F.max("pane").alias("last")))).where("pane > last - 48").drop("last")


def _paths(records, s) -> DataFrame:
    """Paths into error steps in the graph of the last 24 hours."""
    return monitor.root_paths(cut(base.log_graph(_last_day(records))), _targets(s), 5)


def _periods(records: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(active, totals) of the last 24 hours and the 24 before."""
    last = records.agg(F.max("pane").alias("last"))
    back = F.col("last") - F.col("pane")
    named = base.with_active(records).crossJoin(F.broadcast(last)).withColumn("period", F.when(back < 48, "now").when(back < 96, "prev")).where("period is not null")
    active = named.select("period", F.col("event_id").alias("record_id"), F.explode("active").alias("node_id"))
    return active, named.groupBy("period").agg(F.count("*").alias("n"))


def _support(records, s) -> DataFrame:
    return monitor.path_support(_paths(records, s), *_periods(records))



def _text():
    """A path as text; a function, since columns need a session."""
    return F.concat_ws(">", F.col("path").cast("array<string>")).alias("path")


_COUNTS = ["n_now", "n_prev", "total_now", "total_prev"]


def _tested(test, made=lambda r: r):
    def query(s, d):
        return monitor.path_test(_support(made(_log(s, d)), s), test).select("target", _text(), *_COUNTS, stable("p").alias("p"))

    return query


def _report(made, correction=None, p_max=0.05):
    def query(s, d):
        got = monitor.report(monitor.path_test(_support(made(_log(s, d)), s)), p_max, correction)
        return got.select("target", "root", _text(), "n_now", "n_prev", stable("p").alias("p"))

    return query


def _windows(s, d):
    w = monitor.windows(events(s, d).where("event_type = 'error'"))
    return w.groupBy("window").agg(F.count("*").alias("n")).select(F.date_format("window.end", "yyyy-MM-dd HH:mm:ss").alias("window_end"), "n")


def _panes(s, d):
    return monitor.pane_windows(_steps(s, d), ["step"]).select("pane", "step", "n", "now", "prev")


def _pane_moments(s, d):
    return moments.by_pane(base.with_active(base.log(s, d))).groupBy("a", "b").agg(stable(F.sum("s")).alias("s"), F.count("*").alias("panes"))


def _window_moments(s, d):
    m = cut(moments.by_pane(base.with_active(base.log(s, d))))
    ends = m.select("pane").distinct().select(F.col("pane").alias("end"))
    return monitor.combine_panes(m, ends).select("end", "a", "b", stable("s").alias("s"))


def _fit_windows(s, d):
    """Graphs of a window each half hour, learnt from pane moments until the stop rule holds."""
    records = _log(s, d)
    m = cut(moments.by_pane(base.with_active(records)))
    ends = m.select("pane").distinct().select(F.col("pane").alias("end"))
    per = records.groupBy("pane").agg(F.count("*").alias("n"))
    totals = per.join(ends.select("end", F.explode(F.sequence(F.col("end") - 47, F.col("end"))).alias("pane")), "pane").groupBy("end").agg(F.sum("n").alias("n"))
    return monitor.learn_windows(monitor.combine_panes(m, ends), totals, base.LOG_NODES, learner.LearnerParams(lam=0.02), 0.05)


#: A window's learning: error steps cause nothing.
WINDOW = learner.LearnerParams(lam=0.002, sinks=tuple(range(base.STEP, base.STEP + 4)))


def learnt_windows(records: DataFrame, p: learner.LearnerParams = WINDOW, tau: float = 0.05) -> DataFrame:
    """``(back, src, dst, w)``: graphs learnt for the last 24 hours (back 0) and the 24 before (back 1)."""
    last = records.agg(F.max("pane").alias("last"))
    recent = records.crossJoin(F.broadcast(last)).withColumn("pane", F.floor((F.col("last") - F.col("pane")) / monitor.PANES).cast("long")).where("pane < 2")
    m = moments.by_pane(base.with_active(recent)).withColumnRenamed("pane", "end")
    totals = recent.groupBy(F.col("pane").alias("end")).agg(F.count("*").alias("n"))
    return cut(monitor.learn_windows(m, totals, base.LOG_NODES, p, tau, True).withColumnRenamed("end", "back"))


def learnt_report(records: DataFrame, p_max: float = 1e-3, correction: str | None = None) -> DataFrame:
    """The whole chain: learn the last window's graph, list paths into error steps, test them, report; the smallest p names the likeliest root."""
    s = records.sparkSession
    paths = monitor.root_paths(learnt_windows(records).where("back = 0 and w > 0"), _targets(s), 4, every=True)  # a cause raises its effect
    return monitor.report(monitor.path_test(monitor.path_support(paths, *_periods(records))), p_max, correction)


def _learnt(made, p_max=1e-3):
    def query(s, d):
        return learnt_report(cut(made(base.log(s, d))), p_max).select("target", "root", _text(), *_COUNTS, stable("p").alias("p"))

    return query


def _learnt_drift(s, d):
    graphs = learnt_windows(_log(s, d))
    side = lambda back: graphs.where(F.col("back") == back).select("src", "dst", "w")
    return monitor.graph_drift(side(0), side(1), _targets(s))


def _drift(s, d):
    records = _log(s, d)
    a, b = base.log_graph(records.where("pane % 2 = 0")), base.log_graph(records.where("pane % 2 = 1"))
    return monitor.graph_drift(a, b, _targets(s)).select("src", "dst", stable("w_now").alias("w_now"), stable("w_prev").alias("w_prev"), stable("change").alias("change"), "kind")


def _breakdown(s, d):
    """Alarms by cause, from order priorities of returned lines as stand-in categories."""
    names = {"1-URGENT": "external", "2-HIGH": "airline", "3-MEDIUM": "intermediary", "4-NOT SPECIFIED": "agent", "5-LOW": "false alarm"}
    cause = F.coalesce(*[F.when(F.col("o_orderpriority") == k, v) for k, v in names.items()], F.lit("unexplained"))
    got = monitor.alarm_breakdown(table(s, d, "orders").select(cause.alias("category")))
    return got.select("category", "n", stable("share").alias("share"), stable("true_share").alias("true_share"))


def _first_attempt(s, d):
    e = events(s, d).where("event_type in ('purchase', 'error')").withColumn("day", F.to_date("ts"))
    return monitor.first_attempt_rate(e, ["user_id", "day"], ["ts", "event_id"], F.col("event_type") == "purchase").select("groups", stable("rate").alias("rate"))


def _sessions(s, d):
    got = user_sessions(events(s, d))
    return got.select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n_events", "n_errors")


def _asof(s, d):
    """Each purchase with the user's latest event of another kind before it, as a union and a running last value."""
    e = events(s, d).select("event_id", "ts", "user_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    latest = F.last(F.when(F.col("event_type") != "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("before_id", latest).where("event_type = 'purchase'").select("event_id", "before_id")


def _business(s, d):
    """Return rates by month, nation and priority, with the month before: the batch form of monitoring on business tables."""
    t = lambda n: table(s, d, n)
    lines = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey"))
    month = F.year("o_orderdate") * 12 + F.month("o_orderdate")
    per = lines.groupBy(month.alias("m"), F.col("n_name").alias("nation"), F.col("o_orderpriority").alias("step")).agg(F.count("*").alias("n"), F.count(F.when(F.col("l_returnflag") == "R", 1)).alias("errors"))
    w = Window.partitionBy("nation", "step").orderBy("m")
    return per.withColumn("errors_before", F.when(F.lag("m").over(w) == F.col("m") - 1, F.lag("errors").over(w)))


def _sources(s, d):
    """Pages, passages and turns as indicators: how many samples each node of the three kinds has."""
    pages = table(s, d, "pages").select(F.col("page_id").alias("id"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("v"))
    turns = table(s, d, "conversations").select(F.col("conv_id").alias("id"), F.concat_ws("/", "role", F.least("turn", F.lit(3)).cast("string")).alias("v"))
    bench = table(s, d, "benchmark").select(F.col("item_id").alias("id"), F.concat(F.lit("len"), F.floor(F.length("text") / 100).cast("string")).alias("v"))
    parts = [matrices.indicators(f, "id", {"v": k}) for f, k in ((pages, "host"), (turns, "turn"), (bench, "bench"))]
    out = None
    for cells, nodes in parts:
        one = cells.join(nodes, "node_id").groupBy("label").agg(F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
    return out


def _stream_panes(s, d):
    """Pane counts of the log read as a stream, through the sink that replaces a repeated batch."""
    from uuid import uuid4

    home = f"{ready(s).sparkContext.getCheckpointDir()}/stream-{uuid4().hex}"
    counts = monitoring.pane_counts(event_stream(s, d, 10, "events.parquet"), "event_type")
    monitoring.run(counts, monitoring.idempotent(f"{home}/out"), f"{home}/state", mode="complete", once=True).awaitTermination()
    out = s.read.parquet(f"{home}/out")
    last = out.agg(F.max("batch").alias("last"))
    return out.crossJoin(F.broadcast(last)).where("batch = last").select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("pane_start"), "event_type", "n")


def queries() -> dict:
    return {
        "indicators_events": lambda s, d: base.with_active(base.log(s, d)).select(F.explode("active").alias("node_id")).groupBy("node_id").agg(F.count("*").alias("n")),
        "windows_24h": _windows,
        "windows_panes": _panes,
        "moments_panes": _pane_moments,
        "moments_windows": _window_moments,
        "log_graph": lambda s, d: base.log_graph(_log(s, d)).select("src", "dst", stable("w").alias("w")),
        "root_paths": lambda s, d: _paths(_log(s, d), s).select("target", _text(), "ended", stable(F.aggregate("edge_w", F.lit(1.0), lambda a, x: a * x)).alias("weight")),
        "path_support": lambda s, d: _support(_log(s, d), s).select("target", _text(), *_COUNTS),
        "path_ztest": _tested("two_prop_z"), "path_chi2": _tested("chi2"), "path_fisher": _tested("fisher"),
        "anomaly_report": _report(lambda r: r),
        "anomaly_report_burst": _report(lambda r: cut(base.burst(r)), None, 1e-4),
        "anomaly_report_bh": _report(lambda r: cut(base.burst(r)), "bh", 0.01),
        "graph_drift": _drift,
        "error_spikes": lambda s, d: monitor.error_spikes(_steps(s, d), factor=3.0, min_count=2).select("pane", "step", "n", stable("mean").alias("mean"), stable("lift").alias("lift")),
        "alarm_breakdown": _breakdown,
        "first_attempt_rate": _first_attempt,
        "sessions": _sessions,
        "asof_model": _asof,
        "interval_errors": lambda s, d: interval_causes(events(s, d), "2 hours").groupBy("event_type").agg(F.count("*").alias("n"), F.countDistinct("error_id").alias("errors")),
        "business_monitoring": _business,
        "indicator_sources": _sources,
        "weight_quantiles": lambda s, d: base.order_sequence(s, d).agg(*[stable(F.percentile("w", F.lit(q))).alias(f"q{int(q * 100)}") for q in (0.1, 0.5, 0.9)], F.count_distinct("src").alias("nodes")),
        "pivot_steps": lambda s, d: base.log(s, d).where("step is not null").groupBy("fare").pivot("step", [0, 1, 2, 3]).agg(F.count("event_id")).select("fare", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"step{i}") for i in range(4)]),
        "rank_links": lambda s, d: base.net_flow(s, d).select("src", "dst", F.rank().over(Window.partitionBy("src").orderBy(F.desc(F.round("w", 9)))).alias("nth"), F.ntile(4).over(Window.partitionBy("src").orderBy(F.desc(F.round("w", 9)), "dst")).alias("quarter")).where("nth <= 3"),
        "stream_panes": _stream_panes,
        "fit_windows": _fit_windows,
        "learnt_window_graphs": lambda s, d: learnt_windows(_log(s, d)),
        "learnt_report": _learnt(lambda r: r, 0.05),
        "learnt_report_fare_burst": _learnt(base.burst),
        "learnt_report_airline_burst": _learnt(lambda r: base.burst(r, "airline", base.AIRLINE + 2, base.STEP + 1)),
        "learnt_report_airport_burst": _learnt(lambda r: base.burst(r, "airport", base.AIRPORT + 4, base.STEP)),
        "learnt_drift": _learnt_drift,
    }


def _path_ctes(log: str = "log") -> Ctes:
    c = base.log_sql()
    if log == "bursty":
        c.add("bursty", base.BURST_SQL)
    c.add("day", f"SELECT * FROM {log} WHERE pane > (SELECT max(pane) FROM {log}) - 48").add("g", base.log_graph_sql("day"))
    c.add("RECURSE walk", f"SELECT range::INTEGER AS target, [range::INTEGER] AS path, 1.0::DOUBLE AS weight FROM range({base.STEP}, {base.STEP + 4}) UNION ALL SELECT w.target, list_prepend(g.src, w.path), w.weight * g.w FROM walk w JOIN g ON g.dst = w.path[1] WHERE NOT list_contains(w.path, g.src) AND len(w.path) < 5")
    c.add("paths", "SELECT target, path, weight, NOT EXISTS (SELECT 1 FROM g WHERE g.dst = path[1]) AS ended FROM walk WHERE len(path) > 1 AND (len(path) = 5 OR NOT EXISTS (SELECT 1 FROM g WHERE g.dst = path[1]))")
    last = f"(SELECT max(pane) FROM {log})"
    c.add("rec", f"SELECT event_id, CASE WHEN {last} - pane < 48 THEN 'now' ELSE 'prev' END AS period, list_filter([step, airline, fare, airport], lambda x: x IS NOT NULL) AS active FROM {log} WHERE {last} - pane < 96")
    c.add("counted", "SELECT target, array_to_string(path, '>') AS path, path[1] AS root, (SELECT count(*) FROM rec WHERE period = 'now' AND list_has_all(active, paths.path))::BIGINT AS n_now, (SELECT count(*) FROM rec WHERE period = 'prev' AND list_has_all(active, paths.path))::BIGINT AS n_prev, (SELECT count(*) FROM rec WHERE period = 'now')::BIGINT AS total_now, (SELECT count(*) FROM rec WHERE period = 'prev')::BIGINT AS total_prev FROM paths")
    c.add("z", "SELECT *, (x::DOUBLE / a - y::DOUBLE / b) / CASE WHEN dev > 0 THEN dev ELSE 1 END AS z FROM (SELECT *, sqrt(((x + y)::DOUBLE / (a + b)) * (1 - (x + y)::DOUBLE / (a + b)) * (1.0::DOUBLE / a + 1.0::DOUBLE / b)) AS dev FROM (SELECT *, n_now AS x, n_prev AS y, total_now AS a, total_prev AS b FROM counted))")
    return c


_P = f"CASE WHEN dev > 0 THEN {normal_tail_sql('z')} ELSE 1.0 END"


def oracle_sql() -> dict[str, str]:
    log = base.log_sql
    counts = "target, path, n_now, n_prev, total_now, total_prev"
    steps = lambda: log().add("steps", "SELECT pane, step, count(*)::BIGINT AS n FROM log WHERE step IS NOT NULL GROUP BY 1, 2")
    active = "SELECT pane, unnest(list_filter([step, airline, fare, airport], lambda x: x IS NOT NULL)) AS node_id, event_id FROM log"
    pairs = lambda: log().add("act", active).add("pane_m", "SELECT x.pane, x.node_id AS a, y.node_id AS b, count(*)::DOUBLE AS s FROM act x JOIN act y ON x.event_id = y.event_id WHERE x.node_id <= y.node_id GROUP BY 1, 2, 3")
    report = lambda name, cond: _path_ctes(name).add("t", f"SELECT *, {_P} AS p FROM z").then(f"SELECT target, root, path, n_now, n_prev, round(p, 6) + 0.0 AS p FROM t WHERE {cond}")
    lf = lambda n: f"lgamma(({n}) + 1)"
    fisher = f"least(1.0, (SELECT sum(exp({lf('x + y')} + {lf('a + b - x - y')} + {lf('a')} + {lf('b')} - {lf('a + b')} - {lf('i')} - {lf('x + y - i')} - {lf('a - i')} - {lf('b - x - y + i')})) FROM (SELECT unnest(range(x, least(x + y, a) + 1))::DOUBLE AS i)))"
    drift = log().add("g1", base.log_graph_sql("(SELECT * FROM log WHERE pane % 2 = 0)")).add("g2", base.log_graph_sql("(SELECT * FROM log WHERE pane % 2 = 1)"))
    cause = "CASE o_orderpriority WHEN '1-URGENT' THEN 'external' WHEN '2-HIGH' THEN 'airline' WHEN '3-MEDIUM' THEN 'intermediary' WHEN '4-NOT SPECIFIED' THEN 'agent' WHEN '5-LOW' THEN 'false alarm' ELSE 'unexplained' END"
    return {
        "indicators_events": log().add("act", active).then("SELECT node_id, count(*)::BIGINT AS n FROM act GROUP BY 1"),
        "windows_24h": "SELECT strftime(e, '%Y-%m-%d %H:%M:%S') AS window_end, count(*)::BIGINT AS n FROM (SELECT make_timestamp(((floor(epoch(ts) / 1800)::BIGINT + 1 + range) * 1800 * 1000000)::BIGINT) AS e FROM events, range(48) WHERE event_type = 'error') GROUP BY e",
        "stream_panes": "SELECT strftime(make_timestamp((floor(epoch(ts) / 1800) * 1800 * 1000000)::BIGINT), '%Y-%m-%d %H:%M:%S') AS pane_start, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2",
        "windows_panes": steps().then("SELECT pane, step, n, sum(n) OVER (PARTITION BY step ORDER BY pane RANGE BETWEEN 47 PRECEDING AND CURRENT ROW)::BIGINT AS now, coalesce(sum(n) OVER (PARTITION BY step ORDER BY pane RANGE BETWEEN 95 PRECEDING AND 48 PRECEDING), 0)::BIGINT AS prev FROM steps"),
        "moments_panes": pairs().then("SELECT a, b, round(sum(s), 6) + 0.0 AS s, count(*)::BIGINT AS panes FROM pane_m GROUP BY 1, 2"),
        "moments_windows": pairs().then('SELECT e.pane AS "end", m.a, m.b, round(sum(m.s), 6) + 0.0 AS s FROM pane_m m JOIN (SELECT DISTINCT pane FROM log) e ON m.pane BETWEEN e.pane - 47 AND e.pane GROUP BY 1, 2, 3'),
        "log_graph": log().add("g", base.log_graph_sql()).then("SELECT src, dst, round(w, 6) + 0.0 AS w FROM g"),
        "root_paths": _path_ctes().then("SELECT target, array_to_string(path, '>') AS path, ended, round(weight, 6) + 0.0 AS weight FROM paths"),
        "path_support": _path_ctes().then(f"SELECT {counts} FROM counted"),
        "path_ztest": _path_ctes().then(f"SELECT {counts}, round({_P}, 6) + 0.0 AS p FROM z"),
        "path_chi2": _path_ctes().then(f"SELECT {counts}, round(CASE WHEN dev > 0 THEN 2 * {normal_tail_sql('abs(z)')} ELSE 1.0 END, 6) + 0.0 AS p FROM z"),
        "path_fisher": _path_ctes().then(f"SELECT {counts}, round({fisher}, 6) + 0.0 AS p FROM z"),
        "anomaly_report": report("log", "p <= 0.05"),
        "anomaly_report_burst": report("bursty", "p <= 1e-4"),
        "anomaly_report_bh": _path_ctes("bursty").add("t", f"SELECT *, {_P} AS p FROM z").add("r", "SELECT *, row_number() OVER (ORDER BY p) AS i, count(*) OVER () AS m FROM t").then("SELECT target, root, path, n_now, n_prev, round(p, 6) + 0.0 AS p FROM r WHERE i <= (SELECT coalesce(max(i), 0) FROM r WHERE p <= 0.01 * i / m)"),
        "graph_drift": drift.then(f"SELECT coalesce(a.src, b.src) AS src, coalesce(a.dst, b.dst) AS dst, round(a.w, 6) + 0.0 AS w_now, round(b.w, 6) + 0.0 AS w_prev, round(coalesce(a.w, 0) - coalesce(b.w, 0), 6) + 0.0 AS change, CASE WHEN b.w IS NULL THEN 'new' WHEN a.w IS NULL THEN 'gone' ELSE 'changed' END AS kind FROM g1 a FULL JOIN g2 b ON a.src = b.src AND a.dst = b.dst WHERE coalesce(a.dst, b.dst) BETWEEN {base.STEP} AND {base.STEP + 3}"),
        "error_spikes": steps().then("SELECT pane, step, n, round(mean, 6) + 0.0 AS mean, round(n / mean, 6) + 0.0 AS lift FROM (SELECT *, coalesce(sum(n) OVER (PARTITION BY step ORDER BY pane RANGE BETWEEN 48 PRECEDING AND 1 PRECEDING), 0)::DOUBLE / 48 AS mean FROM steps) WHERE n >= 2 AND mean > 0 AND n >= 3 * mean"),
        "alarm_breakdown": f"SELECT category, count(*)::BIGINT AS n, round(count(*)::DOUBLE / (SELECT count(*) FROM orders), 6) + 0.0 AS share, round((SELECT count(*) FILTER (WHERE ({cause}) <> 'false alarm')::DOUBLE / count(*) FROM orders), 6) + 0.0 AS true_share FROM (SELECT {cause} AS category FROM orders) GROUP BY category",
        "first_attempt_rate": "SELECT count(*)::BIGINT AS groups, round(avg(ok), 6) + 0.0 AS rate FROM (SELECT (event_type = 'purchase')::INTEGER AS ok, row_number() OVER (PARTITION BY user_id, ts::DATE ORDER BY ts, event_id) AS i FROM events WHERE event_type IN ('purchase', 'error')) WHERE i = 1",
        "sessions": "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*)::BIGINT AS n_events, count(*) FILTER (event_type = 'error')::BIGINT AS n_errors FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nr FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 2 HOUR >= ts THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, nr",
        "asof_model": "SELECT event_id, before_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type <> 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before_id FROM events) WHERE event_type = 'purchase'",
        "interval_errors": "SELECT o.event_type, count(*)::BIGINT AS n, count(DISTINCT e.event_id)::BIGINT AS errors FROM events e JOIN events o ON e.user_id = o.user_id AND o.event_type <> 'error' AND o.ts < e.ts AND o.ts >= e.ts - INTERVAL 2 HOUR WHERE e.event_type = 'error' GROUP BY 1",
        "business_monitoring": "SELECT m, nation, step, n, errors, CASE WHEN lag(m) OVER w = m - 1 THEN lag(errors) OVER w END AS errors_before FROM (SELECT (year(o_orderdate) * 12 + month(o_orderdate))::INTEGER AS m, n_name AS nation, o_orderpriority AS step, count(*)::BIGINT AS n, count(*) FILTER (l_returnflag = 'R')::BIGINT AS errors FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY 1, 2, 3) WINDOW w AS (PARTITION BY nation, step ORDER BY m)",
        "indicator_sources": "SELECT label, count(*)::BIGINT AS n FROM (SELECT DISTINCT page_id AS id, 'host=' || regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS label FROM pages UNION SELECT conv_id, 'turn=' || role || '/' || least(turn, 3) FROM conversations UNION SELECT item_id, 'bench=len' || floor(length(text) / 100)::INTEGER FROM benchmark) GROUP BY label",
        "weight_quantiles": base.order_sequence_sql().then("SELECT round(quantile_cont(w, 0.1), 6) + 0.0 AS q10, round(quantile_cont(w, 0.5), 6) + 0.0 AS q50, round(quantile_cont(w, 0.9), 6) + 0.0 AS q90, count(DISTINCT src)::BIGINT AS nodes FROM edges"),
        "pivot_steps": log().then("SELECT fare, " + ", ".join(f"count(*) FILTER (step = {i})::BIGINT AS step{i}" for i in range(4)) + " FROM log WHERE step IS NOT NULL GROUP BY fare"),
        "rank_links": base.net_flow_sql().then("SELECT * FROM (SELECT src, dst, (rank() OVER (PARTITION BY src ORDER BY round(w, 9) DESC))::INTEGER AS nth, (ntile(4) OVER (PARTITION BY src ORDER BY round(w, 9) DESC, dst))::INTEGER AS quarter FROM flow) WHERE nth <= 3"),
    }
