import datetime as dt
import time

import pytest
from pyspark.sql import functions as F

from dagframe.operators import monitor, recommend
from dagframe.operators import workload_frames as base
from dagframe.sources import simulated
from dagframe.sources.tables import edge_list, event_stream, events, write_model
from dagframe.streaming import monitoring


def test_diamond_has_two_root_paths(spark):
    e = spark.createDataFrame([(0, 1, 1.0), (0, 2, 1.0), (1, 3, 0.5), (2, 3, 2.0)], "src int, dst int, w double")
    t = spark.createDataFrame([(3,)], "node_id int")
    assert sorted(tuple(r["path"]) for r in monitor.root_paths(e, t).collect()) == [(0, 1, 3), (0, 2, 3)]
    with pytest.raises(ValueError):
        monitor.root_paths(e, t, max_paths=1).count()


def test_path_tests_against_exact_tail(spark):
    from math import comb

    row = spark.createDataFrame([([1, 2], 7, 1, 50, 60)], "path array<int>, n_now int, n_prev int, total_now int, total_prev int")
    exact = sum(comb(50, i) * comb(60, 8 - i) for i in range(7, 9)) / comb(110, 8)
    assert abs(monitor.path_test(row, "fisher").first()["p"] - exact) < 1e-9
    assert monitor.path_test(row).first()["p"] < 0.02


def test_burst_is_reported_with_its_root(spark):
    from dagframe.operators.workload_logs import queries

    got = queries()["anomaly_report_burst"](spark, "/root/testdata/sf0.01").collect()
    assert [(r["root"], r["target"]) for r in got] == [(base.BURST_FARE, base.BURST_STEP)]


@pytest.mark.parametrize("column, node, step", [("fare", base.BURST_FARE, base.BURST_STEP), ("airline", base.AIRLINE + 2, base.STEP + 1), ("airport", base.AIRPORT + 4, base.STEP)])
def test_learnt_graph_finds_the_root_of_a_burst(spark, column, node, step):
    from dagframe.operators.workload_logs import learnt_report

    records = base.burst(base.log(spark, "/root/testdata/sf0.01"), column, node, step).cache()
    got = learnt_report(records).orderBy("p", F.size("path")).collect()
    assert got and (got[0]["root"], got[0]["target"]) == (node, step)
    assert all(node in r["path"] and r["target"] == step for r in got)


def test_stream_equals_batch(spark, sf, tmp_path):
    src = tmp_path / "in"
    spark.read.parquet(f"{sf}/events.parquet").repartition(3).write.parquet(str(src))
    out: list = []
    counts = monitoring.pane_counts(event_stream(spark, str(src), 10), "event_type")
    q = monitoring.run(counts, lambda b, n: out.extend(b.collect()), str(tmp_path / "ck"), once=True)
    q.awaitTermination(120)
    last = max(r["window"]["end"] for r in out)
    batch = events(spark, sf).groupBy(F.window("ts", "30 minutes"), "event_type").agg(F.count("*").alias("n")).where(F.col("window.end") <= last)
    key = lambda r: (r["window"]["end"], r["event_type"], r["n"])
    assert len(out) > 100 and sorted(map(key, out)) == sorted(map(key, batch.collect()))


def test_idempotent_sink_and_model_round_trip(spark, tmp_path):
    e = spark.createDataFrame([(0, 1, 0.5)], "src int, dst int, w double")
    sink = monitoring.idempotent(str(tmp_path / "s"))
    sink(e, 1)
    sink(e, 1)
    assert spark.read.parquet(str(tmp_path / "s")).count() == 1
    write_model(e, str(tmp_path / "m"), "a")
    assert spark.read.parquet(str(tmp_path / "m")).where("run_id = 'a'").count() == 1
    e.write.option("header", True).csv(str(tmp_path / "c"))
    assert edge_list(spark, str(tmp_path / "c")).first()["w"] == 0.5


def test_sql_surface_and_source(spark):
    from dagframe.functions.register import register

    register(spark)
    simulated.register(spark)
    spark.createDataFrame([(1, 0, 1, 0.5), (1, 1, 0, 0.2), (1, 1, 2, 0.3)], "k int, src int, dst int, w double").createOrReplaceTempView("e")
    assert abs(spark.sql("select spectral_bound(src, dst, w) b from e group by k").first()["b"] - 0.200281) < 1e-6
    assert spark.sql("select * from paths_into(array(0, 1), array(1, 2), array(0.5D, 0.5D), 2, 5)").first()["weight"] == 0.25
    assert abs(spark.sql("select normal_tail_exact(1.96D) p").first()["p"] - 0.0249979) < 1e-6
    assert spark.read.format("dagsim").option("n", 7).option("d", 3).load().count() == 21


def test_recommendation(spark):
    cells = spark.createDataFrame([(1, 0, 1.0), (1, 1, -1.0)], "sample_id int, node_id int, x double")
    e = spark.createDataFrame([(0, 2, 0.5), (1, 2, 0.25), (2, 3, 1.0)], "src int, dst int, w double")
    assert recommend.score(cells, e).first()["score"] == 0.25
    assert {r["node_id"]: r["score"] for r in recommend.score(cells, e, hops=2).collect()} == {2: 0.25, 3: 0.25}
    assert [r["via"] for r in recommend.explain(cells, e, 1).collect()] == [0]
    assert recommend.ego_graph(e, 3, 1).count() == 1 and recommend.ego_graph(e, 3, 2).count() == 3


def test_panes_equal_windows(spark, sf):
    log = base.log(spark, sf).where("step is not null")
    last = log.agg(F.max("pane")).first()[0]
    panes = monitor.pane_windows(log.groupBy("pane", "step").agg(F.count("*").alias("n")), ["step"]).where(F.col("pane") == last).first()
    assert panes["now"] == log.where((F.col("pane") > last - 48) & (F.col("step") == panes["step"])).count()
    assert dt.date(2024, 1, 1) < dt.date(2024, 1, 30)


def test_state_between_batches_and_dedup(spark, tmp_path):
    src = tmp_path / "n"
    for n in (3, 5):
        spark.createDataFrame([("a", n)], "step string, n long").coalesce(1).write.mode("append").parquet(str(src))
    out: list = []
    stream = spark.readStream.schema("step string, n long").option("maxFilesPerTrigger", 1).parquet(str(src))
    monitoring.run(monitoring.count_drift(stream, "step"), lambda b, k: out.extend(map(tuple, b.collect())), str(tmp_path / "c"), "update", once=True).awaitTermination(120)
    assert sorted(out) == [("a", 3, -1), ("a", 5, 3)] or sorted(out) == [("a", 3, 5), ("a", 5, -1)]
    ev = tmp_path / "e"
    spark.sql("select id % 3 event_id, timestamp'2024-01-01 00:00:00' ts from range(9)").write.parquet(str(ev))
    seen: list = []
    raw = spark.readStream.schema("event_id long, ts timestamp").parquet(str(ev))
    monitoring.run(monitoring.deduplicated(raw), lambda b, k: seen.extend(b.collect()), str(tmp_path / "d"), once=True).awaitTermination(120)
    assert sorted(r["event_id"] for r in seen) == [0, 1, 2]


def test_interval_and_session_operators(spark):
    ev = spark.sql("select * from values (1, timestamp'2024-01-01 00:00:00', 7, 'view'), (2, timestamp'2024-01-01 00:20:00', 7, 'error'), (3, timestamp'2024-01-01 05:00:00', 7, 'click'), (4, timestamp'2024-01-01 00:10:00', 8, 'view') t(event_id, ts, user_id, event_type)")
    assert [(r["error_id"], r["event_id"]) for r in monitoring.interval_causes(ev).collect()] == [(2, 1)]
    assert sorted((r["user_id"], r["n_events"], r["n_errors"]) for r in monitoring.user_sessions(ev).collect()) == [(7, 1, 0), (7, 2, 1), (8, 1, 0)]


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    src = tmp_path / "n"
    times = ["2024-01-01 00:10:00", "2024-01-01 06:00:00"], ["2024-01-01 12:00:00"], ["2024-01-01 00:20:00", "2024-01-01 11:40:00"], ["2024-01-02 00:00:00"]
    for part in times:
        spark.createDataFrame([(t,) for t in part], "t string").select(F.col("t").cast("timestamp").alias("ts")).coalesce(1).write.mode("append").parquet(str(src))
        time.sleep(1.1)  # files are taken by age, in seconds
    out: list = []
    stream = spark.readStream.schema("ts timestamp").option("maxFilesPerTrigger", 1).parquet(str(src))
    query = monitoring.run(monitoring.pane_counts(stream), lambda b, k: out.extend(b.collect()), str(tmp_path / "c"), once=True)
    query.awaitTermination(120)
    assert monitoring.late_rows(query) == 1
    assert sum(r["n"] for r in out) == 4  # the last pane is still open, the late row is gone
