"""Queries on graphs: the bound and its gradient, exact measures, planted graphs, accuracy measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.functions.columns import normal_sql, stable, uniform_sql
from dagframe.operators import acyclicity, bound, grid, metrics, simulate
from dagframe.operators import workload_frames as base
from dagframe.plans import sqlgen
from dagframe.plans.lineage import cut
from dagframe.plans.sqlgen import Ctes
from dagframe.sources.tables import table

D, EPN, SEED = 20, 2, 7
P = 2 * EPN / (D - 1)


def _flow(spark, d):
    return cut(base.net_flow(spark, d))


def planted(spark: SparkSession) -> DataFrame:
    return simulate.weights(simulate.er_dag(spark, D, EPN, SEED), seed=SEED)


def _sequence_guess(spark, d) -> tuple[DataFrame, DataFrame]:
    """Two graphs of brands from the given lines: the net flow, and the stronger half of the order sequences."""
    seq = cut(base.order_sequence(spark, d))
    return cut(base.net_flow(spark, d)), seq.where("w >= 0.5")


def _sequence_guess_sql() -> Ctes:
    return base.net_flow_sql().add("guess", "SELECT * FROM edges WHERE w >= 0.5")


#: Result-like rows of the given orders: groups, a share, a number and an amount.
ORDER_RESULTS = "o_orderstatus AS graph, o_orderpriority AS noise, o_totalprice / 1000000 AS f1"


def _order_results(spark, d) -> DataFrame:
    return table(spark, d, "orders").selectExpr(*ORDER_RESULTS.split(", "))


def _order_trace(spark, d) -> DataFrame:
    """Two positive measures of a graph of orders, a row an order: all mass (which its bound never exceeds) and the exponential
    trace of the two-cycle whose weights are its value and the rest of its key."""
    w = F.col("o_totalprice") / 1000000
    v = F.pmod(F.col("o_orderkey"), F.lit(97)) / 100
    return table(spark, d, "orders").select(F.pmod(F.col("o_orderkey"), F.lit(2)).cast("int").alias("run"), (w * w + v * v).alias("bound"), (2 * F.cosh(w * v) - 2).alias("trexp"), F.when(v > 0, 2).otherwise(0).cast("long").alias("nnz"))


ORDER_TRACE_SQL = "SELECT (o_orderkey % 2)::INTEGER AS run, w * w + v * v AS bound, exp(w * v) + exp(-w * v) - 2 AS trexp, CASE WHEN v > 0 THEN 2 ELSE 0 END::BIGINT AS nnz FROM (SELECT o_orderkey, o_totalprice / 1000000 AS w, (o_orderkey % 97)::DOUBLE / 100 AS v FROM orders)"


def planted_sql() -> Ctes:
    u = uniform_sql(SEED, "weight", "src", "dst")
    return Ctes(
        ("node_", f"SELECT range::INTEGER AS node, {uniform_sql(SEED, 'order', 'range')} AS place FROM range({D})"),
        ("dag", f"SELECT a.node AS src, b.node AS dst FROM node_ a, node_ b WHERE a.place < b.place AND {uniform_sql(SEED, 'edge', 'a.node', 'b.node')} < {P!r}"),
        ("planted", f"SELECT src, dst, CASE WHEN {uniform_sql(SEED, 'sign', 'src', 'dst')} < 0.5 THEN -(0.5 + 1.5 * {u}) ELSE 0.5 + 1.5 * {u} END AS w FROM dag"),
    )


def guess(edges: DataFrame) -> DataFrame:
    """A made-up prediction for measures: planted edges kept, turned, dropped or weakened by hash, and some wrong ones."""
    u = simulate.uniform(SEED, "guess", F.col("src"), F.col("dst"))
    turned = u < 0.2
    kept = edges.withColumn("u", u).where("u < 0.8").select(F.when(turned, F.col("dst")).otherwise(F.col("src")).alias("src"), F.when(turned, F.col("src")).otherwise(F.col("dst")).alias("dst"), (F.col("w") * F.col("u")).alias("w"))
    extra = edges.sparkSession.range(D - 1).select(F.col("id").cast("int").alias("src"), (F.col("id") + 1).cast("int").alias("dst"), (0.05 + F.col("id") / 50).alias("w"))
    return kept.unionByName(extra).groupBy("src", "dst").agg(F.max("w").alias("w"))


GUESS_SQL = f"""SELECT src, dst, max(w) AS w FROM (
  SELECT CASE WHEN u < 0.2 THEN dst ELSE src END AS src, CASE WHEN u < 0.2 THEN src ELSE dst END AS dst, w * u AS w FROM (SELECT *, {uniform_sql(SEED, 'guess', 'src', 'dst')} AS u FROM planted) WHERE u < 0.8
  UNION ALL SELECT range::INTEGER, (range + 1)::INTEGER, 0.05 + range::DOUBLE / 50 FROM range({D - 1})) GROUP BY src, dst"""


def confusion_sql(truth: str, guessed: str, by: str = "") -> str:
    """(by, predicted, true, tp, reversed, extra, missing) of two edge queries."""
    k = f"{by}, " if by else ""
    g = f"GROUP BY {by}" if by else ""
    return f"""SELECT {k}sum(p1 + p2)::BIGINT AS predicted, sum(t1 + t2)::BIGINT AS true, sum(tp)::BIGINT AS tp, sum(r)::BIGINT AS reversed, sum(p1 + p2 - tp - r)::BIGINT AS extra, sum(greatest(t1 + t2 - tp - r, 0))::BIGINT AS missing
    FROM (SELECT *, t1 * p1 + t2 * p2 AS tp, CASE WHEN t1 * p1 + t2 * p2 = 0 AND t1 * p2 + t2 * p1 > 0 THEN 1 ELSE 0 END AS r FROM (
      SELECT {k}least(src, dst) AS lo, greatest(src, dst) AS hi, max(CASE WHEN src < dst THEN t ELSE 0 END) AS t1, max(CASE WHEN src > dst THEN t ELSE 0 END) AS t2, max(CASE WHEN src < dst THEN p ELSE 0 END) AS p1, max(CASE WHEN src > dst THEN p ELSE 0 END) AS p2
      FROM (SELECT {k}src, dst, 1 AS t, 0 AS p FROM {truth} UNION ALL SELECT {k}src, dst, 0, 1 FROM {guessed}) GROUP BY {k}lo, hi)) {g}"""


MEASURES_SQL = """predicted, "true", tp, reversed, extra, missing, round(2.0 * tp / (predicted + "true"), 6) + 0.0 AS f1, (extra + missing + reversed)::BIGINT AS shd, round(reversed::DOUBLE / predicted, 6) + 0.0 AS fdr, round(tp::DOUBLE / "true", 6) + 0.0 AS tpr"""


def _measured(confusion: DataFrame, d: int, *by: str) -> DataFrame:
    m = metrics.measures(confusion.withColumn("d", F.lit(d)))
    return m.select(*by, "predicted", "true", "tp", "reversed", "extra", "missing", *[stable(c).alias(c) for c in ("f1", "fdr", "tpr", "fpr")], F.col("shd").cast("long").alias("shd"))


#: Counts that a published table of three networks gives: (network, method, nodes, true, predicted, right, reversed).
REPLAY = [("small", "baseline", 11, 17, 17, 7, 6), ("small", "bound", 11, 17, 15, 7, 6), ("medium", "baseline", 1565, 3648, 164, 140, 24), ("medium", "bound", 1565, 3648, 234, 210, 24), ("large", "baseline", 4441, 12873, 560, 553, 7), ("large", "bound", 4441, 12873, 794, 785, 9)]


def _replay(spark, d):
    """Measures from published counts. For the medium and large networks the printed right edges don't give the printed measures;
    predicted less reversed does, and is what REPLAY holds."""
    rows = spark.createDataFrame(REPLAY, "network string, method string, d int, true long, predicted long, tp long, reversed long")
    full = rows.withColumns({"extra": F.col("predicted") - F.col("tp") - F.col("reversed"), "missing": F.col("true") - F.col("tp") - F.col("reversed")})
    return metrics.measures(full).select("network", "method", *[stable(c, 9).alias(c) for c in ("f1", "fdr", "tpr", "fpr")], F.col("shd").cast("long").alias("shd"))


def _noise(kind):
    def query(spark, d):
        return simulate.noise_cells(spark, 50, D, kind, SEED).select("sample_id", "node_id", stable("x").alias("x"))

    return query


def _noise_sql(kind):
    s, j = f"(range // {D})", f"(range % {D})"
    u = uniform_sql(SEED, "noise", s, j)
    x = {"gauss": normal_sql(SEED, "noise", s, j), "exp": f"-ln({u})", "gumbel": f"-ln(-ln({u}))"}[kind]
    return f"SELECT {s}::BIGINT AS sample_id, {j}::INTEGER AS node_id, round({x}, 6) + 0.0 AS x FROM range({50 * D})"


def _samples(spark, d):
    """Forty samples of the planted graph, level by level."""
    cells = simulate.noise_cells(spark, 40, D, "gauss", SEED)
    return simulate.sample_levels(cut(planted(spark)), cells, 4).select("sample_id", "node_id", stable("x").alias("x"))


def _samples_sql():
    s, j = f"(range // {D})", f"(range % {D})"
    c = planted_sql().add("l0", f"SELECT {s}::BIGINT AS sample_id, {j}::INTEGER AS node_id, {normal_sql(SEED, 'noise', s, j)} AS x FROM range({40 * D})")
    for t in range(1, 5):
        c.add(f"l{t}", f"SELECT sample_id, dst AS node_id, sum(x * w) AS x FROM l{t - 1} JOIN planted ON node_id = src GROUP BY 1, 2")
    return c.then("SELECT sample_id, node_id, round(sum(x), 6) + 0.0 AS x FROM (" + " UNION ALL ".join(f"SELECT * FROM l{t}" for t in range(5)) + ") GROUP BY 1, 2")


def _results(spark) -> DataFrame:
    """Sixty made-up result rows, by hash: inputs of the ``*_arithmetic`` queries, which check sums against SQL and measure nothing."""
    n = F.col("id")
    u = simulate.uniform(SEED, "result", n)
    return spark.range(60).select(F.element_at(F.array(F.lit("er"), F.lit("sf")), (n % 2 + 1).cast("int")).alias("graph"), F.element_at(F.array(F.lit("gauss"), F.lit("exp"), F.lit("gumbel")), (n % 3 + 1).cast("int")).alias("noise"), (10 * (1 + n % 5)).cast("int").alias("d"), F.when(n % 4 < 2, "bound").otherwise("trexp").alias("method"), u.alias("f1"), F.floor(u * 40).cast("double").alias("shd"), (F.col("id") + 1 + 10 * u).alias("seconds"))


RESULTS_SQL = f"""SELECT CASE range % 2 WHEN 0 THEN 'er' ELSE 'sf' END AS graph, CASE range % 3 WHEN 0 THEN 'gauss' WHEN 1 THEN 'exp' ELSE 'gumbel' END AS noise, (10 * (1 + range % 5))::INTEGER AS d, CASE WHEN range % 4 < 2 THEN 'bound' ELSE 'trexp' END AS method, u AS f1, floor(u * 40) AS shd, range + 1 + 10 * u AS seconds
FROM (SELECT range, {uniform_sql(SEED, 'result', 'range')} AS u FROM range(60))"""


def _snapshots(spark):
    g = guess(planted(spark))
    return g.withColumn("eps", F.lit(0.1)).unionByName(g.withColumn("w", F.col("w") * 0.6).withColumn("eps", F.lit(0.01)))


def _readout(spark, d):
    got = grid.read_out(_snapshots(spark), planted(spark), D)
    return grid.best_cell(got).select("eps", "tau", "predicted", "tp", stable("f1").alias("f1"), F.col("shd").cast("long").alias("shd")).unionByName(got.select("eps", "tau", "predicted", "tp", stable("f1").alias("f1"), F.col("shd").cast("long").alias("shd")))


def _readout_sql():
    c = planted_sql().add("guess", GUESS_SQL).add("tau_", "SELECT * FROM (VALUES (0.1::DOUBLE), (0.2), (0.3), (0.4), (0.5)) v(tau)")
    c.add("snap", "SELECT 0.1::DOUBLE AS eps, src, dst, w FROM guess UNION ALL SELECT 0.01::DOUBLE, src, dst, w * 0.6 FROM guess")
    c.add("kept", "SELECT eps, tau, src, dst FROM snap JOIN tau_ ON abs(w) >= tau").add("all_t", "SELECT eps, tau, src, dst FROM (SELECT DISTINCT eps FROM snap), tau_, planted")
    c.add("conf", confusion_sql("all_t", "kept", "eps, tau"))
    c.add("m", 'SELECT eps, tau, predicted, tp, 2.0::DOUBLE * tp / (predicted + "true") AS f, (extra + missing + reversed)::BIGINT AS shd FROM conf')
    one = "SELECT eps, tau, predicted, tp, round(f, 6) + 0.0 AS f1, shd FROM"
    return c.then(f"SELECT * FROM ({one} m ORDER BY f DESC, eps DESC, tau LIMIT 1) UNION ALL {one} m")


def _auc(spark, d):
    return metrics.roc_auc(planted(spark), guess(planted(spark)), D).select(stable("auc").alias("auc"))


def _auc_sql():
    c = planted_sql().add("guess", GUESS_SQL).add("nodes_", f"SELECT range AS i FROM range({D})")
    c.add("pairs", "SELECT coalesce(abs(g.w), 0) AS v, p.src IS NOT NULL AS pos FROM nodes_ a CROSS JOIN nodes_ b LEFT JOIN guess g ON g.src = a.i AND g.dst = b.i LEFT JOIN planted p ON p.src = a.i AND p.dst = b.i WHERE a.i <> b.i")
    return c.then("SELECT round(avg(CASE WHEN x.v > y.v THEN 1.0 WHEN x.v = y.v THEN 0.5 ELSE 0.0 END), 6) + 0.0 AS auc FROM pairs x, pairs y WHERE x.pos AND NOT y.pos")


def _algebra(spark, d):
    """Common, added and removed edges of two graphs, counted."""
    a, b = (x.select("src", "dst") for x in _sequence_guess(spark, d))
    n = lambda f, name: f.agg(F.count("*").alias("n")).select(F.lit(name).alias("part"), "n")
    return n(a.intersectAll(b), "common").unionByName(n(a.exceptAll(b), "only first")).unionByName(n(b.exceptAll(a), "only second")).unionByName(n(a.union(b).distinct(), "either"))


def queries() -> dict:
    seq = lambda s, d: cut(base.order_sequence(s, d))
    return {
        "bound_node_masses": lambda s, d: bound.node_scale(bound.node_masses(bound.square(base.order_sequence(s, d)))).select("node", *[stable(c).alias(c) for c in ("out_mass", "in_mass", "scale")]),
        "bound_rescale_round": lambda s, d: bound.forward_states(seq(s, d), 1)[1].adjacency.select("src", "dst", stable("w").alias("w"), stable("a").alias("a")),
        "bound_profile_k5": lambda s, d: bound.bound_profile(seq(s, d), 5).select("k", stable("bound").alias("bound")),
        "bound_profile_alpha_half": lambda s, d: bound.bound_profile(_flow(s, d), 4, 0.5).select("k", stable("bound").alias("bound")),
        "bound_max_aggregate": lambda s, d: bound.spectral_bound(seq(s, d), 5, aggregate="max").select(stable("bound").alias("bound")),
        "bound_peeled_first": lambda s, d: bound.spectral_bound(base.order_sequence(s, d).where("src < dst"), 1, peel_first=True).select(stable("bound").alias("bound")),
        "bound_partials": lambda s, d: bound.local_partials(bound.node_scale(bound.node_masses(bound.square(base.order_sequence(s, d))))).select("node", stable("fx").alias("fx"), stable("fy").alias("fy")),
        "bound_gradient_dense0": lambda s, d: bound.gradient_dense0(bound.node_masses(bound.square(seq(s, d)))).select("src", "dst", stable("g").alias("g")),
        "bound_gradient_k1": lambda s, d: bound.bound_gradient(seq(s, d), 1).select("src", "dst", stable("w").alias("w"), stable("g").alias("g")),
        "bound_gradient_k5": lambda s, d: bound.bound_gradient(_flow(s, d), 5).select("src", "dst", stable("w").alias("w"), stable("g").alias("g")),
        "bound_thresholds": lambda s, d: acyclicity.thresholds(table(s, d, "part").select((F.col("p_partkey") % 6 + 1).alias("k")).distinct().select(F.pow(F.lit(10.0), -F.col("k")).alias("eps"), (F.col("k") * 50).cast("int").alias("d"))).select("d", stable("eps").alias("eps"), stable("for_trexp", 12).alias("for_trexp"), stable("for_trpow", 12).alias("for_trpow")),
        "trexp_walks": lambda s, d: acyclicity.trexp(_flow(s, d), 8).select(stable("trexp", 12).alias("trexp")),
        "trpow_walks": lambda s, d: acyclicity.trpow(_flow(s, d), 25, 6).select(stable("trpow", 9).alias("trpow")),
        "spectral_radius_power": lambda s, d: acyclicity.spectral_radius(seq(s, d), 8).select(stable("radius").alias("radius")),
        "peel_rounds": lambda s, d: acyclicity.peel_rounds(planted(s), 4),
        "is_dag_audit": lambda s, d: acyclicity.dag_audit(planted(s)),
        "break_cycles": lambda s, d: acyclicity.break_cycles(base.order_sequence(s, d).where("w > 0.45")).select("src", "dst", stable("w").alias("w")),
        "cyclic_components": lambda s, d: acyclicity.components(base.order_sequence(s, d).where("w > 0.45")).select("node", "component"),
        "cost_model": lambda s, d: metrics.cost_model(base.order_sequence(s, d), 5),
        "planted_er_edges": lambda s, d: planted(s).select("src", "dst", stable("w").alias("w")),
        "planted_sf_edges": lambda s, d: simulate.sf_dag(s, 50, 4, SEED),
        "planted_noise_gauss": _noise("gauss"), "planted_noise_exp": _noise("exp"), "planted_noise_gumbel": _noise("gumbel"),
        "planted_samples": _samples,
        "edge_confusion": lambda s, d: metrics.edge_confusion(*_sequence_guess(s, d)),
        "metrics_planted": lambda s, d: _measured(metrics.edge_confusion(planted(s), guess(planted(s))), D),
        "metrics_table_replay": _replay,
        "metrics_compare": lambda s, d: metrics.compare(guess(planted(s)), guess(planted(s)).where("w > 0.3"), planted(s)),
        "roc_auc": _auc,
        "correlation_arithmetic": lambda s, d: metrics.trace_correlation(_order_trace(s, d), "run").select("run", stable("corr").alias("corr"), "n"),
        "audit_arithmetic": lambda s, d: metrics.audit_constraint(_order_trace(s, d), 1e-2, 20).select("consistent", stable("corr").alias("corr"), "most_edges", "threshold_holds"),
        "readout_arithmetic": _readout,
        "summary_arithmetic": lambda s, d: grid.summarise(_results(s), "graph", "noise", "method").select("graph", "noise", "method", "runs", *[stable(c).alias(c) for c in ("f1_mean", "f1_dev", "shd_mean", "shd_dev")]),
        "cube_arithmetic": lambda s, d: grid.cube(_order_results(s, d), "graph", "noise").select("graph", "noise", stable("f1_mean").alias("f1_mean"), "runs"),
        "speedup_arithmetic": lambda s, d: metrics.speedup(_results(s), "trexp", "bound", "graph", "noise").select("graph", "noise", *[stable(c).alias(c) for c in ("slow", "fast", "speedup")]),
        "edge_set_algebra": _algebra,
    }


def oracle_sql() -> dict[str, str]:
    s6 = lambda c, n=6: f"round({c}, {n}) + 0.0 AS {c}"
    seq, flow = base.order_sequence_sql, base.net_flow_sql
    profile = lambda c, k: c.then(" UNION ALL ".join(f"SELECT {t} AS k, round(sum(scale), 6) + 0.0 AS bound FROM st{t}" for t in range(k + 1)))
    power = seq().add("a", "SELECT src, dst, w * w AS a FROM edges").add("v0", "SELECT DISTINCT node, 1.0::DOUBLE AS v FROM (SELECT src AS node FROM a UNION ALL SELECT dst FROM a)")
    for t in range(1, 9):
        power.add(f"y{t}", f"SELECT src AS node, sum(a * v) AS v FROM v{t - 1} JOIN a ON node = dst GROUP BY src").add(f"v{t}", f"SELECT node, v / (SELECT sum(v) FROM y{t}) AS v FROM y{t}")
    peel = planted_sql().add("c0", "SELECT src, dst FROM planted")
    for t in range(1, 5):
        peel.add(f"c{t}", f"SELECT src, dst FROM c{t - 1} WHERE src IN (SELECT dst FROM c{t - 1}) AND dst IN (SELECT src FROM c{t - 1})")
    trpow = sqlgen.walks(flow(), "flow", 6).then("SELECT round(sum(closed * CASE length WHEN 1 THEN 25 WHEN 2 THEN 300 WHEN 3 THEN 2300 WHEN 4 THEN 12650 WHEN 5 THEN 53130 ELSE 177100 END), 9) + 0.0 AS trpow FROM closed")
    replay = "SELECT * FROM (VALUES " + ", ".join(f"('{a}', '{b}', {d}, {t}, {p}, {tp}, {r})" for a, b, d, t, p, tp, r in REPLAY) + ') v(network, method, d, "true", predicted, tp, reversed)'
    return {
        "bound_node_masses": sqlgen.forward(seq(), "edges", 0, 0.9).then(f"SELECT node, {s6('out_mass')}, {s6('in_mass')}, {s6('scale')} FROM st0"),
        "bound_rescale_round": sqlgen.forward(seq(), "edges", 1, 0.9).then(f"SELECT src, dst, {s6('w')}, {s6('a')} FROM adj1"),
        "bound_profile_k5": profile(sqlgen.forward(seq(), "edges", 5, 0.9), 5),
        "bound_profile_alpha_half": profile(sqlgen.forward(flow(), "flow", 4, 0.5), 4),
        "bound_max_aggregate": sqlgen.forward(seq(), "edges", 5, 0.9).then("SELECT round(max(scale), 6) + 0.0 AS bound FROM st5"),
        "bound_peeled_first": "SELECT 0.0::DOUBLE AS bound",
        "bound_partials": sqlgen.gradient(sqlgen.forward(seq(), "edges", 0, 0.9), 0, 0.9).then(f"SELECT node, {s6('fx')}, {s6('fy')} FROM pt0"),
        "bound_gradient_dense0": sqlgen.gradient(sqlgen.forward(seq(), "edges", 0, 0.9), 0, 0.9).then("SELECT x.node AS src, y.node AS dst, round(x.fx + y.fy, 6) + 0.0 AS g FROM pt0 x, pt0 y WHERE x.node <> y.node"),
        "bound_gradient_k1": sqlgen.gradient(sqlgen.forward(seq(), "edges", 1, 0.9), 1, 0.9).then(f"SELECT src, dst, {s6('w')}, {s6('g')} FROM grad"),
        "bound_gradient_k5": sqlgen.gradient(sqlgen.forward(flow(), "flow", 5, 0.9), 5, 0.9).then(f"SELECT src, dst, {s6('w')}, {s6('g')} FROM grad"),
        "bound_thresholds": "SELECT (k * 50)::INTEGER AS d, round(pow(10.0, -k), 6) + 0.0 AS eps, round(ln(1 + pow(10.0, -k) / (k * 50)), 12) + 0.0 AS for_trexp, round(exp(ln(1 + pow(10.0, -k) / (k * 50)) / (k * 50)) - 1, 12) + 0.0 AS for_trpow FROM (SELECT DISTINCT p_partkey % 6 + 1 AS k FROM part)",
        "trexp_walks": sqlgen.walks(flow(), "flow", 8).then("SELECT round(sum(closed / factorial(length::INTEGER)::DOUBLE), 12) + 0.0 AS trexp FROM closed"),
        "trpow_walks": trpow,
        "spectral_radius_power": power.then("SELECT round((SELECT sum(v) FROM y8) / (SELECT sum(v) FROM v7), 6) + 0.0 AS radius"),
        "peel_rounds": peel.then(" UNION ALL ".join(f"SELECT {t} AS round, count(*)::BIGINT AS n_edges FROM c{t}" for t in range(5))),
        "is_dag_audit": planted_sql().add("RECURSE reach", "SELECT src, dst FROM planted UNION SELECT r.src, p.dst FROM reach r JOIN planted p ON r.dst = p.src").then("SELECT (SELECT count(*) FROM planted)::BIGINT AS n_edges, (SELECT count(*) FROM reach WHERE src = dst)::BIGINT AS core_edges, NOT EXISTS (SELECT 1 FROM reach WHERE src = dst) AS acyclic"),
        "cyclic_components": seq().add("e", "SELECT src, dst FROM edges WHERE w > 0.45").add("RECURSE reach", "SELECT src, dst FROM e UNION SELECT r.src, x.dst FROM reach r JOIN e x ON r.dst = x.src").then("SELECT a.src AS node, min(a.dst) AS component FROM reach a JOIN reach b ON a.src = b.dst AND a.dst = b.src GROUP BY a.src"),
        "cost_model": seq().then("SELECT count(*)::BIGINT AS s, (SELECT count(DISTINCT n) FROM (SELECT src AS n FROM edges UNION ALL SELECT dst FROM edges))::BIGINT AS d, (count(*) * 16)::BIGINT AS bytes, (count(*) * 11)::BIGINT AS touched FROM edges"),
        "planted_er_edges": planted_sql().then(f"SELECT src, dst, {s6('w')} FROM planted"),
        "planted_noise_gauss": _noise_sql("gauss"), "planted_noise_exp": _noise_sql("exp"), "planted_noise_gumbel": _noise_sql("gumbel"),
        "planted_samples": _samples_sql(),
        "edge_confusion": _sequence_guess_sql().then(confusion_sql("flow", "guess")),
        "metrics_planted": planted_sql().add("guess", GUESS_SQL).add("conf", confusion_sql("planted", "guess")).then(f'SELECT {MEASURES_SQL}, round((reversed + extra)::DOUBLE / ({D} * {D - 1} / 2 - "true"), 6) + 0.0 AS fpr FROM conf'),
        "metrics_table_replay": f'SELECT network, method, round(2.0::DOUBLE * tp / (predicted + "true"), 9) + 0.0 AS f1, round(reversed::DOUBLE / predicted, 9) + 0.0 AS fdr, round(tp::DOUBLE / "true", 9) + 0.0 AS tpr, round((predicted - tp)::DOUBLE / (d::DOUBLE * (d - 1) / 2 - "true"), 9) + 0.0 AS fpr, (predicted - tp - reversed + "true" - tp - reversed + reversed)::BIGINT AS shd FROM ({replay})',
        "metrics_compare": planted_sql().add("guess", GUESS_SQL).add("less", "SELECT * FROM guess WHERE w > 0.3").then("SELECT (SELECT count(*) FROM guess g WHERE NOT EXISTS (SELECT 1 FROM less l WHERE l.src = g.src AND l.dst = g.dst))::BIGINT AS only_a, 0::BIGINT AS only_b, (SELECT count(*) FROM guess g JOIN planted p USING (src, dst))::BIGINT AS right_a, (SELECT count(*) FROM less g JOIN planted p USING (src, dst))::BIGINT AS right_b"),
        "roc_auc": _auc_sql(),
        "correlation_arithmetic": f"SELECT run, round(corr(bound, trexp), 6) + 0.0 AS corr, count(*)::BIGINT AS n FROM ({ORDER_TRACE_SQL}) GROUP BY run",
        "audit_arithmetic": f"SELECT min((trexp <= 20 * (exp(bound) - 1) + 1e-9)::INTEGER)::INTEGER AS consistent, round(corr(bound, trexp), 6) + 0.0 AS corr, max(nnz)::BIGINT AS most_edges, min((bound > ln(1 + 0.01 / 20) OR trexp <= 0.01)::INTEGER)::INTEGER AS threshold_holds FROM ({ORDER_TRACE_SQL})",
        "readout_arithmetic": _readout_sql(),
        "summary_arithmetic": f"SELECT graph, noise, method, count(*)::BIGINT AS runs, round(avg(f1), 6) + 0.0 AS f1_mean, round(stddev_pop(f1), 6) + 0.0 AS f1_dev, round(avg(shd), 6) + 0.0 AS shd_mean, round(stddev_pop(shd), 6) + 0.0 AS shd_dev FROM ({RESULTS_SQL}) GROUP BY 1, 2, 3",
        "cube_arithmetic": f"SELECT graph, noise, round(avg(f1), 6) + 0.0 AS f1_mean, count(*)::BIGINT AS runs FROM (SELECT {ORDER_RESULTS} FROM orders) GROUP BY CUBE (graph, noise)",
        "speedup_arithmetic": f"SELECT graph, noise, round(slow, 6) + 0.0 AS slow, round(fast, 6) + 0.0 AS fast, round(slow / fast, 6) + 0.0 AS speedup FROM (SELECT graph, noise, avg(seconds) FILTER (method = 'trexp') AS slow, avg(seconds) FILTER (method = 'bound') AS fast FROM ({RESULTS_SQL}) GROUP BY 1, 2) WHERE slow IS NOT NULL AND fast IS NOT NULL",
        "edge_set_algebra": _sequence_guess_sql().add("a", "SELECT src, dst FROM flow").add("b", "SELECT src, dst FROM guess").then("SELECT 'common' AS part, count(*)::BIGINT AS n FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'only first', count(*)::BIGINT FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'only second', count(*)::BIGINT FROM (SELECT * FROM b EXCEPT SELECT * FROM a) UNION ALL SELECT 'either', count(*)::BIGINT FROM (SELECT * FROM a UNION SELECT * FROM b)"),
    }
