import numpy as np
import pytest

from dagframe.operators import baseline, grid, learner, loss, metrics, moments, simulate
from dagframe.operators.learner import LearnerParams


def edges(spark, rows):
    return spark.createDataFrame([(a, b, float(w)) for a, b, w in rows], "src int, dst int, w double")


def _matrix(spark, c):
    d = len(c)
    return spark.createDataFrame([(i, j, float(c[i, j])) for i in range(d) for j in range(i, d)], "a int, b int, c double")


def _planted(d=8, seed=3, kind="er"):
    truth = simulate.local_dag(kind, d, 1.5, seed)
    x = simulate.local_sample(truth, 400, "gauss", seed)
    return truth, x, x.T @ x / len(x)


def test_moments_agree(spark):
    r = np.random.default_rng(1)
    x = r.standard_normal((60, 5)) * (r.random((60, 5)) < 0.7)
    want = x.T @ x / 60
    wide = spark.createDataFrame(x.tolist(), ["a", "b", "c", "d", "e"])
    cells = spark.createDataFrame([(i, j, float(x[i, j])) for i in range(60) for j in range(5) if x[i, j]], "sample_id int, node_id int, x double")
    arrays = spark.createDataFrame([(row.tolist(),) for row in x], "v array<double>")
    for got in (moments.from_wide(wide, list("abcde")), moments.from_cells(cells, 60), moments.from_cells(cells, 60, chunk=2), moments.from_vectors(arrays, "v", 2)):
        assert np.allclose(moments.to_matrix(got, 5), want)


def test_losses_agree(spark):
    _, x, c = _planted()
    e = edges(spark, [(0, 1, 0.5), (2, 1, -0.3), (3, 4, 0.2)])
    cells = spark.createDataFrame([(i, j, float(x[i, j])) for i in range(len(x)) for j in range(8)], "sample_id int, node_id int, x double")
    a, b = loss.from_samples(cells, e, len(x)).first(), loss.from_moments(_matrix(spark, c), e).first()
    assert np.allclose(a, b)
    g1 = sorted(map(tuple, loss.gradient_from_samples(cells, e, len(x)).collect()))
    g2 = sorted(map(tuple, loss.gradient_from_moments(_matrix(spark, c), e).collect()))
    assert np.allclose(g1, g2)


@pytest.mark.parametrize("constraint", ["bound", "trexp"])
def test_learner_finds_a_planted_graph(constraint):
    f1 = []
    for seed in (1, 2, 3):
        truth, _, c = _planted(8, seed)
        w, trace, _ = learner.fit_dense(c, LearnerParams(t_outer=40, constraint=constraint, lam=0.05))
        q = np.abs(w) >= 0.3
        f1.append(2 * (q & (truth != 0)).sum() / ((truth != 0).sum() + q.sum()))
        assert trace[-1][constraint] < trace[0][constraint] and min(trace[-1]["bound"], trace[-1]["trexp"]) <= 1e-4
    assert np.mean(f1) > 0.75


def test_bound_keeps_up_with_the_exact_measure(spark):
    cells = [("er", noise, 10, seed, m) for noise in ("gauss", "gumbel") for seed in (1, 2) for m in ("bound", "trexp")]
    got = grid.best_cell(baseline.planted_runs(spark, cells, LearnerParams(t_outer=30)), "graph", "noise", "d", "seed", "method").toPandas()
    by = got.groupby("method")["f1"].mean()
    assert by["bound"] > by["trexp"] - 0.1
    assert got[got.method == "bound"]["corr"].mean() > 0.8


def test_engines_agree_on_steps(spark):
    _, _, c = _planted(6, 5)
    m = _matrix(spark, c)
    rows = [(0, 1, 0.1), (1, 2, -0.2), (2, 0, 0.1), (3, 4, 0.3), (4, 5, 0.1)]
    p = LearnerParams(t_outer=1, t_inner=3, k=2)
    got = sorted(map(tuple, learner.inner(edges(spark, rows), m, p, 1.0, 1.0, 3).collect()))
    src, dst, w = (np.array(x) for x in zip(*rows, strict=True))
    s2, d2, w2, _ = learner.fit_sparse(lambda a, b: c[a, b], src, dst, w.astype(float), 6, p)
    assert np.allclose([x[2] for x in got], [v for _, _, v in sorted(zip(s2, d2, w2, strict=True))], rtol=1e-8)


def test_search_baselines(spark):
    r = np.random.default_rng(8)
    a = r.standard_normal(3000)
    b = 1.5 * a + 0.5 * r.standard_normal(3000)
    x = np.stack([a, b, r.standard_normal(3000)], 1)
    m = _matrix(spark, x.T @ x / 3000)
    skeleton = lambda f: {frozenset((e["src"], e["dst"])) for e in f.collect()}
    assert skeleton(baseline.exhaustive(m, 3, 3000)) == skeleton(baseline.hill_climb(m, 3, 3000)) == {frozenset((0, 1))}
    assert baseline.correlation_graph(m, 1).first()[:2] == (0, 1)
    fitted = learner.refit(m, edges(spark, [(0, 1, 1)])).first()
    assert abs(fitted["w"] - 1.5) < 0.05 and abs(fitted["variance"] - 0.25) < 0.03


def test_confusion_and_replay(spark):
    t, p = edges(spark, [(0, 1, 1), (1, 2, 1)]), edges(spark, [(1, 0, 1), (1, 2, 1), (0, 2, 1)])
    r = metrics.measures(metrics.edge_confusion(t, p).withColumn("d", metrics.F.lit(3))).first()
    assert (r["tp"], r["reversed"], r["extra"], r["missing"], r["shd"]) == (1, 1, 1, 0, 2) and abs(r["f1"] - 0.4) < 1e-12
    auc = metrics.roc_auc(t, p, 3).first()[0]
    assert abs(auc - (1 * (0.5 * 2 + 2) + 1 * (2 * 0.5)) / 8) < 1e-12


def test_simulation_is_repeatable_and_acyclic(spark):
    from dagframe.operators.acyclicity import is_dag

    for g in (simulate.er_dag(spark, 20), simulate.sf_dag(spark, 30), simulate.er_dag_large(spark, 1000, 2000)):
        assert is_dag(simulate.weights(g)) and g.count() == g.distinct().count()
    e = simulate.weights(simulate.er_dag(spark, 6)).cache()
    x = {r["sample_id"]: r["x"] for r in simulate.sample(spark, e, 20, 6).collect()}
    levels = simulate.sample_levels(e, simulate.noise_cells(spark, 20, 6), 6)
    for r in levels.collect():
        assert abs(x[r["sample_id"]][r["node_id"]] - r["x"]) < 1e-9


def _cells(spark, x):
    return spark.createDataFrame([(i, j, float(x[i, j])) for i in range(len(x)) for j in range(x.shape[1])], "sample_id int, node_id int, x double")


def test_whole_batches_equal_the_moments_run(spark):
    _, x, c = _planted(5, 4)
    m, cells = _matrix(spark, c), _cells(spark, x)
    one = LearnerParams(t_outer=2, t_inner=8, k=2, tol_inner=0.0, eps=0.0)
    start = edges(spark, [(0, 1, 0.1), (1, 2, -0.2), (2, 0, 0.1), (3, 4, 0.3)])
    for engine, begin in (("dense", None), ("local_sparse", start), ("distributed", start)):
        p = one if engine != "distributed" else learner.replace(one, t_outer=1, t_inner=2, k=1)
        a = learner.fit(m, 5, p, engine, begin)[0].toPandas().sort_values(["src", "dst"])
        b = learner.fit(m, 5, learner.replace(p, batch=len(x)), engine, begin, cells=cells)[0].toPandas().sort_values(["src", "dst"])
        assert np.allclose(a["w"], b["w"], atol=1e-9), engine


def test_small_batches_agree_between_engines_and_learn(spark):
    truth, x, c = _planted(5, 4)
    m, cells = _matrix(spark, c), _cells(spark, x)
    rows = [(0, 1, 0.1), (1, 2, -0.2), (2, 0, 0.1), (3, 4, 0.3)]
    p = LearnerParams(t_outer=1, t_inner=2, k=1, batch=100, eps=0.0)
    a = learner.fit(m, 5, p, "local_sparse", edges(spark, rows), cells)[0].toPandas().sort_values(["src", "dst"])
    b = learner.fit(m, 5, p, "distributed", edges(spark, rows), cells)[0].toPandas().sort_values(["src", "dst"])
    assert np.allclose(a["w"], b["w"], rtol=1e-8)
    got = learner.fit(m, 5, LearnerParams(t_outer=12, t_inner=60, batch=100, lam=0.05), "dense", cells=cells)[0].toPandas()
    found = {(r.src, r.dst) for r in got.itertuples() if abs(r.w) >= 0.3}
    want = set(zip(*np.nonzero(truth), strict=True))
    assert 2 * len(found & want) / (len(found) + len(want)) > 0.6
    with pytest.raises(ValueError):
        learner.fit(m, 5, p, "dense")


@pytest.mark.parametrize("options", [{"penalty_gradient": "as_printed", "lam": 0.3}, {"theta": 0.055}])
def test_engines_agree_under_options(spark, options):
    _, _, c = _planted(6, 5)
    m, rows = _matrix(spark, c), [(0, 1, 0.1), (1, 2, -0.2), (2, 0, 0.1), (3, 4, 0.3), (4, 5, 0.1), (5, 3, 0.06)]
    p = LearnerParams(t_outer=1, t_inner=2, k=1, eps=0.0, **options)
    a, b = (learner.fit(m, 6, p, e, edges(spark, rows))[0].toPandas().sort_values(["src", "dst"]) for e in ("local_sparse", "distributed"))
    assert list(zip(a.src, a.dst)) == list(zip(b.src, b.dst)) and np.allclose(a.w, b.w, rtol=1e-8)
    with pytest.raises(ValueError):
        learner.fit(m, 6, learner.replace(p, constraint="trexp"), "local_sparse", edges(spark, rows))


def test_trace_on_the_cyclic_core():
    r = np.random.default_rng(2)
    w = np.where(r.random((60, 60)) < 0.04, r.uniform(-0.6, 0.6, (60, 60)), 0.0)
    np.fill_diagonal(w, 0.0)
    i, j = np.nonzero(w)
    assert abs(learner.trexp_core(i, j, w[i, j], 60) - learner.trexp_dense(w)[0]) < 1e-12
    learner.CORE, kept = 0, learner.CORE
    a = w * w
    low = learner.trexp_core(i, j, w[i, j], 60)
    learner.CORE = kept
    assert abs(low - (np.trace(a @ a) / 2 + np.trace(a @ a @ a) / 6)) < 1e-12


def test_fisher_at_log_scale(spark):
    from math import comb

    from dagframe.operators import monitor

    rows = [([1], 40, 12, 900, 1100), ([2], 3, 30, 400, 500), ([3], 0, 0, 10, 10), ([4], 5, 0, 5, 0)]
    got = {r["path"][0]: r["p"] for r in monitor.path_test(spark.createDataFrame(rows, "path array<int>, n_now long, n_prev long, total_now long, total_prev long"), "fisher").collect()}
    for path, x, y, a, b in rows:
        exact = sum(comb(a, i) * comb(b, x + y - i) for i in range(x, min(x + y, a) + 1) if x + y - i <= b) / comb(a + b, x + y)
        assert abs(got[path[0]] - exact) < 1e-9, path
    big = spark.createDataFrame([([1], 51_000, 50_000, 10_000_000, 10_000_000)], "path array<int>, n_now long, n_prev long, total_now long, total_prev long")
    assert 1e-4 < monitor.path_test(big, "fisher").first()["p"] < 2e-3
