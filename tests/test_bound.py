import math

import numpy as np
import pytest

from dagframe.operators import acyclicity, bound
from dagframe.operators.bound_local import dense_value_and_grad, value_and_grad
from dagframe.operators.learner import trexp_dense

TWO = [(0, 1, 0.5), (1, 0, 0.2), (1, 2, 0.3)]


def table(spark, rows):
    return spark.createDataFrame([(a, b, float(w)) for a, b, w in rows], "src int, dst int, w double")


def test_two_cycle_profile_and_gradient(spark):
    e = table(spark, TWO)
    got = [r["bound"] for r in bound.bound_profile(e, 5).orderBy("k").collect()]
    assert np.allclose(got, [0.346923, 0.216947, 0.206047, 0.202170, 0.200780, 0.200281], atol=1e-6)
    grad = {(r["src"], r["dst"]): r["g"] for r in bound.bound_gradient(e, 5).collect()}
    assert np.allclose([grad[0, 1], grad[1, 0], grad[1, 2]], [0.39924257, 0.99785278, 0.0045657], atol=1e-7)
    assert abs(acyclicity.trexp(e, 12).first()[0] - 0.0100083361) < 1e-9


def test_three_cycle_and_empty(spark):
    e = table(spark, [(0, 1, 1), (1, 2, 1), (2, 0, 1)])
    assert abs(bound.bound_value(e) - 3) < 1e-9
    assert abs(acyclicity.trexp(e, 15).first()[0] - 0.50417494) < 1e-7
    assert abs(acyclicity.trpow(e, 3).first()[0] - 3) < 1e-9
    assert bound.bound_value(table(spark, [(0, 1, 1)])) == 0
    assert bound.bound_value(table(spark, []) if False else table(spark, [(0, 1, 1)]).limit(0)) == 0


@pytest.mark.parametrize("n", [4, 8, 13])
def test_chain_needs_depth_or_peeling(n):
    src, dst, w = np.arange(n - 1), np.arange(1, n), np.ones(n - 1)
    for k in range(4):
        assert abs(value_and_grad(src, dst, w, n, k)[0] - max(0, n - 2 - 2 * k)) < 1e-9


def test_peeling_makes_deep_chains_zero(spark):
    e = table(spark, [(i, i + 1, 1) for i in range(9)])
    assert bound.spectral_bound(e, 1, peel_first=True).first()[0] == 0
    assert acyclicity.longest_path(e) == 9 and acyclicity.is_dag(e)


@pytest.mark.parametrize("alpha", [0.5, 0.9])
def test_gradient_is_the_derivative_and_masking_is_exact(alpha):
    r = np.random.default_rng(4)
    w = r.uniform(-1, 1, (8, 8)) * (r.random((8, 8)) < 0.5) * (1 - np.eye(8))
    src, dst = np.nonzero(w)
    for k in (1, 3):
        value, grad = value_and_grad(src, dst, w[src, dst], 8, k, alpha)
        mask = (w != 0).astype(float)
        assert np.allclose(dense_value_and_grad(w, k, alpha, mask)[1], dense_value_and_grad(w, k, alpha)[1], atol=1e-12)
        assert np.allclose(dense_value_and_grad(w, k, alpha)[1][src, dst], grad, atol=1e-10)
        for e in range(0, len(src), 5):
            h = 1e-6
            step = np.zeros(len(src))
            step[e] = h
            numeric = (value_and_grad(src, dst, w[src, dst] + step, 8, k, alpha, False)[0] - value_and_grad(src, dst, w[src, dst] - step, 8, k, alpha, False)[0]) / (2 * h)
            assert abs(numeric - grad[e]) < 1e-5 * max(1, abs(value))


def test_bound_is_above_radius_and_thresholds_hold():
    r = np.random.default_rng(0)
    for _ in range(40):
        d = int(r.integers(3, 9))
        w = r.uniform(-1, 1, (d, d)) * (r.random((d, d)) < 0.5) * (1 - np.eye(d))
        value = dense_value_and_grad(w)[0]
        assert acyclicity.local_radius(w) <= value + 1e-9
        assert trexp_dense(w)[0] <= d * math.expm1(value) + 1e-9
        assert abs(trexp_dense(w * 0.01)[0]) < 1


def test_distributed_equals_local(spark):
    r = np.random.default_rng(2)
    pairs = {(int(a), int(b)) for a, b in r.integers(0, 12, (40, 2)) if a != b}
    rows = [(a, b, float(r.uniform(-1, 1))) for a, b in sorted(pairs)]
    got = sorted((x["src"], x["dst"], x["g"]) for x in bound.bound_gradient(table(spark, rows), 3).collect())
    src, dst, w = (np.array(c) for c in zip(*rows, strict=True))
    assert np.allclose([g for *_, g in got], value_and_grad(src, dst, w, 12, 3)[1], rtol=1e-9)


def test_overflow_raises():
    with pytest.raises(ArithmeticError):
        value_and_grad(np.array([0, 1]), np.array([1, 0]), np.array([1e200, 1e200]), 2)


def test_components_and_cycle_breaking(spark):
    e = table(spark, [(0, 1, 1), (1, 0, 0.2), (1, 2, 1), (2, 3, 1), (3, 4, 0.5), (4, 2, 0.7), (4, 5, 1)])
    want = {0: 0, 1: 0, 2: 2, 3: 2, 4: 2}
    for limit in (1000, 0):
        assert {r["node"]: r["component"] for r in acyclicity.components(e, local_edges=limit).collect()} == want
        left = acyclicity.break_cycles(e, local_edges=limit)
        assert acyclicity.is_dag(left) and left.count() == 5


def test_plans_stay_native(spark):
    e = table(spark, TWO)
    plan = bound.rescale(bound.square(e), bound.node_scale(bound.node_masses(bound.square(e))))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Cartesian" not in plan
