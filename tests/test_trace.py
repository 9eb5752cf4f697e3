"""The exponential trace of sparse runs is whole at any size: closed walks of all lengths, whatever the number of nodes."""

from math import factorial

import numpy as np
import pytest

from dagframe.operators import learner
from dagframe.operators.learner import LearnerParams


def rings(n, steps, a):
    src = np.arange(n * steps)
    return src, np.where(src % steps == steps - 1, src - steps + 1, src + 1), np.full(n * steps, np.sqrt(a))


def test_long_cycles_count_in_large_graphs():
    one = sum(4 * 0.5 ** (4 * k) / factorial(4 * k) for k in range(1, 5))
    for n in (1, 499, 501, 3000):  # 4 to 12,000 nodes, no closed walk of two or three steps
        got = learner.trexp_sparse(*rings(n, 4, 0.5), 4 * n)
        assert abs(got - n * one) < 1e-12 * n * one


@pytest.mark.parametrize(("n", "density", "high"), [(60, 0.04, 0.6), (300, 0.01, 1.2), (40, 0.3, 0.9), (5, 0.8, 1.0), (30, 0.9, 1.5)])
def test_equal_to_the_dense_trace(n, density, high):
    r = np.random.default_rng(n)
    w = np.where(r.random((n, n)) < density, r.uniform(-high, high, (n, n)), 0.0)
    i, j = np.nonzero(w)
    want = learner.trexp_dense(w)[0]
    assert abs(learner.trexp_sparse(i, j, w[i, j], n) - want) < 1e-11 * want


def test_few_ways_at_a_time_and_empty_graphs(monkeypatch):
    r = np.random.default_rng(8)
    i, j = np.nonzero(r.random((80, 80)) < 0.06)
    w = r.uniform(0.1, 0.9, len(i))
    want = learner.trexp_sparse(i, j, w, 80)
    monkeypatch.setattr(learner, "WALKS", 50)
    assert abs(learner.trexp_sparse(i, j, w, 80) - want) < 1e-11 * want
    assert learner.trexp_sparse(i[:0], j[:0], w[:0], 80) == 0 == learner.trexp_sparse(np.array([0, 1]), np.array([1, 2]), np.ones(2), 3)


def test_a_run_is_the_same_in_any_number_of_copies():
    src, dst, w = rings(1, 4, 0.25)
    for n in (1, 700):
        s, t, v = (np.concatenate([x + 4 * c * (k < 2) for c in range(n)]) for k, x in enumerate((src, dst, w)))
        trace = learner.fit_sparse(lambda a, b: np.where(a == b, 1.0, 0.3), s, t, v, 4 * n, LearnerParams(t_outer=1, t_inner=3, k=1, lam=0.01, rho0=1.0 / n, eta0=0.0, stop_on="trexp"))[3]
        first = trace[0]["trexp"] / n if n == 1 else first
        assert first > 0 and abs(trace[0]["trexp"] / n - first) < 1e-9 * first
