"""Invariants of the bound, over random graphs; learner options."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from dagframe.operators import learner, simulate
from dagframe.operators.bound_local import value_and_grad
from dagframe.operators.learner import LearnerParams
from dagframe.plans.planner import choose_engine, moment_plan

graphs = st.integers(2, 9).flatmap(lambda d: st.tuples(st.just(d), st.lists(st.tuples(st.integers(0, d - 1), st.integers(0, d - 1), st.floats(0.05, 2)), min_size=1, max_size=25)))


def arrays(rows):
    own = {(a, b): w for a, b, w in rows if a != b}
    if not own:
        return np.zeros(0, int), np.zeros(0, int), np.zeros(0)
    src, dst = (np.array(x) for x in zip(*own, strict=True))
    return src, dst, np.array(list(own.values()))


@settings(max_examples=60, deadline=None)
@given(graphs, st.integers(0, 4), st.floats(0.2, 3))
def test_invariants(graph, k, c):
    d, rows = graph
    src, dst, w = arrays(rows)
    value = value_and_grad(src, dst, w, d, k)[0]
    assert np.isclose(value_and_grad(src, dst, c * w, d, k)[0], c * c * value, rtol=1e-7, atol=1e-12)
    p = np.random.default_rng(d).permutation(d)
    assert np.isclose(value_and_grad(p[src], p[dst], w, d, k)[0], value, rtol=1e-9, atol=1e-12)
    assert np.isclose(value_and_grad(dst, src, w, d, 0, 0.1)[0], value_and_grad(src, dst, w, d, 0, 0.9)[0], rtol=1e-9, atol=1e-12)
    full = np.zeros((d, d))
    full[src, dst] = w
    assert np.abs(np.linalg.eigvals(full * full)).max() <= value + 1e-6 * max(1, value)
    order = src < dst
    deep = value_and_grad(src[order], dst[order], w[order], d, d)[0]
    assert abs(deep) < 1e-12  # a graph along an order has no cycle


@pytest.mark.parametrize("options", [{"penalty_gradient": "as_printed"}, {"init": "redraw"}, {"support": "screened", "screen": 3}, {"support": "random", "zeta": 0.4}, {"theta": 0.01}, {"constraint": "trpow"}, {"constraint": "radius"}, {"stop_on": "bound", "eps": 0.2}, {"rho_growth": 1.0}])
def test_learner_options(options):
    truth = simulate.local_dag("er", 7, 1.5, 2)
    x = simulate.local_sample(truth, 200, "exp", 1)
    x = x - x.mean(0)
    w, trace, kept = learner.fit_dense(x.T @ x / 200, LearnerParams(t_outer=6, t_inner=60, **options), (0.1,))
    assert np.isfinite(w).all() and (np.diag(w) == 0).all() and 1 <= len(trace) <= 6 and 0.1 in kept
    assert all(t["nnz"] <= 42 and np.isfinite(t["loss"]) for t in trace)


def test_scalars_and_plans():
    assert learner.raise_multiplier(1, 2, 0.5) == 2 and learner.grow_penalty(2, 1.5) == 3 and learner.grow_penalty(2, 1) == 2
    assert learner.should_stop(0.5, 1e-9, 1e-4) and not learner.should_stop(0.5, 1e-9, 1e-4, "bound") and learner.should_stop(0.5, 1e-9, 1e-4, "trexp")
    assert [choose_engine(100, 50), choose_engine(10**5, 10**6), choose_engine(10**6, 10**9)] == ["dense", "local_sparse", "distributed"]
    assert [moment_plan(8, 10, 80), moment_plan(1000, 10, 9000), moment_plan(10**5, 10, 100)] == ["wide", "blocked", "cells"]


def test_sparse_start_is_sparse_and_bounded(spark):
    d = 3000
    e = learner.init_edges(spark, d, 1e-3, 5).toPandas()
    assert 0.9 * 9000 < len(e) <= 9000 and (e.src != e.dst).all() and not e.duplicated(["src", "dst"]).any()
    assert (e.w.abs() <= (6 / (2 * d)) ** 0.5 + 1e-12).all()
