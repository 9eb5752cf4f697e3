"""Sparse runs hold edges and moments in files: the same numbers, and little memory an edge."""

import tracemalloc

import numpy as np
import pytest

from dagframe.operators import learner, mapped
from dagframe.operators.bound_local import value_and_grad


@pytest.mark.parametrize("few", [False, True])
def test_bound_and_fit_are_those_of_arrays(monkeypatch, few):
    if few:
        monkeypatch.setattr(mapped, "AT_ONCE", 7)
    r = np.random.default_rng(4)
    x = r.normal(size=(60, 25))
    c = x.T @ x / 60
    i, j = np.nonzero((r.random((25, 25)) < 0.2) & ~np.eye(25, dtype=bool))
    w, (a, b) = r.normal(size=len(i)), np.nonzero(np.triu(np.ones((25, 25))))
    edges = mapped.Edges(i, j, w, 25)
    edges.hold(mapped.pair_lookup(a, b, c[a, b], 25))
    for gone in (0.0, 0.4):
        edges.alive &= r.random(len(edges.alive)) >= gone
        edges.w[~edges.alive] = 0.0
        edges.compact()
        src, dst, held = edges.rows()
        full = np.zeros((25, 25))
        full[src, dst] = held
        assert abs(edges.fit() - np.trace(c - 2 * c @ full + full.T @ c @ full)) < 1e-10
        for alpha in (0.9, 0.5, 1.0):
            value, g = value_and_grad(src, dst, held, 25, 5, alpha)
            assert np.isclose(edges.bound(5, alpha), value) and np.allclose(2 * edges.p * edges.w, g, rtol=1e-9, atol=1e-12)


def test_collected_rows(spark):
    table = spark.range(5000).selectExpr("cast(id as int) a", "id * id b", "id / 7 c").repartition(3)
    got = mapped.collected(table, 5000)
    order = np.argsort(got["a"])
    assert (got["a"][order] == np.arange(5000)).all() and (got["b"][order] == np.arange(5000) ** 2).all() and np.allclose(got["c"][order], np.arange(5000) / 7)
    with pytest.raises(ValueError):
        mapped.collected(table, 4999)


def test_a_large_run_takes_little_memory():
    d = 60_000
    dst = np.repeat(np.arange(d), 5)
    src = (dst + np.tile([1, 2, 3, 5, 8], d)) % d
    p = learner.LearnerParams(t_outer=1, t_inner=2, lam=0.01, theta=1e-3, stop_on="bound")
    tracemalloc.start()
    try:
        assert len(learner.fit_sparse(lambda a, b: np.where(a == b, 1.0, 0.2), src, dst, np.full(5 * d, 0.05), d, p)[3]) == 1
        assert tracemalloc.get_traced_memory()[1] < 80e6  # 25 pairs of parents a node took over 100 MB
    finally:
        tracemalloc.stop()
