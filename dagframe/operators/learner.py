"""Continuous structure learning: an augmented Lagrangian around a least-squares fit and an acyclicity measure.

Data enter once, as second moments, so a step costs nothing per sample; with ``batch``, a step's moments are those of a mini-batch
of samples, made for many steps in one job. The engines: ``dense`` (a full matrix in one process),
``local_sparse`` (coordinate arrays in one process) and ``distributed`` (edges and state stay tables; a step is one plan).
``fit_many`` learns many small models at once, one per group, inside tasks.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import asdict, dataclass, replace
from math import exp, fsum, lgamma, log

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.functions.columns import uniform
from dagframe.operators import batches, bound, loss, mapped, optim
from dagframe.operators.bound_local import dense_value_and_grad
from dagframe.operators.mapped import Pairs, pair_lookup
from dagframe.operators.moments import from_cells as moments_of
from dagframe.operators.moments import to_matrix
from dagframe.plans.lineage import cut


@dataclass(frozen=True)
class LearnerParams:
    """All knobs of a run. ``init``: ``warm`` goes on from the last round, ``redraw`` draws anew; ``support``: ``full``, ``random``
    (density zeta) or ``screened`` (the strongest correlations); ``stop_on``: ``bound``, ``trexp`` or ``either``; ``sinks``: nodes known to cause nothing (dense engine)."""

    zeta: float = 1e-4
    lam: float = 0.1
    eps: float = 1e-4
    k: int = 5
    alpha: float = 0.9
    theta: float = 0.0
    t_outer: int = 1000
    t_inner: int = 200
    lr: float = 0.01
    rho0: float = 1.0
    eta0: float = 1.0
    rho_growth: float = 1.5
    rho_most: float = 1e16
    tol_inner: float = 1e-6
    stop_on: str = "either"
    init: str = "warm"
    support: str = "full"
    screen: int = 10
    penalty_gradient: str = "derived"
    constraint: str = "bound"
    batch: int = 0
    seed: int = 7
    sinks: tuple[int, ...] = ()


def raise_multiplier(eta: float, rho: float, value: float) -> float:
    return eta + rho * value


def grow_penalty(rho: float, factor: float = 1.5, most: float = 1e16) -> float:
    """A factor of 1 keeps the penalty."""
    return min(rho * factor, most)


def should_stop(value: float, trace: float | None, eps: float, stop_on: str = "either") -> bool:
    hit = {"bound": value <= eps, "trexp": trace is not None and trace <= eps}
    return hit["bound"] or hit["trexp"] if stop_on == "either" else hit[stop_on]


def augmented(frame: DataFrame, rho: float, eta: float, penalty_gradient: str = "derived") -> DataFrame:
    """Rows with ``loss``, ``bound``, and gradients ``gl`` and ``gb``: the objective and the whole gradient.

    ``as_printed`` takes the factor rho + bound of the published formula, for comparison; the derivative has rho * bound.
    """
    b = F.col("bound")
    factor = eta + rho * b if penalty_gradient == "derived" else eta + rho + b
    return frame.withColumns({"objective": F.col("loss") + rho / 2 * b * b + eta * b, "g": F.col("gl") + factor * F.col("gb")})


def threshold(edges: DataFrame, theta: float) -> DataFrame:
    """Edges whose absolute weight is at least theta."""
    return edges.where(F.abs("w") >= theta)


extract_graph = threshold


def init_edges(spark: SparkSession, d: int, zeta: float = 1e-4, seed: int = 7) -> DataFrame:
    """A sparse random start: about zeta * d**2 edges, Glorot-uniform weights; the pairs are drawn, never listed."""
    wide = (6.0 / (2 * d)) ** 0.5
    at = lambda stream: F.floor(uniform(seed, stream, F.col("id")) * d).cast("int")
    drawn = spark.range(int(np.ceil(zeta * d * d))).select(at("i").alias("src"), at("j").alias("dst")).where("src <> dst").distinct()
    return drawn.withColumn("w", (2 * uniform(seed, "w", F.col("src"), F.col("dst")) - 1) * wide)


# ---- one process, dense

Constraint = Callable[[np.ndarray], tuple[float, np.ndarray]]


def trexp_dense(w: np.ndarray) -> tuple[float, np.ndarray]:
    """Exponential trace less d, and its gradient; by scaling and squaring of the series."""
    a = w * w
    if (norm := np.abs(a).sum(1).max(initial=0)) > 600:
        raise ArithmeticError("the exponential trace isn't finite")
    s = max(0, int(np.ceil(np.log2(max(norm, 1e-300)))) + 1)
    x = a / 2**s
    term, total = np.eye(len(a)), np.eye(len(a))
    for m in range(1, 19):
        term = term @ x / m
        total = total + term
    for _ in range(s):
        total = total @ total
    return float(np.trace(total) - len(a)), total.T * 2 * w


def constraint_of(p: LearnerParams) -> Constraint:
    if p.constraint == "bound":
        return lambda w: dense_value_and_grad(w, p.k, p.alpha)
    if p.constraint == "trexp":
        return trexp_dense
    if p.constraint == "trpow":

        def trpow(w: np.ndarray) -> tuple[float, np.ndarray]:
            d = len(w)
            m = np.eye(d) + w * w / d
            part = np.linalg.matrix_power(m, d - 1)
            return float(np.trace(part @ m) - d), part.T * 2 * w

        return trpow
    if p.constraint == "radius":

        def radius(w: np.ndarray) -> tuple[float, np.ndarray]:
            a = w * w + 1e-12
            right, left = np.ones(len(a)), np.ones(len(a))
            for _ in range(60):
                right, left = a @ right, left @ a
                right, left = right / right.sum(), left / left.sum()
            return float((left @ a @ right) / (left @ right)), np.outer(left, right) / (left @ right) * 2 * w

        return radius
    raise ValueError("constraint is bound, trexp, trpow or radius")


def _screened(c: np.ndarray, m: int) -> np.ndarray:
    d = len(c)
    r = np.abs(c) / np.sqrt(np.maximum(np.outer(np.diag(c), np.diag(c)), 1e-300))
    np.fill_diagonal(r, -1)
    keep = np.zeros((d, d), dtype=bool)
    for j in range(d):
        keep[np.argsort(-r[:, j])[: min(m, d - 1)], j] = True
    return keep


def fit_dense(c: np.ndarray, p: LearnerParams, snapshots: tuple[float, ...] = (), draw: Callable[[int], np.ndarray] | None = None) -> tuple[np.ndarray, list[dict], dict[float, np.ndarray]]:
    """(weights, trace, weights when the stop measure first fell below each of ``snapshots``) from second moments.

    ``draw(step)`` gives the moments of that step's mini-batch; steps count on over outer rounds.
    """
    if p.batch and draw is None:
        raise ValueError("mini-batches need samples: use fit(..., cells=...)")
    full, steps = c, 0
    d, measure, random = len(c), constraint_of(p), np.random.default_rng(p.seed)
    off = 1 - np.eye(d)
    off[list(p.sinks)] = 0
    still = np.diag(c) <= 0  # a node that never varies has no edges
    off[still] = off[:, still] = 0
    if p.support == "screened":
        off = off * _screened(c, p.screen)
    elif p.support == "random":
        off = off * (random.random((d, d)) < max(p.zeta, 0.0))
    wide = (6.0 / (2 * d)) ** 0.5
    begin = lambda: random.uniform(-wide, wide, (d, d)) * off * (random.random((d, d)) < max(p.zeta, 1e-4 if d > 100 else 1.0))
    w, rho, eta, trace, kept, began = begin(), p.rho0, p.eta0, [], {}, time.perf_counter()
    cd = c @ np.eye(d)
    for outer in range(p.t_outer):
        if outer and p.init == "redraw":
            w = begin()
        step, last, inner, value = optim.Adam(w.shape, p.lr), np.inf, 0, 0.0
        for inner in range(1, p.t_inner + 1):
            value, gb = measure(w)
            if draw is not None:
                c = draw(steps)
                cd, steps = c, steps + 1
            cw = c @ w
            fit = float(np.trace(c) - 2 * (cd * w).sum() + (w * cw).sum())
            total = fit + p.lam * np.abs(w).sum() + rho / 2 * value * value + eta * value
            factor = eta + rho * value if p.penalty_gradient == "derived" else eta + rho + value
            w = step.step(w, (2 * (cw - cd) + p.lam * np.sign(w) + factor * gb) * off)
            if p.theta:
                w = np.where(np.abs(w) >= p.theta, w, 0.0)
            if inner % 10 == 0 and draw is None:
                if abs(last - total) <= p.tol_inner * max(1.0, abs(total)):
                    break
                last = total
        value = measure(w)[0]
        fit = float(np.trace(full) - 2 * (full * w).sum() + (w * (full @ w)).sum()) if draw is not None else fit
        exact = trexp_dense(w)[0] if d <= 200 or p.stop_on == "trexp" else None
        trace.append({"outer": outer, "inner": inner, "loss": fit + p.lam * float(np.abs(w).sum()), "bound": dense_value_and_grad(w, p.k, p.alpha)[0], "trexp": exact, "nnz": int((w != 0).sum()), "rho": rho, "eta": eta, "seconds": time.perf_counter() - began})
        watched = exact if p.stop_on == "trexp" and exact is not None else value if p.stop_on == "bound" else min(value, exact if exact is not None else value)
        for e in snapshots:
            if watched <= e and e not in kept:
                kept[e] = w.copy()
        if should_stop(value, exact, p.eps, p.stop_on):
            break
        eta, rho = raise_multiplier(eta, rho, value), grow_penalty(rho, p.rho_growth, p.rho_most)
    for e in snapshots:
        kept.setdefault(e, w)
    return w, trace, kept


# ---- one process, sparse


def _cyclic(src: np.ndarray, dst: np.ndarray, w: np.ndarray, d: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Edges, with squared weights, of the part of a graph that can hold cycles."""
    a = w * w
    while len(a):
        live = (np.bincount(src, weights=a, minlength=d) > 0) & (np.bincount(dst, weights=a, minlength=d) > 0)
        kept = live[src] & live[dst] & (a > 0)
        if kept.all():
            break
        src, dst, a = src[kept], dst[kept], a[kept]
    return src, dst, a


#: Share of the exponential trace that the ends of its series may come to, and products of walks made at a time.
TRACE_ERROR, WALKS = 1e-13, 2_000_000


def trexp_sparse(src: np.ndarray, dst: np.ndarray, w: np.ndarray, d: int) -> float:
    """The exponential trace less d, of any number of nodes: all closed walks, to ``TRACE_ERROR`` of their sum.

    A closed walk is a way forth from its first node and a way back to it, each of half its steps. Weights are scaled so that no
    row sums up to more than ``r``, close to the spectral radius, which leaves closed walks as they are. So what may follow a way,
    and what may close it, is bounded: ways go on until what is left of a first node's series, and what its dropped ways could
    still add, is below its share of the error.
    """
    src, dst, a = _cyclic(src, dst, w, d)
    if not len(a):
        return 0.0
    nodes, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    n, (i, j) = len(nodes), (at[: len(a)], at[len(a) :])
    x = np.ones(n)
    for _ in range(50):
        y = np.bincount(i, weights=a * x[j], minlength=n)
        x = np.maximum(y / y.max() + 1e-3 * x, 1e-100)
        x /= x.max()
    if (np.bincount(i, weights=(scaled := a * x[j] / x[i]), minlength=n).max()) < np.bincount(i, weights=a, minlength=n).max():
        a = scaled
    r = float(np.bincount(i, weights=a, minlength=n).max())
    if not r <= 600:
        raise ArithmeticError("the exponential trace isn't finite")
    ends = []
    for one, other in ((i, j), (j, i)):
        by = np.argsort(one, kind="stable")
        ends.append((np.r_[0, np.cumsum(np.bincount(one, minlength=n))], other[by], a[by]))

    def grow(ways: tuple, end: tuple) -> tuple:
        """All ways one step longer; those between the same nodes are one."""
        key, value = ways
        (first, to, by), node = end, key % n
        size = first[node + 1] - first[node]
        edge = np.repeat(first[node] - (np.cumsum(size) - size), size) + np.arange(size.sum())
        key, value = np.repeat(key - node, size) + to[edge], np.repeat(value, size) * by[edge]
        order = np.argsort(key, kind="stable")
        key = key[order]
        new = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.zeros(0, np.int64)
        return key[new], np.add.reduceat(value[order], new) if len(new) else value

    def met(forth: tuple, back: tuple) -> float:
        if not len(forth[0]) or not len(back[0]):
            return 0.0
        at = np.minimum(np.searchsorted(back[0], forth[0]), len(back[0]) - 1)
        return float(forth[1][back[0][at] == forth[0]] @ back[1][at[back[0][at] == forth[0]]])

    def some(ways: tuple, live: np.ndarray) -> tuple:
        return ways[0][live], ways[1][live]

    key = np.sort(i * n + j)
    two = np.minimum(np.searchsorted(key, j * n + i), len(key) - 1)
    two = float((a * np.where(key[two] == j * n + i, a[np.argsort(i * n + j, kind="stable")][two], 0.0)).sum()) / 2
    error = max(TRACE_ERROR * two / n, 1e-30)
    room = lambda m, q: error * exp(min(lgamma(m + 1) - q * log(r) - r, 600.0))
    total, begin = [], np.arange(n, dtype=np.int64) * (n + 1)
    held = [(b, 0, (begin[b : b + 4096], np.ones(len(begin[b : b + 4096]))), (begin[b : b + 4096], np.ones(len(begin[b : b + 4096])))) for b in range(0, n, 4096)]
    while held:
        b, p, forth, back = held.pop()
        own = lambda ways: ways[0] // n - b  # noqa: E731, B023
        work = max(int((ends[k][0][ways[0] % n + 1] - ends[k][0][ways[0] % n]).sum()) for k, ways in ((0, forth), (1, back)))
        if work > WALKS and len(rows := np.unique(own(forth))) > 1:  # fewer first nodes at a time
            middle = rows[len(rows) // 2]
            held += [(b, p, some(forth, own(forth) < middle), some(back, own(back) < middle)), (b, p, some(forth, own(forth) >= middle), some(back, own(back) >= middle))]
            continue
        p, before = p + 1, back
        forth = grow(forth, ends[0])
        forth = some(forth, forth[1] * np.bincount(own(forth), minlength=1)[own(forth)] >= room(2 * p - 1, p - 1) / 2 ** (p + 3))
        total.append(met(forth, before) / exp(lgamma(2 * p)))
        back = grow(back, ends[1])
        back = some(back, back[1] >= room(2 * p, p) / 2 ** (p + 3))
        total.append(met(forth, back) / exp(lgamma(2 * p + 1)))
        if not len(forth[0]) or not len(back[0]):
            continue
        sums, most = np.bincount(own(forth), weights=forth[1], minlength=4096), np.zeros(4096)
        np.maximum.at(most, own(back), back[1])
        live = sums * most > room(2 * p + 1, 1) / 4
        forth, back = some(forth, live[own(forth)]), some(back, live[own(back)])
        if len(forth[0]) and len(back[0]):
            held.append((b, p, forth, back))
    return fsum(total)


CORE = 2000


def trexp_core(src: np.ndarray, dst: np.ndarray, w: np.ndarray, d: int) -> float:
    """The exponential trace less d for at most ``CORE`` nodes that can be in cycles, else its terms of two and three steps, which
    it is never below. For comparison: no learner calls it; ``trexp_sparse`` is the whole trace at any size."""
    src, dst, a = _cyclic(src, dst, w, d)
    nodes = np.unique(np.concatenate([src, dst]))
    if not len(nodes):
        return 0.0
    if len(nodes) <= CORE:
        full = np.zeros((len(nodes), len(nodes)))
        full[np.searchsorted(nodes, src), np.searchsorted(nodes, dst)] = np.sqrt(a)
        return trexp_dense(full)[0]
    key = src.astype(np.int64) * d + dst
    order = np.argsort(key)
    key, value = key[order], a[order]

    def weight(i: np.ndarray, j: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(key, i.astype(np.int64) * d + j), len(key) - 1)
        return np.where(key[at] == i.astype(np.int64) * d + j, value[at], 0.0)

    by = np.argsort(src, kind="stable")
    degree = np.bincount(src, minlength=d)
    first, three = np.cumsum(degree) - degree, 0.0
    for at in range(0, len(a), 100_000):  # paths of two edges, some at a time
        e = slice(at, at + 100_000)
        n = degree[dst[e]]
        left = np.repeat(np.arange(len(a))[e], n)
        right = by[np.repeat(first[dst[e]], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)]
        three += float((a[left] * a[right] * weight(dst[right], src[left])).sum())
    return float((a * weight(dst, src)).sum()) / 2 + three / 6


def fit_sparse(c: Pairs, src: np.ndarray, dst: np.ndarray, w: np.ndarray, d: int, p: LearnerParams, draw: Callable[[int], Pairs] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[dict]]:
    """The same on coordinate arrays; ``c(a, b)`` gives moments of pairs, ``draw(step)`` those of a step's mini-batch. The start
    is the support: it only shrinks. A step costs the pairs of parents of each node besides the bound's O(k * edges).

    Weights below theta go after every step. ``redraw`` gives what is left new weights in each outer round. The constraint
    is the bound.
    """
    if p.constraint != "bound":
        raise ValueError("the sparse engine takes the bound as its constraint; use the dense one")
    if p.batch and draw is None:
        raise ValueError("mini-batches need samples: use fit(..., cells=...)")
    trace, rho, eta, began, random, steps = [], p.rho0, p.eta0, time.perf_counter(), np.random.default_rng(p.seed), 0
    wide, edges = (6.0 / (2 * d)) ** 0.5, mapped.Edges(src, dst, w, d)
    edges.hold(c)
    for outer in range(p.t_outer):
        if outer and p.init == "redraw":
            edges.w[edges.alive] = random.uniform(-wide, wide, len(w))
        edges.begin()
        last, inner, fit = np.inf, 0, 0.0
        for inner in range(1, p.t_inner + 1):
            value = edges.bound(p.k, p.alpha)
            if draw is not None:
                edges.hold(draw(steps))
                steps += 1
            factor = eta + rho * value if p.penalty_gradient == "derived" else eta + rho + value
            fit, total = edges.step(value, rho, eta, p.lam, p.lr, p.theta, factor)
            edges.compact()
            if inner % 10 == 0 and draw is None:
                if abs(last - total) <= p.tol_inner * max(1.0, abs(total)):
                    break
                last = total
        if draw is not None:
            edges.hold(c)
            fit = edges.fit()
        value = edges.bound(p.k, p.alpha, False)
        src, dst, w = edges.rows()
        exact = trexp_sparse(src, dst, w, d)
        trace.append({"outer": outer, "inner": inner, "loss": fit + p.lam * edges.size(), "bound": value, "trexp": exact, "nnz": len(w), "rho": rho, "eta": eta, "seconds": time.perf_counter() - began})
        if should_stop(value, exact, p.eps, p.stop_on):
            break
        eta, rho = raise_multiplier(eta, rho, value), grow_penalty(rho, p.rho_growth, p.rho_most)
    return src, dst, w, trace


# ---- tables

TRACE = "outer int, inner int, loss double, bound double, trexp double, nnz long, rho double, eta double, seconds double"


def trace_table(spark: SparkSession, trace: list[dict]) -> DataFrame:
    return spark.createDataFrame([tuple(t[c.split()[0]] for c in TRACE.split(", ")) for t in trace], TRACE)


def edges_of(spark: SparkSession, w: np.ndarray) -> DataFrame:
    i, j = np.nonzero(w)
    return spark.createDataFrame(pd.DataFrame({"src": i.astype("int32"), "dst": j.astype("int32"), "w": w[i, j]}), "src int, dst int, w double")


def distributed_step(state: DataFrame, moments: DataFrame, p: LearnerParams, rho: float, eta: float, step: int) -> DataFrame:
    """EDGE_STATE after one step, all as tables: loss gradient, bound and its gradient from one forward pass, Adam, filter."""
    edges = state.select("src", "dst", "w")
    value, gb = bound.value_and_gradient(edges, p.k, p.alpha)
    gl = loss.gradient_from_moments(moments, edges, p.lam).select("src", "dst", F.col("g").alias("gl"))
    factor = eta + rho * value if p.penalty_gradient == "derived" else eta + rho + value
    grad = gl.join(gb.select("src", "dst", F.col("g").alias("gb")), ["src", "dst"], "left").select("src", "dst", (F.col("gl") + factor * F.coalesce("gb", F.lit(0.0))).alias("g"))
    return cut(threshold(optim.adam(state, grad, step, p.lr), p.theta))


def inner(edges: DataFrame, moments: DataFrame, p: LearnerParams, rho: float = 1.0, eta: float = 1.0, steps: int | None = None, cells: DataFrame | None = None, n: int | None = None, first: int = 0) -> DataFrame:
    """Weights after ``steps`` (default t_inner) distributed steps; with ``p.batch`` each on a mini-batch of ``cells``' n samples."""
    state = optim.start(edges)
    for t in range(1, (steps or p.t_inner) + 1):
        own = moments_of(batches.draw(cells, p.batch, n, p.seed, first + t - 1)) if p.batch else moments
        state = distributed_step(state, own, p, rho, eta, t)
    return state.select("src", "dst", "w")


LOCAL_ROWS = 20_000_000


class BatchMoments:
    """Moments of mini-batches on the driver, made for many steps in one job; at most LOCAL_ROWS / 10 rows at a time."""

    def __init__(self, cells: DataFrame, n: int, d: int, p: LearnerParams):
        self.cells, self.n, self.d, self.p, self.held = cells, n, d, p, {}
        self.ahead = max(1, min(p.t_inner, LOCAL_ROWS // 10 // max(1, d * (d + 1) // 2)))

    def rows(self, step: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if step not in self.held:
            steps = self.ahead
            found = batches.moments_by_step(batches.prefetch(self.cells, self.p.batch, self.n, steps, self.p.seed, step))
            got = within(found, LOCAL_ROWS // 10)
            at = got["step"].to_numpy()
            a, b, c = (got[k].to_numpy() for k in "abc")
            self.held = {t: (a[at == t], b[at == t], c[at == t]) for t in range(step, step + steps)}
        return self.held[step]

    def matrix(self, step: int) -> np.ndarray:
        a, b, v = self.rows(step)
        c = np.zeros((self.d, self.d))
        c[a, b] = c[b, a] = v
        return c

    def pairs(self, step: int) -> Pairs:
        return pair_lookup(*self.rows(step), self.d)


def within(table: DataFrame, most: int):
    """``table`` on the driver, as Arrow, if it has at most ``most`` rows."""
    got = table.limit(most + 1).toArrow()
    if got.num_rows > most:
        raise ValueError(f"more than {most} rows for one process; use the distributed engine")
    return got


def support_pairs(edges: DataFrame) -> DataFrame:
    """``(a, b)``, a < b, that a run on the support of ``edges`` can ask for: edges, and pairs of parents of one node."""
    e = edges.select("src", "dst")
    other = e.select(F.col("src").alias("other"), "dst")
    return e.join(other, "dst").where("src < other").select(F.col("src").alias("a"), F.col("other").alias("b")).unionByName(e.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"))).distinct()


def support_moments(moments: DataFrame, edges: DataFrame) -> DataFrame:
    """The moments that a run on the support of ``edges`` can ask for: nodes, edges, and pairs of parents of one node."""
    return moments.where("a = b").unionByName(moments.where("a <> b").join(support_pairs(edges), ["a", "b"], "left_semi"))


def fit(moments: DataFrame, d: int, p: LearnerParams = LearnerParams(), engine: str | None = None, start: DataFrame | None = None, cells: DataFrame | None = None, listed: bool = False) -> tuple[DataFrame, DataFrame]:
    """``(EDGES, TRACE)`` from MOMENTS; the engine is chosen by size unless named. ``cells`` are the samples that mini-batches of
    ``p.batch`` are drawn from; the trace's loss is that of all moments. ``listed``: the moments are those of the start's support already.

    The dense engine takes every option; the others learn under the bound, and the distributed one stops on the bound.
    """
    from dagframe.plans.planner import choose_engine

    spark = moments.sparkSession
    engine = engine or choose_engine(d, start.count() if start is not None else int(np.ceil(p.zeta * d * d)))
    if p.batch and cells is None:
        raise ValueError("mini-batches need cells")
    n = cells.select("sample_id").distinct().count() if p.batch else 0
    if engine == "dense":
        drawn = BatchMoments(cells, n, d, p).matrix if p.batch else None
        w, trace, _ = fit_dense(to_matrix(moments, d), p, draw=drawn)
        return edges_of(spark, w), trace_table(spark, trace)
    if p.constraint != "bound" or p.support == "screened" or p.sinks:
        raise ValueError("only the dense engine takes another constraint than the bound, sinks, or screens the support itself")
    edges = start if start is not None else init_edges(spark, d, p.zeta, p.seed)
    if engine == "local_sparse":
        edges = edges.select("src", "dst", "w") if listed else cut(edges.select("src", "dst", "w"))
        rows, m = mapped.collected(edges, LOCAL_ROWS), mapped.collected((moments if listed else support_moments(moments, edges)).select("a", "b", "c"), LOCAL_ROWS)
        drawn = BatchMoments(cells, n, d, p).pairs if p.batch else None
        src, dst, w, trace = fit_sparse(pair_lookup(m.pop("a"), m.pop("b"), m.pop("c"), d), rows.pop("src"), rows.pop("dst"), rows.pop("w"), d, p, drawn)
        return spark.createDataFrame(pa.table({"src": src.astype("int32"), "dst": dst.astype("int32"), "w": w})), trace_table(spark, trace)
    if p.init == "redraw":
        raise ValueError("the distributed engine goes on from the last round")
    rho, eta, trace, began = p.rho0, p.eta0, [], time.perf_counter()
    for outer in range(p.t_outer):
        edges = inner(edges, moments, p, rho, eta, cells=cells, n=n, first=outer * p.t_inner)
        value, fitted = bound.spectral_bound(edges, p.k, p.alpha).first()["bound"], loss.from_moments(moments, edges, p.lam).first()["loss"]
        trace.append({"outer": outer, "inner": p.t_inner, "loss": fitted, "bound": value, "trexp": None, "nnz": edges.count(), "rho": rho, "eta": eta, "seconds": time.perf_counter() - began})
        if should_stop(value, None, p.eps, "bound"):
            break
        eta, rho = raise_multiplier(eta, rho, value), grow_penalty(rho, p.rho_growth, p.rho_most)
    return edges, trace_table(spark, trace)


def fit_many(moments: DataFrame, d: int, p: LearnerParams, key: str = "run_id", tau: float = 0.3, indicators: bool = False) -> DataFrame:
    """``(key, src, dst, w)``: one dense model per key, learnt inside tasks from its MOMENTS.

    ``indicators``: all columns are 0 or 1, so means are known from the moments and covariances are learnt from.
    """
    held = asdict(p)

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        c = np.zeros((d, d))
        a, b = frame["a"].to_numpy(dtype=int), frame["b"].to_numpy(dtype=int)
        c[a, b] = c[b, a] = frame["c"]
        if indicators:
            c -= np.outer(np.diag(c), np.diag(c))
        w, _, _ = fit_dense(c, LearnerParams(**held))
        i, j = np.nonzero(np.abs(w) >= tau)
        return pd.DataFrame({key: frame[key].iloc[0], "src": i.astype("int32"), "dst": j.astype("int32"), "w": w[i, j]})

    return moments.groupBy(key).applyInPandas(one, f"{key} {moments.schema[key].dataType.simpleString()}, src int, dst int, w double")


def solve(moments: DataFrame, d: int, paradigm: str = "bound", p: LearnerParams = LearnerParams(), **options) -> DataFrame:
    """EDGES by one of the three formulations: ``search`` over graphs, ``exact`` continuous measure, or ``bound``."""
    if paradigm == "search":
        from dagframe.operators import baseline

        return baseline.exhaustive(moments, d, **options) if d <= 5 else baseline.hill_climb(moments, d, **options)
    return fit(moments, d, replace(p, constraint="trexp") if paradigm == "exact" else p, "dense")[0]


def refit(moments: DataFrame, edges: DataFrame) -> DataFrame:
    """``(src, dst, w, variance)``: least squares of each node on its parents, and what variance is left."""
    c = loss.both_ways(moments)
    other = edges.select(F.col("src").alias("other"), "dst")
    pairs = edges.select("src", "dst").join(other, "dst").join(c, (F.col("src") == F.col("a")) & (F.col("other") == F.col("b")), "left").select("dst", "src", "other", F.coalesce("c", F.lit(0.0)).alias("c"))
    target = edges.select("src", "dst").join(c, (F.col("src") == F.col("a")) & (F.col("dst") == F.col("b")), "left").select("dst", "src", F.lit(-1).alias("other"), F.coalesce("c", F.lit(0.0)).alias("c"))
    own = edges.select("dst").distinct().join(moments.where("a = b").select(F.col("a").alias("dst"), "c"), "dst").select("dst", F.lit(-1).alias("src"), F.lit(-1).alias("other"), "c")

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        parents = sorted(set(frame["src"]) - {-1})
        at = {v: i for i, v in enumerate(parents)}
        m, t, v = np.zeros((len(parents), len(parents))), np.zeros(len(parents)), 0.0
        for s, o, x in zip(frame["src"], frame["other"], frame["c"], strict=True):
            if s == -1:
                v = x
            elif o == -1:
                t[at[s]] = x
            else:
                m[at[s], at[o]] = x
        w = np.linalg.lstsq(m, t, rcond=None)[0]
        return pd.DataFrame({"src": np.array(parents, dtype="int32"), "dst": np.full(len(parents), frame["dst"].iloc[0], dtype="int32"), "w": w, "variance": v - float(w @ t)})

    return pairs.unionByName(target).unionByName(own).groupBy("dst").applyInPandas(one, "src int, dst int, w double, variance double")


def log_density(cells: DataFrame, edges: DataFrame, variance: DataFrame) -> DataFrame:
    """``(sample_id, log_density)`` of samples under the network: each node's residual under its own variance (``node_id, variance``)."""
    every = cells.select("sample_id").distinct().crossJoin(variance)  # a node without a residual has zero, not no density
    r = every.join(loss.residuals(cells, edges), ["sample_id", "node_id"], "left").withColumn("r", F.coalesce("r", F.lit(0.0)))
    return r.groupBy("sample_id").agg(F.sum(-0.5 * (F.log(2 * np.pi * F.col("variance")) + F.col("r") * F.col("r") / F.col("variance"))).alias("log_density"))
