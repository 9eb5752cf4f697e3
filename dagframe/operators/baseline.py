"""What the bound is compared with: exact continuous measures, search over graphs, and a correlation graph."""

from __future__ import annotations

from dataclasses import asdict, replace
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.operators.learner import LearnerParams, fit
from dagframe.operators.moments import to_matrix


def fit_trexp(moments: DataFrame, d: int, p: LearnerParams = LearnerParams()) -> tuple[DataFrame, DataFrame]:
    """The learner under the exponential trace; cubic in d."""
    return fit(moments, d, replace(p, constraint="trexp", stop_on="trexp"), "dense")


def fit_trpow(moments: DataFrame, d: int, p: LearnerParams = LearnerParams()) -> tuple[DataFrame, DataFrame]:
    """The learner under the power trace of I + A/d, which keeps its range."""
    return fit(moments, d, replace(p, constraint="trpow"), "dense")


def fit_radius(moments: DataFrame, d: int, p: LearnerParams = LearnerParams()) -> tuple[DataFrame, DataFrame]:
    """The learner under the power-iterated spectral radius."""
    return fit(moments, d, replace(p, constraint="radius"), "dense")


def _node_score(c: np.ndarray, j: int, parents: tuple[int, ...], n: int) -> float:
    """Description length of one node on its parents; lower is better."""
    left = c[j, j]
    if parents:
        m, t = c[np.ix_(parents, parents)], c[list(parents), j]
        left -= float(t @ np.linalg.lstsq(m, t, rcond=None)[0])
    return float(n * np.log(max(left, 1e-12)) + len(parents) * np.log(n))


def parent_scores(moments: DataFrame, d: int, n: int, most: int | None = None) -> DataFrame:
    """``(node, parents, score)`` of every node and parent set of at most ``most`` (default all)."""
    spark, c = moments.sparkSession, to_matrix(moments, d)
    rows = [(j, list(ps), _node_score(c, j, ps, n)) for j in range(d) for m in range((d - 1 if most is None else most) + 1) for ps in combinations([i for i in range(d) if i != j], m)]
    return spark.createDataFrame(rows, "node int, parents array<int>, score double")


def exhaustive(moments: DataFrame, d: int, n: int = 1000) -> DataFrame:
    """EDGES ``(src, dst, w)`` of the best graph on up to five nodes: over all orders, each node's best parents before it."""
    if d > 5:
        raise ValueError("exhaustive search takes at most five nodes")
    spark = moments.sparkSession
    scores = parent_scores(moments, d, n)
    from itertools import permutations

    orders = spark.createDataFrame([(k, list(o)) for k, o in enumerate(permutations(range(d)))], "number int, ordering array<int>")
    placed = orders.select("number", F.posexplode("ordering").alias("at", "node"), "ordering").withColumn("before", F.slice("ordering", F.lit(1), F.col("at")))
    fits = placed.join(F.broadcast(scores), "node").where(F.size(F.array_except("parents", "before")) == 0)
    best = fits.groupBy("number", "node").agg(F.min(F.struct("score", "parents")).alias("x"))
    total = best.groupBy("number").agg(F.sum("x.score").alias("score"), F.collect_list(F.struct("node", "x.parents")).alias("graph"))
    top = total.orderBy("score", "number").limit(1)
    return top.select(F.explode("graph").alias("g")).select(F.explode("g.parents").alias("src"), F.col("g.node").alias("dst")).withColumn("w", F.lit(1.0))


def hill_climb(moments: DataFrame, d: int, n: int = 1000, max_parents: int = 4, moves: int = 500) -> DataFrame:
    """EDGES by greedy search: the best of all additions, deletions and reversals, while the score falls."""
    c = to_matrix(moments, d)
    w = climb(c, n, max_parents, moves)
    i, j = np.nonzero(w)
    return moments.sparkSession.createDataFrame(pd.DataFrame({"src": i.astype("int32"), "dst": j.astype("int32"), "w": w[i, j].astype(float)}), "src int, dst int, w double")


def climb(c: np.ndarray, n: int, max_parents: int = 4, moves: int = 500) -> np.ndarray:
    """The same in one process, on a matrix of second moments: an adjacency of zeros and ones."""
    d = len(c)
    a = np.zeros((d, d), dtype=bool)
    parents = lambda j: tuple(np.flatnonzero(a[:, j]))
    own = np.array([_node_score(c, j, (), n) for j in range(d)])
    cache: dict = {}

    def score(j: int, ps: tuple[int, ...]) -> float:
        if (j, ps) not in cache:
            cache[j, ps] = _node_score(c, j, ps, n)
        return cache[j, ps]

    for _ in range(moves):
        reach = a.copy()
        for k in range(d):
            reach |= np.outer(reach[:, k], reach[k])
        best = (-1e-9, None)
        for i in range(d):
            for j in range(d):
                if i == j:
                    continue
                pj = parents(j)
                if not a[i, j] and not reach[j, i] and len(pj) < max_parents and not a[j, i]:
                    gain = score(j, tuple(sorted((*pj, i)))) - own[j]
                    best = min(best, (gain, ("add", i, j)))
                elif a[i, j]:
                    less = score(j, tuple(p for p in pj if p != i)) - own[j]
                    best = min(best, (less, ("drop", i, j)))
                    a[i, j] = False
                    around = reach_one(a, i, j)
                    a[i, j] = True
                    pi = parents(i)
                    if not around and len(pi) < max_parents:
                        best = min(best, (less + score(i, tuple(sorted((*pi, j)))) - own[i], ("turn", i, j)))
        if best[1] is None:
            break
        what, i, j = best[1]
        a[i, j] = what == "add"
        if what == "turn":
            a[j, i] = True
        for k in (i, j):
            own[k] = score(k, parents(k))
    return a.astype(float)


def reach_one(a: np.ndarray, i: int, j: int) -> bool:
    """Whether j can be reached from i."""
    seen, todo = {i}, [i]
    while todo:
        for k in np.flatnonzero(a[todo.pop()]):
            if k == j:
                return True
            if k not in seen:
                seen.add(int(k))
                todo.append(int(k))
    return False


def correlation_graph(moments: DataFrame, m: int) -> DataFrame:
    """The ``m`` pairs with the largest absolute correlation: ``(a, b, r)``, no direction."""
    own = moments.where("a = b")
    at = lambda end: own.select(F.col("a").alias(end), F.col("c").alias(f"v_{end}"))
    r = F.col("c") / F.sqrt(F.col("v_a") * F.col("v_b"))
    return moments.where("a <> b").join(at("a"), "a").join(at("b"), "b").select("a", "b", r.alias("r")).orderBy(F.desc(F.abs("r")), "a", "b").limit(m)


def expert_agreement(report: DataFrame, expert: DataFrame) -> DataFrame:
    """Alarms beside the categories that experts gave them, ``expert(report_id, category)``; unlabelled ones stay."""
    return report.join(expert, "report_id", "left").withColumn("category", F.coalesce("category", F.lit("unlabelled")))


#: Residues of given values, as draws between 0 and 1: a prime number of places.
PLACES = 10_007


def given_noise(lines: DataFrame, d: int) -> dict[tuple[str, int], tuple[int, np.ndarray]]:
    """Number and covariances of noise of three kinds on d nodes, by kind and replicate, from all rows of ``lines(place, step, seed)``.

    A row is one sample: its uniform draw for node j is the residue of place + j * step, so that those of any two nodes are
    independent. Each task gives back sums alone; what reaches the driver depends on d and the replicates only.
    """
    names = ("gauss", "exp", "gumbel")

    def run(batches):
        held = {}
        for b in batches:
            place, step, seed = (b[c].to_numpy() for c in ("place", "step", "seed"))
            u = ((place[:, None] + step[:, None] * np.arange(1, 2 * d + 1)) % PLACES + 0.5) / PLACES
            u, angle = u[:, :d], 2 * np.pi * u[:, d:]
            minus = -np.log(u)
            for name, e in zip(names, (np.sqrt(2 * minus) * np.cos(angle), minus, -np.log(minus)), strict=True):
                e = np.c_[e, np.ones(len(e))]  # a last column of ones, for sums and numbers
                for s in np.unique(seed):
                    mine = e[seed == s]
                    held[name, int(s)] = held.get((name, int(s)), 0) + mine.T @ mine
        rows = [(name, s, i, j, float(m[i, j])) for (name, s), m in held.items() for i in range(d + 1) for j in range(d + 1)]
        yield pd.DataFrame(rows, columns=["noise", "seed", "a", "b", "s"])

    own = lines.select(*[F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c) for c in ("place", "step", "seed")])
    sums = own.mapInPandas(run, "noise string, seed int, a int, b int, s double").groupBy("noise", "seed", "a", "b").agg(F.sum("s").alias("s"))
    out: dict = {}
    for (name, s), m in sums.toPandas().groupby(["noise", "seed"]):
        full = m.pivot(index="a", columns="b", values="s").to_numpy()
        n, mean = full[d, d], full[d, :d] / full[d, d]
        out[str(name), int(s)] = (int(n), full[:d, :d] / n - np.outer(mean, mean))
    return out


def planted_runs(spark: SparkSession, cells: list[tuple[str, str, int, int, str]], p: LearnerParams, eps: tuple[float, ...] = (1e-1, 1e-2, 1e-3, 1e-4), taus: tuple[float, ...] = (0.1, 0.2, 0.3, 0.4, 0.5), given: dict | None = None) -> DataFrame:
    """RESULTS of planted experiments, one learning run per task: ``cells`` lists (graph, noise, d, seed, method).

    A run is read out at every stop tolerance and filter of the grid; method is ``bound``, ``trexp``, ``trpow``, ``radius``,
    ``climb`` or ``correlation``. With ``given`` (see ``given_noise``) the samples carry noise of given rows through the planted graph.
    """
    held = asdict(p)

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        graph, kind, d, seed, method = frame.iloc[0][["graph", "noise", "d", "seed", "method"]]
        truth, kept, trace, seconds = _planted_fit(graph, kind, int(d), int(seed), method, held, eps, given)
        b, t = np.array([r["bound"] for r in trace]), np.array([r["trexp"] for r in trace], dtype=float)
        last = float(t[-1]) if trace else None
        corr = float(np.corrcoef(b, t)[0, 1]) if len(b) > 2 and b.std() > 0 and t.std() > 0 else None
        rows, a = [], truth != 0
        for e in eps:
            for tau in taus:
                q = np.abs(kept[e]) >= tau
                tp = int((a & q).sum())
                turned = int(((a & q.T) & ~q).sum())
                extra = int(q.sum()) - tp - turned
                missing = int(a.sum()) - tp - turned
                f1 = 2 * tp / max(1, int(a.sum() + q.sum()))
                rows.append((graph, kind, d, seed, method, e, tau, tp, turned, extra, missing, f1, extra + missing + turned, corr, last, seconds))
        return pd.DataFrame(rows, columns=RESULT_NAMES)

    return _runs(spark, cells).applyInPandas(one, RESULTS)


def planted_traces(spark: SparkSession, cells: list[tuple[str, str, int, int, str]], p: LearnerParams, given: dict | None = None) -> DataFrame:
    """The trace of each of these runs: a row for each outer round, with the run's cell."""
    held = asdict(p)

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        cell = frame.iloc[0][["graph", "noise", "d", "seed", "method"]]
        trace = _planted_fit(cell["graph"], cell["noise"], int(cell["d"]), int(cell["seed"]), cell["method"], held, (p.eps,), given)[2]
        return pd.DataFrame([(*cell, r["outer"], r["bound"], r["trexp"], r["nnz"], r["loss"], r["seconds"]) for r in trace], columns=[c.split()[0] for c in TRACES.split(", ")])

    return _runs(spark, cells).applyInPandas(one, TRACES)


TRACES = "graph string, noise string, d int, seed int, method string, outer int, bound double, trexp double, nnz long, loss double, seconds double"


def _runs(spark: SparkSession, cells: list):
    named = spark.createDataFrame(cells, "graph string, noise string, d int, seed int, method string").withColumn("run", F.concat_ws("/", "graph", "noise", F.col("d").cast("string"), F.col("seed").cast("string"), "method"))
    return named.repartition(max(1, len(cells)), "run").groupBy("run")


def _planted_fit(graph: str, kind: str, d: int, seed: int, method: str, held: dict, eps: tuple[float, ...], given: dict | None = None):
    """(true weights, weights by stop tolerance, trace, seconds) of one run, inside a task."""
    import os

    os.environ.setdefault("OMP_NUM_THREADS", "1")
    import time

    from dagframe.operators.learner import fit_dense
    from dagframe.operators.simulate import local_dag, local_sample

    truth = local_dag(graph, d, 2 if graph == "er" else 4, seed)
    if given is None:
        x = local_sample(truth, 10 * d, kind, seed + 1000)
        x = x - x.mean(0)
        n, c = len(x), x.T @ x / len(x)
    else:
        n, own = given[kind, seed]
        carried = np.linalg.inv(np.eye(d) - truth)
        c = carried.T @ own[:d, :d] @ carried
    began = time.perf_counter()
    if method in ("climb", "correlation"):
        w = climb(c, n) if method == "climb" else _top_correlations(c, int((truth != 0).sum()))
        return truth, dict.fromkeys(eps, w), [], time.perf_counter() - began
    _, trace, kept = fit_dense(c, LearnerParams(**(held | {"constraint": method, "eps": min(eps), "seed": seed})), eps)
    return truth, kept, trace, time.perf_counter() - began


RESULTS = "graph string, noise string, d int, seed int, method string, eps double, tau double, tp int, reversed int, extra int, missing int, f1 double, shd int, corr double, trexp double, seconds double"
RESULT_NAMES = [c.split()[0] for c in RESULTS.split(", ")]


def _top_correlations(c: np.ndarray, m: int) -> np.ndarray:
    r = np.abs(np.triu(c / np.sqrt(np.outer(np.diag(c), np.diag(c))), 1))
    w = np.zeros_like(r)
    at = np.argsort(-r, axis=None)[:m]
    w.flat[at] = r.flat[at]
    return w
