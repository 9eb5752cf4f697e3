"""Exact acyclicity measures on edge tables, consistency thresholds, graph audits and repair."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dagframe.operators.bound import checked, square
from dagframe.plans.lineage import cut


def bound_for_trexp(eps: float, d: int) -> float:
    """A bound at or below this keeps the exponential trace within eps."""
    return math.log1p(eps / d)


def bound_for_trpow(eps: float, d: int) -> float:
    """The same for the power trace; a sufficient threshold of our own, positive for every eps."""
    return math.expm1(math.log1p(eps / d) / d)


def thresholds(frame: DataFrame) -> DataFrame:
    """``(eps, d)`` rows with both thresholds, as column arithmetic."""
    one = F.log1p(F.col("eps") / F.col("d"))
    return frame.withColumns({"for_trexp": one, "for_trpow": F.expm1(one / F.col("d"))})


def peel_once(edges: DataFrame) -> DataFrame:
    """Edges whose start has an incoming and whose end has an outgoing edge."""
    starts, ends = edges.select("src").distinct(), edges.select("dst").distinct()
    return edges.join(ends.withColumnRenamed("dst", "src"), "src", "left_semi").join(starts.withColumnRenamed("src", "dst"), "dst", "left_semi").select(*edges.columns)


def cyclic_core(edges: DataFrame, rounds: int = 10_000) -> DataFrame:
    """Edges that remain when sources and sinks are taken away again and again; none iff the graph is acyclic."""
    now = cut(checked(edges))
    size = now.count()
    for _ in range(rounds):
        new = cut(peel_once(now))
        left = new.count()
        if left == size or not left:
            return new
        now, size = new, left
    return now


def peel_rounds(edges: DataFrame, rounds: int) -> DataFrame:
    """``(round, n_edges)`` for a fixed number of rounds."""
    now, rows = cut(checked(edges)), None
    for t in range(rounds + 1):
        one = now.agg(F.count("*").alias("n_edges")).select(F.lit(t).alias("round"), "n_edges")
        rows = one if rows is None else rows.unionByName(one)
        now = cut(peel_once(now))
    return rows


def is_dag(edges: DataFrame) -> bool:
    return not cyclic_core(edges).take(1)


def longest_path(edges: DataFrame) -> int:
    """Edges on the longest path of an acyclic graph: rounds of taking sources away."""
    now, n = cut(checked(edges)), 0
    while now.take(1):
        ends = now.select(F.col("dst").alias("src")).distinct()
        new = cut(now.join(ends, "src", "left_semi").select(*now.columns))
        n += 1
        if new.count() == now.count():
            raise ValueError("the graph has a cycle")
        now = new
    return n


def _step(walks: DataFrame, adjacency: DataFrame) -> DataFrame:
    joined = walks.select("src", F.col("dst").alias("mid"), "v").join(adjacency.select(F.col("src").alias("mid"), "dst", "a"), "mid")
    return joined.groupBy("src", "dst").agg(F.sum(F.col("v") * F.col("a")).alias("v"))


def closed_walks(edges: DataFrame, length: int, peel: bool = True) -> DataFrame:
    """``(length, closed)``: weights of closed walks of each length, on the cyclic core only."""
    adjacency = cut(square(cyclic_core(edges) if peel else checked(edges)).select("src", "dst", "a"))
    walks, rows = adjacency.withColumnRenamed("a", "v"), None
    for m in range(1, length + 1):
        one = walks.where("src = dst").agg(F.coalesce(F.sum("v"), F.lit(0.0)).alias("closed")).select(F.lit(m).alias("length"), "closed")
        rows = one if rows is None else rows.unionByName(one)
        if m < length:
            walks = cut(_step(walks, adjacency))
    return rows


def trexp(edges: DataFrame, max_len: int = 30) -> DataFrame:
    """``(trexp)``: the exponential trace less d, by its series up to ``max_len``; exactly 0 for an acyclic graph."""
    return closed_walks(edges, max_len).agg(F.coalesce(F.sum(F.col("closed") / F.factorial("length")), F.lit(0.0)).alias("trexp")) if max_len <= 20 else closed_walks(edges, max_len).agg(F.coalesce(F.sum(F.col("closed") * F.exp(-_log_factorial("length"))), F.lit(0.0)).alias("trexp"))


def _log_factorial(n: str):
    return F.expr(f"aggregate(sequence(1, {n}), cast(0 as double), (acc, x) -> acc + ln(x))")


def trpow(edges: DataFrame, d: int, max_len: int | None = None) -> DataFrame:
    """``(trpow)``: the binomial version over walks of at most ``max_len`` (default d) steps."""
    binomial = F.exp(F.expr(f"aggregate(sequence(1, length), cast(0 as double), (acc, x) -> acc + ln(({d} - x + 1) / x))"))
    return closed_walks(edges, max_len or d).agg(F.sum(F.col("closed") * binomial).alias("trpow"))


def spectral_radius(edges: DataFrame, iterations: int = 20) -> DataFrame:
    """``(radius)`` by power iteration from equal entries, the growth of the entries' sum in the last step."""
    adjacency = cut(square(checked(edges)).select("src", "dst", "a"))
    nodes = adjacency.select(F.explode(F.array("src", "dst")).alias("node")).distinct()
    vector = cut(nodes.select("node", F.lit(1.0).alias("v")))
    for t in range(iterations):
        product = vector.join(adjacency, F.col("node") == F.col("dst")).groupBy("src").agg(F.sum(F.col("a") * F.col("v")).alias("v")).select(F.col("src").alias("node"), "v")
        norm = vector.agg(F.sum("v").alias("before")).crossJoin(product.agg(F.sum("v").alias("after")))  # one row each
        if t == iterations - 1:
            return norm.select(F.coalesce(F.col("after") / F.col("before"), F.lit(0.0)).alias("radius"))
        vector = cut(product.crossJoin(norm.select("after")).select("node", (F.col("v") / F.col("after")).alias("v")))
    return norm


def local_radius(w: np.ndarray) -> float:
    """Exact, for a matrix in one process."""
    return float(np.abs(np.linalg.eigvals(w * w)).max()) if len(w) else 0.0


def dag_audit(edges: DataFrame) -> DataFrame:
    """``(n_edges, core_edges, acyclic)`` in one row."""
    whole, core = checked(edges), cyclic_core(edges)
    return whole.agg(F.count("*").alias("n_edges")).crossJoin(core.agg(F.count("*").alias("core_edges"))).withColumn("acyclic", F.col("core_edges") == 0)


def _reach_labels(core: DataFrame, forward: bool, rounds: int) -> DataFrame:
    """Smallest node that reaches each node (or that it reaches), on the core."""
    a, b = ("src", "dst") if forward else ("dst", "src")
    nodes = core.select(F.explode(F.array("src", "dst")).alias("node")).distinct()
    label = cut(nodes.select("node", F.col("node").alias("m")))
    for _ in range(rounds):
        moved = core.join(label, F.col(a) == F.col("node")).groupBy(b).agg(F.min("m").alias("n")).withColumnRenamed(b, "node")
        new = cut(label.join(moved, "node", "left").select("node", F.least("m", F.coalesce("n", "m")).alias("m")))
        if not new.exceptAll(label).take(1):
            return new
        label = new
    return label


LOCAL_EDGES = 200_000


def _local_components(src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    """For edges among nodes 0..n-1: each node's strongly connected component, as its smallest node."""
    n = int(max(src.max(), dst.max())) + 1
    order = np.argsort(src, kind="stable")
    first, to = np.searchsorted(src[order], np.arange(n + 1)), dst[order]
    number, low, on, stack, label, clock = [-1] * n, [0] * n, [False] * n, [], np.arange(n), 0
    for root in range(n):
        if number[root] >= 0:
            continue
        todo = [(root, int(first[root]))]
        while todo:
            v, i = todo.pop()
            if number[v] < 0:
                number[v] = low[v] = clock
                clock += 1
                stack.append(v)
                on[v] = True
            if i < first[v + 1]:
                u = int(to[i])
                todo.append((v, i + 1))
                if number[u] < 0:
                    todo.append((u, int(first[u])))
                elif on[u]:
                    low[v] = min(low[v], number[u])
                continue
            if low[v] == number[v]:
                part = []
                while True:
                    u = stack.pop()
                    on[u] = False
                    part.append(u)
                    if u == v:
                        break
                label[part] = min(part)
            if todo:
                low[todo[-1][0]] = min(low[todo[-1][0]], low[v])
    return label


def _collected(edges: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(node names, numbered src, numbered dst, w) of a table that is known to be small."""
    rows = edges.select("src", "dst", "w").toArrow()
    src, dst, w = (rows[c].to_numpy() for c in ("src", "dst", "w"))
    names, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    return names, at[: len(src)], at[len(src) :], w


def components(edges: DataFrame, rounds: int = 1000, local_edges: int = LOCAL_EDGES) -> DataFrame:
    """``(node, component)`` of the cyclic parts: nodes on common cycles share a component, named by its smallest node.

    A core of at most ``local_edges`` edges is solved in one process. Larger ones go by colours: the smallest node that reaches a
    node; within a colour, the nodes that reach its root make up one component, and the rest goes round again.
    """
    left, done = cyclic_core(edges), None
    kind = edges.schema["src"].dataType.simpleString()
    if left.limit(local_edges + 1).count() <= local_edges:
        names, src, dst, _ = _collected(left)
        if not len(names):
            return edges.sparkSession.createDataFrame([], f"node {kind}, component {kind}")
        label = _local_components(src, dst)
        big = np.flatnonzero(np.bincount(label, minlength=len(names))[label] > 1)
        return edges.sparkSession.createDataFrame([(names[i].item(), names[label[i]].item()) for i in big], f"node {kind}, component {kind}")
    while left.take(1):
        colour = _reach_labels(left, True, rounds)
        inside = left.join(colour.select(F.col("node").alias("src"), F.col("m").alias("cs")), "src").join(colour.select(F.col("node").alias("dst"), F.col("m").alias("cd")), "dst").where("cs = cd")
        reached = cut(colour.where("node = m"))
        size = reached.count()
        while True:
            more = inside.join(reached.select(F.col("node").alias("dst"), F.col("m").alias("cd")), ["dst", "cd"]).select(F.col("src").alias("node"), F.col("cd").alias("m"))
            reached = cut(reached.unionByName(more).distinct())
            if reached.count() == size:
                break
            size = reached.count()
        one = reached.join(reached.groupBy("m").count().where("count > 1"), "m", "left_semi").select("node", F.col("m").alias("component"))
        done = one if done is None else done.unionByName(one)
        gone = reached.select("node")
        left = cyclic_core(left.join(gone.withColumnRenamed("node", "src"), "src", "left_anti").join(gone.withColumnRenamed("node", "dst"), "dst", "left_anti").select("src", "dst", "w"))
    return done if done is not None else edges.select(F.col("src").alias("node"), F.col("src").alias("component")).limit(0)


def break_cycles(edges: DataFrame, rounds: int = 10_000, local_edges: int = 20_000) -> DataFrame:
    """A DAG: the weakest edge (by absolute weight, then ends) of every cyclic component goes until none is left."""
    now = cut(checked(edges).select("src", "dst", "w"))
    for _ in range(rounds):
        core = cyclic_core(now)
        n = core.limit(local_edges + 1).count()
        if not n:
            return now
        if n <= local_edges:
            names, src, dst, w = _collected(core)
            live, gone = np.ones(len(src), dtype=bool), []
            order = np.lexsort((dst, src, np.abs(w)))
            while True:
                label = _local_components(src[live], dst[live]) if live.any() else np.zeros(0)
                inner = [i for i in order if live[i] and label[src[i]] == label[dst[i]]]
                weakest = {int(label[src[i]]): i for i in reversed(inner)}
                if not weakest:
                    break
                live[list(weakest.values())] = False
                gone += [(names[src[i]].item(), names[dst[i]].item()) for i in weakest.values()]
            cuts = now.sparkSession.createDataFrame(gone, now.select("src", "dst").schema)
            return now.join(F.broadcast(cuts), ["src", "dst"], "left_anti")
        part = components(core)
        inner = core.join(part.select(F.col("node").alias("src"), "component"), "src").join(part.select(F.col("node").alias("dst"), F.col("component").alias("c2")), "dst").where("component = c2")
        weakest = inner.groupBy("component").agg(F.min(F.struct(F.abs("w").alias("v"), "src", "dst")).alias("x")).select("x.src", "x.dst")
        now = cut(now.join(weakest, ["src", "dst"], "left_anti"))
    raise RuntimeError("cycles remain")
