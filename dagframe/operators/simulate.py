"""Planted graphs and samples, from md5 uniforms keyed by seed and position: equal in every engine and on every run."""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.functions.columns import normal, uniform


def er_dag(spark: SparkSession, d: int, edges_per_node: float = 2, seed: int = 7, most: int = 2000) -> DataFrame:
    """``(src, dst)``: each pair of a random order is an edge with equal chance; about ``edges_per_node`` * d in all."""
    if d > most:
        raise ValueError(f"all pairs of more than {most} nodes; use er_dag_large")
    p = min(1.0, 2.0 * edges_per_node / max(1, d - 1))
    node = spark.range(d).select(F.col("id").cast("int").alias("node")).withColumn("place", uniform(seed, "order", F.col("node")))
    a = node.select(F.col("node").alias("src"), F.col("place").alias("pa"))
    b = node.select(F.col("node").alias("dst"), F.col("place").alias("pb"))
    return a.crossJoin(b).where(F.col("pa") < F.col("pb")).where(uniform(seed, "edge", F.col("src"), F.col("dst")) < p).select("src", "dst")


def er_dag_large(spark: SparkSession, d: int, n_edges: int, seed: int = 7) -> DataFrame:
    """``(src, dst)`` with about ``n_edges`` edges, for any d: ends drawn by hash, turned along a random order."""
    at = lambda stream: F.floor(uniform(seed, stream, F.col("id")) * d).cast("int")
    place = lambda c: F.xxhash64(F.col(c), F.lit(seed))
    ends = spark.range(n_edges).select(at("s").alias("i"), at("t").alias("j")).where("i <> j")
    first = place("i") < place("j")
    return ends.select(F.when(first, F.col("i")).otherwise(F.col("j")).alias("src"), F.when(first, F.col("j")).otherwise(F.col("i")).alias("dst")).distinct()


def _local_uniform(*parts) -> float:
    return (int(hashlib.md5(":".join(map(str, parts)).encode(), usedforsecurity=False).hexdigest()[:8], 16) + 0.5) / 2**32


def sf_dag(spark: SparkSession, d: int, edges_per_node: int = 4, seed: int = 7) -> DataFrame:
    """``(src, dst)`` of a scale-free DAG: each new node points at up to ``edges_per_node`` earlier ones, chosen by degree."""
    ends, rows = [], []
    for new in range(1, d):
        chosen: set[int] = set()
        for k in range(4 * edges_per_node):
            if len(chosen) == min(edges_per_node, new):
                break
            u = _local_uniform(seed, "attach", new, k)
            chosen.add(ends[int(u * len(ends))] if ends and _local_uniform(seed, "mode", new, k) < 0.9 else int(u * new))
        rows += [(new, old) for old in sorted(chosen)]
        ends += [x for old in chosen for x in (old, new)]
    return spark.createDataFrame(rows, "src int, dst int")


def weights(edges: DataFrame, low: float = 0.5, high: float = 2.0, seed: int = 7) -> DataFrame:
    """``edges`` with ``w``, uniform in ±[low, high]."""
    size = low + (high - low) * uniform(seed, "weight", F.col("src"), F.col("dst"))
    return edges.withColumn("w", F.when(uniform(seed, "sign", F.col("src"), F.col("dst")) < 0.5, -size).otherwise(size))


def noise(kind: str, seed: int, *keys: Column) -> Column:
    """One draw with unit scale: ``gauss``, ``exp`` or ``gumbel``."""
    if kind == "gauss":
        return normal(seed, "noise", *keys)
    u = uniform(seed, "noise", *keys)
    if kind == "exp":
        return -F.log(u)
    if kind == "gumbel":
        return -F.log(-F.log(u))
    raise ValueError("noise is gauss, exp or gumbel")


def noise_cells(spark: SparkSession, n: int, d: int, kind: str = "gauss", seed: int = 7) -> DataFrame:
    """``(sample_id, node_id, x)`` of all n * d draws."""
    cells = spark.range(n * d).select(F.floor(F.col("id") / d).alias("sample_id"), (F.col("id") % d).cast("int").alias("node_id"))
    return cells.withColumn("x", noise(kind, seed, F.col("sample_id"), F.col("node_id")))


def sample(spark: SparkSession, edges: DataFrame, n: int, d: int, kind: str = "gauss", seed: int = 7, most: int = 5000) -> DataFrame:
    """``(sample_id, x array<double>)``: noise carried through the graph, solved in each task with the whole graph."""
    if d > most:
        raise ValueError(f"the graph of more than {most} nodes doesn't go to all tasks")
    w = np.zeros((d, d))
    rows = edges.select("src", "dst", "w").toArrow()
    w[rows["src"].to_numpy(), rows["dst"].to_numpy()] = rows["w"].to_numpy()
    held = spark.sparkContext.broadcast(np.linalg.inv(np.eye(d) - w))

    def run(batches):
        for b in batches:
            e = np.array(b.column(1).to_pylist(), dtype=np.float64).reshape(-1, d)
            x = e @ held.value
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * d), pa.array(x.ravel()))], ["sample_id", "x"])

    draws = spark.range(n).select(F.col("id").alias("sample_id"), F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: noise(kind, seed, F.col("id"), j)).alias("e"))
    return draws.mapInArrow(run, "sample_id long, x array<double>")


def sample_levels(edges: DataFrame, cells: DataFrame, depth: int) -> DataFrame:
    """``cells`` of noise with effects added level by level: the same values as ``sample``, as plain joins."""
    x, added = cells, cells
    for _ in range(depth):
        added = added.join(edges, added["node_id"] == edges["src"]).groupBy("sample_id", F.col("dst").alias("node_id")).agg(F.sum(F.col("x") * F.col("w")).alias("x"))
        x = x.unionByName(added)
    return x.groupBy("sample_id", "node_id").agg(F.sum("x").alias("x"))


def plant(frame: DataFrame, effects: list[tuple[str, str, float]]) -> DataFrame:
    """``frame`` with effects added on its own columns, in the order listed: child = child + w * parent."""
    for parent, child, w in effects:
        frame = frame.withColumn(child, F.col(child) + w * F.col(parent))
    return frame


def local_sample(w: np.ndarray, n: int, kind: str, seed: int) -> np.ndarray:
    """Samples in one process, for many small runs inside tasks."""
    r = np.random.default_rng(seed)
    e = {"gauss": r.standard_normal, "exp": r.standard_exponential, "gumbel": lambda s: r.gumbel(size=s)}[kind]((n, len(w)))
    return e @ np.linalg.inv(np.eye(len(w)) - w)


def local_dag(kind: str, d: int, edges_per_node: float, seed: int) -> np.ndarray:
    """A planted weight matrix in one process: ``er`` or ``sf``."""
    r = np.random.default_rng(seed)
    a = np.zeros((d, d), dtype=bool)
    if kind == "er":
        a = np.triu(r.random((d, d)) < min(1.0, 2 * edges_per_node / max(1, d - 1)), 1)
    else:
        ends: list[int] = []
        for new in range(1, d):
            m = min(int(edges_per_node), new)
            chosen: set[int] = set()
            while len(chosen) < m:
                chosen.add(int(ends[r.integers(len(ends))]) if ends and r.random() < 0.9 else int(r.integers(new)))
            for old in chosen:
                a[new, old] = True
                ends += [old, new]
    order = r.permutation(d)
    w = a * r.uniform(0.5, 2.0, (d, d)) * r.choice([-1.0, 1.0], (d, d))
    return w[np.ix_(order, order)]


SQRT_2PI = math.sqrt(2 * math.pi)
