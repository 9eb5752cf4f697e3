"""First-order steps on edge tables and arrays. ``EDGE_STATE(src, dst, w, m1, m2)``."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def adam(state: DataFrame, grad: DataFrame, step: int, lr: float = 0.01, beta1: float = 0.9, beta2: float = 0.999, eps: float = 1e-8) -> DataFrame:
    """``state`` after one Adam step along ``grad(src, dst, g)``; edges only, one co-partitioned join."""
    joined = state.join(grad.select("src", "dst", "g"), ["src", "dst"])
    m1 = beta1 * F.col("m1") + (1 - beta1) * F.col("g")
    m2 = beta2 * F.col("m2") + (1 - beta2) * F.col("g") * F.col("g")
    move = lr * (m1 / (1 - beta1**step)) / (F.sqrt(m2 / (1 - beta2**step)) + eps)
    return joined.select("src", "dst", (F.col("w") - move).alias("w"), m1.alias("m1"), m2.alias("m2"))


def sgd(state: DataFrame, grad: DataFrame, lr: float = 0.01) -> DataFrame:
    return state.join(grad.select("src", "dst", "g"), ["src", "dst"]).select("src", "dst", (F.col("w") - lr * F.col("g")).alias("w"), *[c for c in state.columns if c not in ("src", "dst", "w")])


def proximal(state: DataFrame, grad: DataFrame, lr: float = 0.01, lam: float = 0.1) -> DataFrame:
    """A gradient step of the smooth part, then soft thresholding; edges at zero go."""
    moved = sgd(state, grad, lr)
    small = F.greatest(F.abs("w") - lr * lam, F.lit(0.0))
    return moved.withColumn("w", F.signum("w") * small).where("w <> 0")


def start(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst", "w", F.lit(0.0).alias("m1"), F.lit(0.0).alias("m2"))


class Adam:
    """The same step on arrays."""

    def __init__(self, shape, lr: float = 0.01, beta1: float = 0.9, beta2: float = 0.999, eps: float = 1e-8):
        self.m1, self.m2, self.t, self.lr, self.b1, self.b2, self.eps = np.zeros(shape), np.zeros(shape), 0, lr, beta1, beta2, eps

    def step(self, w: np.ndarray, g: np.ndarray) -> np.ndarray:
        self.t += 1
        self.m1 = self.b1 * self.m1 + (1 - self.b1) * g
        self.m2 = self.b2 * self.m2 + (1 - self.b2) * g * g
        return w - self.lr * (self.m1 / (1 - self.b1**self.t)) / (np.sqrt(self.m2 / (1 - self.b2**self.t)) + self.eps)

    def keep(self, live: np.ndarray) -> None:
        self.m1, self.m2 = self.m1[live], self.m2[live]
