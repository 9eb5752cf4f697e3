"""The SQL surface: functions and table functions under plain names."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from dagframe.operators.bound_local import value_and_grad


@pandas_udf("double")
def group_bound(src: pd.Series, dst: pd.Series, w: pd.Series) -> float:
    """The bound of one group's edges: ``select k, spectral_bound(src, dst, w) from edges group by k``."""
    nodes, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    return value_and_grad(at[: len(src)], at[len(src) :], w.to_numpy(dtype=float), len(nodes), gradient=False)[0] if len(src) else 0.0


@pandas_udf("double")
def group_auc(score: pd.Series, positive: pd.Series) -> float:
    """Area under the ROC curve of a group's scores; ties half."""
    rank = score.rank().to_numpy()
    y = positive.to_numpy(dtype=bool)
    p, n = y.sum(), (~y).sum()
    return float((rank[y].sum() - p * (p + 1) / 2) / (p * n)) if p and n else 0.5


@pandas_udf("double")
def exact_normal_tail(z: pd.Series) -> pd.Series:
    """P(Z >= z) to machine precision."""
    from math import erfc, sqrt

    return z.map(lambda x: 0.5 * erfc(x / sqrt(2)))


@udtf(returnType="path array<int>, weight double")
class PathsInto:
    """Paths into a target from nodes without parents, over the edges of one row: arrays src, dst, w."""

    def eval(self, src: list, dst: list, w: list, target: int, longest: int):
        parents: dict = {}
        for a, b, v in zip(src, dst, w, strict=True):
            parents.setdefault(b, []).append((a, v))
        todo = [([target], 1.0)]
        while todo:
            path, weight = todo.pop()
            above = [(a, v) for a, v in parents.get(path[0], []) if a not in path]
            if not parents.get(path[0]) and len(path) > 1:
                yield path, weight
            elif len(path) < longest:
                todo += [([a, *path], weight * v) for a, v in above]


def register(spark: SparkSession) -> None:
    """``spectral_bound``, ``roc_auc`` (aggregates), ``normal_tail_exact`` (scalar) and ``paths_into`` (table function)."""
    spark.udf.register("spectral_bound", group_bound)
    spark.udf.register("roc_auc", group_auc)
    spark.udf.register("normal_tail_exact", exact_normal_tail)
    spark.udtf.register("paths_into", PathsInto)


def tail_column(z):
    return exact_normal_tail(F.col(z) if isinstance(z, str) else z)
