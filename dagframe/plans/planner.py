"""Choice of engine by the size of a learning problem."""

from __future__ import annotations

DENSE_NODES = 2_000
LOCAL_EDGES = 20_000_000


def choose_engine(d: int, s: int, local_edges: int = LOCAL_EDGES) -> str:
    """``dense`` for few nodes, ``local_sparse`` while the edges fit one process, else ``distributed``."""
    if d <= DENSE_NODES:
        return "dense"
    return "local_sparse" if s <= local_edges else "distributed"


def moment_plan(d: int, n: int, nnz: int) -> str:
    """How second moments are built: one aggregate, blocks, or only the pairs that occur together."""
    if d <= 16:
        return "wide"
    return "blocked" if d <= 20_000 and nnz > 0.05 * n * d else "cells"
