"""The spectral-radius bound of a weighted graph and its gradient, on edge tables.

A graph is ``EDGES(src, dst, w)``. Each round keeps one row per edge and one per node: masses are one grouped sum over both
ends (partial sums first), scales are a projection, rescaling joins the edges with the node table twice. Node tables are
joined without hints: adaptive execution sends them to all tasks when they turn out small, and shuffles otherwise. Lineage is
cut once a round, so a plan's size doesn't grow with the depth.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dagframe.plans.lineage import cut


class BoundOverflow(ArithmeticError):
    """The bound left the range of doubles: the balance doesn't suit the graph."""


def checked(edges: DataFrame) -> DataFrame:
    """The rows of an edge table that count: no loops, no nulls, no zero weights."""
    return edges.where("src is not null and dst is not null and src <> dst and w <> 0")


def square(edges: DataFrame) -> DataFrame:
    """The non-negative adjacency: every weight squared, in ``a``."""
    return edges.select("src", "dst", "w", (F.col("w") * F.col("w")).alias("a"))


def node_masses(adjacency: DataFrame) -> DataFrame:
    """``(node, out_mass, in_mass)`` of every node with an edge."""
    ends = adjacency.select(F.explode(F.array(F.struct(F.col("src").alias("node"), F.col("a").alias("o"), F.lit(0.0).alias("i")), F.struct(F.col("dst").alias("node"), F.lit(0.0).alias("o"), F.col("a").alias("i")))).alias("x"))
    return ends.groupBy(F.col("x.node").alias("node")).agg(F.sum("x.o").alias("out_mass"), F.sum("x.i").alias("in_mass"))


def _balanced(alpha: float) -> Column:
    out, inn = F.col("out_mass"), F.col("in_mass")
    if alpha == 0:
        return inn
    if alpha == 1:
        return out
    return F.when((out > 0) & (inn > 0), F.exp(alpha * F.log(out) + (1 - alpha) * F.log(inn))).otherwise(0.0)


def node_scale(state: DataFrame, alpha: float = 0.9) -> DataFrame:
    """``state`` with ``scale``, the geometric mix of both masses; zero where a mass that counts is zero."""
    if not 0 <= alpha <= 1:
        raise ValueError("alpha must be within 0 and 1")
    return state.withColumn("scale", _balanced(alpha))


def with_ends(edges: DataFrame, state: DataFrame, *names: str) -> DataFrame:
    """``edges`` with node columns of both ends, as ``name_src`` and ``name_dst``."""
    at = lambda end: state.select(F.col("node").alias(end), *[F.col(n).alias(f"{n}_{end}") for n in names])
    return edges.join(at("src"), "src").join(at("dst"), "dst")


def rescale(adjacency: DataFrame, state: DataFrame) -> DataFrame:
    """One round: every edge times its end's scale over its start's; zero where the start's scale is zero."""
    both = with_ends(adjacency, state, "scale")
    return both.select("src", "dst", "w", F.when(F.col("scale_src") > 0, F.col("a") * F.col("scale_dst") / F.col("scale_src")).otherwise(0.0).alias("a"))


@dataclass
class Round:
    """One round's edges and nodes."""

    adjacency: DataFrame
    state: DataFrame


def forward_states(edges: DataFrame, k: int = 5, alpha: float = 0.9) -> list[Round]:
    """All rounds 0..k; k rescalings in all."""
    adjacency, rounds = cut(square(checked(edges))), []
    for t in range(k + 1):
        state = cut(node_scale(node_masses(adjacency), alpha))
        rounds.append(Round(adjacency, state))
        if t < k:
            adjacency = cut(rescale(adjacency, state))
    return rounds


def _value(state: DataFrame, aggregate: str) -> DataFrame:
    if aggregate not in ("sum", "max"):
        raise ValueError("aggregate is sum or max")
    total = F.sum("scale") if aggregate == "sum" else F.max("scale")
    return state.agg(F.coalesce(total, F.lit(0.0)).alias("bound"))


def spectral_bound(edges: DataFrame, k: int = 5, alpha: float = 0.9, aggregate: str = "sum", peel_first: bool = False) -> DataFrame:
    """One row ``(bound)``, never below the spectral radius of the squared weights.

    ``aggregate="max"`` is the tighter valid bound by the largest scale. ``peel_first`` takes nodes without predecessors or
    successors away first, so an acyclic graph of any depth has bound 0.
    """
    if peel_first:
        from dagframe.operators.acyclicity import cyclic_core

        edges = cyclic_core(edges)
    return _value(forward_states(edges, k, alpha)[-1].state, aggregate)


def bound_value(edges: DataFrame, **options) -> float:
    """The bound as a number; raises if it isn't finite."""
    value = spectral_bound(edges, **options).first()["bound"]
    if value != value or value in (float("inf"), float("-inf")):
        raise BoundOverflow("the bound isn't finite; choose alpha nearer to the side of the smaller masses")
    return value


def bound_profile(edges: DataFrame, depth: int = 5, alpha: float = 0.9, aggregate: str = "sum") -> DataFrame:
    """``(k, bound)`` for k = 0..depth, from one run of the rounds."""
    rows = None
    for t, r in enumerate(forward_states(edges, depth, alpha)):
        one = _value(r.state, aggregate).select(F.lit(t).alias("k"), "bound")
        rows = one if rows is None else rows.unionByName(one)
    return rows


def suggest_alpha(edges: DataFrame, grid: tuple[float, ...] = (0.1, 0.3, 0.5, 0.7, 0.9), k: int = 2) -> float:
    """The grid's balance with the lowest finite bound; the grid is tried from the side that the larger masses suggest."""
    most = node_masses(square(checked(edges))).agg(F.max("out_mass").alias("o"), F.max("in_mass").alias("i")).first()
    order = sorted(grid, reverse=(most["o"] or 0) <= (most["i"] or 0))
    best = (float("inf"), order[0])
    for alpha in order:
        value = spectral_bound(edges, k, alpha).first()["bound"]
        if value == value and value < best[0]:
            best = (value, alpha)
    return best[1]


def local_partials(state: DataFrame, alpha: float = 0.9) -> DataFrame:
    """``state`` with ``fx`` and ``fy``, how the scale answers to the out-mass and the in-mass; zero beside a zero mass."""
    both = (F.col("out_mass") > 0) & (F.col("in_mass") > 0)
    ratio = F.log(F.col("in_mass")) - F.log(F.col("out_mass"))
    return state.withColumns({"fx": F.when(both, alpha * F.exp((1 - alpha) * ratio)).otherwise(0.0), "fy": F.when(both, (1 - alpha) * F.exp(-alpha * ratio)).otherwise(0.0)})


def gradient_dense0(state: DataFrame, alpha: float = 0.9, most: int = 2000) -> DataFrame:
    """``(src, dst, g)`` on all ordered pairs: the gradient at depth 0 without a mask. Only for up to ``most`` nodes."""
    if state.limit(most + 1).count() > most:
        raise ValueError(f"all pairs of more than {most} nodes; use bound_gradient")
    part = local_partials(state, alpha)
    return part.select(F.col("node").alias("src"), "fx").crossJoin(part.select(F.col("node").alias("dst"), "fy")).where("src <> dst").select("src", "dst", (F.col("fx") + F.col("fy")).alias("g"))


def _edges_with(adjacency: DataFrame, sensitivity: DataFrame) -> DataFrame:
    return adjacency.join(sensitivity, ["src", "dst"])


def node_sensitivity(held: DataFrame) -> DataFrame:
    """``(node, u)``: how the final value answers to a node's scale in the round that ``held`` rescaled.

    ``held``: edges with ``p`` (sensitivity to the rescaled weight), ``a``, ``scale_src`` and ``scale_dst`` of before.
    """
    live = F.col("scale_src") > 0
    gain = F.when(live, F.col("p") * F.col("a") / F.col("scale_src")).otherwise(0.0)
    loss = F.when(live, -F.col("p") * F.col("a") * F.col("scale_dst") / (F.col("scale_src") * F.col("scale_src"))).otherwise(0.0)
    ends = held.select(F.explode(F.array(F.struct(F.col("dst").alias("node"), gain.alias("v")), F.struct(F.col("src").alias("node"), loss.alias("v")))).alias("x"))
    return ends.groupBy(F.col("x.node").alias("node")).agg(F.sum("x.v").alias("u"))


def backward_round(sensitivity: DataFrame, before: Round, alpha: float) -> DataFrame:
    """Sensitivities ``(src, dst, p)`` to the weights of the round before, on its edges only."""
    state = local_partials(before.state, alpha)
    held = with_ends(_edges_with(before.adjacency, sensitivity), state, "scale", "fx", "fy")
    u = node_sensitivity(held)
    both = with_ends(held, u, "u")
    kept = F.when(F.col("scale_src") > 0, F.col("p") * F.col("scale_dst") / F.col("scale_src")).otherwise(0.0)
    return both.select("src", "dst", (kept + F.col("u_src") * F.col("fx_src") + F.col("u_dst") * F.col("fy_dst")).alias("p"))


def _gradient(rounds: list[Round], alpha: float) -> DataFrame:
    last = local_partials(rounds[-1].state, alpha)
    now = cut(with_ends(rounds[-1].adjacency, last, "fx", "fy").select("src", "dst", (F.col("fx_src") + F.col("fy_dst")).alias("p")))
    for before in reversed(rounds[:-1]):
        now = cut(backward_round(now, before, alpha))
    return _edges_with(rounds[0].adjacency, now).select("src", "dst", "w", (2 * F.col("p") * F.col("w")).alias("g"))


def bound_gradient(edges: DataFrame, k: int = 5, alpha: float = 0.9) -> DataFrame:
    """``(src, dst, w, g)``: the bound's gradient by the weights, on existing edges only."""
    return _gradient(forward_states(edges, k, alpha), alpha)


def value_and_gradient(edges: DataFrame, k: int = 5, alpha: float = 0.9) -> tuple[float, DataFrame]:
    """The bound as a number and its gradient ``(src, dst, w, g)``, from one forward pass."""
    rounds = forward_states(edges, k, alpha)
    return _value(rounds[-1].state, "sum").first()["bound"], _gradient(rounds, alpha)
