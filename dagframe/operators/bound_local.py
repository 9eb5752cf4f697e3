"""The same bound and gradient in one process, on coordinate arrays or dense matrices; all in NumPy.

For graphs whose edges fit one process: learners call it in their inner loop, many models at once inside grouped maps.
"""

from __future__ import annotations

import numpy as np


def _mix(out: np.ndarray, inn: np.ndarray, alpha: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    live = (out > 0) & (inn > 0)
    lo, li = np.log(np.where(live, out, 1)), np.log(np.where(live, inn, 1))
    if alpha in (0, 1):
        scale = out if alpha else inn
    else:
        scale = np.where(live, np.exp(alpha * lo + (1 - alpha) * li), 0.0)
    return scale, np.where(live, alpha * np.exp((1 - alpha) * (li - lo)), 0.0), np.where(live, (1 - alpha) * np.exp(alpha * (lo - li)), 0.0)


def _over(x: np.ndarray, by: np.ndarray) -> np.ndarray:
    return np.divide(x, by, out=np.zeros_like(x), where=by > 0)


def value_and_grad(src: np.ndarray, dst: np.ndarray, w: np.ndarray, d: int, k: int = 5, alpha: float = 0.9, gradient: bool = True) -> tuple[float, np.ndarray | None]:
    """The bound of edges (src, dst, w) among d nodes, and its gradient by the weights."""
    total = lambda at, x: np.bincount(at, weights=x, minlength=d)
    a, kept = w * w, []
    for t in range(k + 1):
        out, inn = total(src, a), total(dst, a)
        scale, fx, fy = _mix(out, inn, alpha)
        kept.append((a, scale, fx, fy))
        if t < k:
            a = a * _over(scale[dst], scale[src])
    value = float(kept[-1][1].sum())
    if not np.isfinite(value) or not np.isfinite(kept[0][0]).all():
        raise ArithmeticError("the bound isn't finite")
    if not gradient:
        return value, None
    p = kept[-1][2][src] + kept[-1][3][dst]
    for a, scale, fx, fy in reversed(kept[:-1]):
        u = total(dst, p * _over(a, scale[src])) - total(src, p * _over(a * scale[dst], scale[src] ** 2))
        p = p * _over(scale[dst], scale[src]) + u[src] * fx[src] + u[dst] * fy[dst]
    return value, 2 * p * w


def dense_value_and_grad(w: np.ndarray, k: int = 5, alpha: float = 0.9, mask: np.ndarray | None = None) -> tuple[float, np.ndarray]:
    """The same over a full matrix; ``mask`` limits the recurrence to its entries from the start (None: no mask)."""
    hold = 1.0 if mask is None else mask
    a, kept = w * w, []
    for t in range(k + 1):
        scale, fx, fy = _mix(a.sum(1), a.sum(0), alpha)
        kept.append((a, scale, fx, fy))
        if t < k:
            a = _over(a * scale[None, :], np.broadcast_to(scale[:, None], a.shape))
    p = (kept[-1][2][:, None] + kept[-1][3][None, :]) * hold
    for a, scale, fx, fy in reversed(kept[:-1]):
        wide = np.broadcast_to(scale[:, None], a.shape)
        u = _over(p * a, wide).sum(0) - _over(p * a * scale[None, :], wide**2).sum(1)
        p = (_over(p * scale[None, :], wide) + (u * fx)[:, None] + (u * fy)[None, :]) * hold
    return float(kept[-1][1].sum()), 2 * p * w
