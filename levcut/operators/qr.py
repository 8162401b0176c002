"""Deterministic choice of k columns of a small matrix by rank-revealing rules."""

from __future__ import annotations

import numpy as np

RULES = ("pivot", "low_rr", "high_rr", "window_rr", "strong_rr")


def _greedy(mat: np.ndarray, k: int, score) -> list[int]:
    """k rounds: the free column of best score, then its direction is projected out."""
    rest, chosen = mat.astype(float).copy(), []
    for _ in range(k):
        values = score(rest)
        values[chosen] = -1.0
        best = int(np.argmax(values > values.max() - 1e-12 * max(1.0, abs(values.max()))))
        chosen.append(best)
        q = rest[:, best] / max(np.linalg.norm(rest[:, best]), 1e-300)
        for _ in range(2):
            rest = rest - np.outer(q, q @ rest)
    return chosen


def pivot(mat: np.ndarray, k: int) -> list[int]:
    """Largest residual norm first."""
    return _greedy(mat, k, lambda r: np.linalg.norm(r, axis=0))


def low_rr(mat: np.ndarray, k: int) -> list[int]:
    """Largest part in the leading right singular vector of what is left."""

    def score(rest: np.ndarray) -> np.ndarray:
        return np.abs(np.linalg.svd(rest, full_matrices=False)[2][0])

    return _greedy(mat, k, score)


def high_rr(mat: np.ndarray, k: int) -> list[int]:
    """Columns leave one by one: the largest part in the singular vector of the smallest value."""
    keep = list(range(mat.shape[1]))
    while len(keep) > k:
        _, s, vt = np.linalg.svd(mat[:, keep], full_matrices=True)
        null = vt[-1]
        keep.pop(int(np.argmax(np.abs(null))))
    order = pivot(mat[:, keep], k)
    return [keep[i] for i in order]


def window_rr(mat: np.ndarray, k: int, window: int | None = None, tau: float = 0.5) -> list[int]:
    """Pivots only within a sliding window of columns if one is long enough, then swaps."""
    window = window or max(k, 4)
    rest, chosen = mat.astype(float).copy(), []
    for _ in range(k):
        norms = np.linalg.norm(rest, axis=0)
        norms[chosen] = -1.0
        free = [j for j in range(mat.shape[1]) if j not in chosen][:window]
        best = max(free, key=lambda j: (norms[j], -j))
        if norms[best] < tau * norms.max():
            best = int(norms.argmax())
        chosen.append(best)
        q = rest[:, best] / max(np.linalg.norm(rest[:, best]), 1e-300)
        rest = rest - np.outer(q, q @ rest)
    return _swap(mat, chosen, 2.0, 1)


def strong_rr(mat: np.ndarray, k: int, f: float = 2.0) -> list[int]:
    """From pivots, swaps while the volume of the chosen columns grows by more than f."""
    return _swap(mat, pivot(mat, k), f, 10 * k * k + 50)


def _swap(mat: np.ndarray, chosen: list[int], f: float, most: int) -> list[int]:
    chosen = list(chosen)
    for _ in range(most):
        c = mat[:, chosen]
        inverse = np.linalg.pinv(c)
        others = [j for j in range(mat.shape[1]) if j not in chosen]
        if not others:
            break
        inside = inverse @ mat[:, others]
        rest = np.linalg.norm(mat[:, others] - c @ inside, axis=0)
        rows = np.linalg.norm(inverse, axis=1)
        growth = inside**2 + np.outer(rows, rest) ** 2
        i, j = np.unravel_index(int(growth.argmax()), growth.shape)
        if growth[i, j] <= f * f:
            break
        chosen[i] = others[j]
    return chosen


def select(mat: np.ndarray, k: int, rule: str = "pivot", f: float = 2.0) -> list[int]:
    if mat.shape[1] < k:
        raise ValueError("fewer columns than k")
    if mat.shape[1] == k:
        return list(range(k))
    if rule == "strong_rr":
        return strong_rr(mat, k, f)
    return {"pivot": pivot, "low_rr": low_rr, "high_rr": high_rr, "window_rr": window_rr}[rule](mat, k)
