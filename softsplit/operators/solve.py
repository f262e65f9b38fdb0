"""Cell scores from the normal equations."""

from __future__ import annotations

import numpy as np


def solve_scores(a: np.ndarray, b: np.ndarray, lam: float) -> tuple[np.ndarray, str]:
    """w with (A + lam I) w = -b, and the way it was found.

    Cholesky where it works and the matrix is well conditioned, least squares of minimum norm otherwise.
    The ridge is added here, once, after all partitions were summed.
    """
    system = a + lam * np.eye(len(a))
    try:
        low = np.linalg.cholesky(system)
        if np.linalg.cond(system) <= 1e12:
            return -np.linalg.solve(low.T, np.linalg.solve(low, b)), "cholesky"
    except np.linalg.LinAlgError:
        pass
    return -np.linalg.lstsq(system, b, rcond=None)[0], "least_squares"


def round_objective(a: np.ndarray, b: np.ndarray, w: np.ndarray, lam: float) -> float:
    """The quadratic model of a round: b'w + w'Aw/2 + lam w'w/2."""
    return float(b @ w + 0.5 * w @ a @ w + 0.5 * lam * w @ w)


def residual(a: np.ndarray, b: np.ndarray, w: np.ndarray, lam: float) -> float:
    return float(np.linalg.norm((a + lam * np.eye(len(a))) @ w + b))
