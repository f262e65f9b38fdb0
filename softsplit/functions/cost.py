"""Cost measures: bytes, hashes, numbers, times and their ratios."""

from __future__ import annotations

import math
import statistics
import time
from collections.abc import Sequence


def comm_bytes(method: str, **d: float) -> float:
    """Bytes of a round, in 8-byte numbers.

    ssb: cells, classes. exact: classes, levels (pairs of nodes and candidates summed over features).
    hist: classes, nodes, features, bins.
    """
    if method == "ssb":
        k, c = d["cells"], d.get("classes", 1)
        return 8 * (2 * k + 1) + 8 * c * (k * (k + 1) / 2 + k)
    if method == "exact":
        return 16 * d.get("classes", 1) * sum(nodes * candidates for nodes, candidates in d["levels"])
    if method == "hist":
        return 16 * d.get("classes", 1) * d["nodes"] * d["features"] * d["bins"]
    raise ValueError(f"unknown method {method!r}")


def hash_calls(layout: str, cells: int, features: int, nnz: int) -> int:
    """Column layout hashes each feature once for each cell, row layout each non-zero."""
    return cells * (features if layout == "column" else nnz)


def model_numbers(method: str, rounds: int, cells: int, classes: int = 1) -> int:
    """ssb: one score for each round, cell and class; trees: split and leaf numbers of nodes for each class."""
    return rounds * classes * cells if method == "ssb" else rounds * classes * (2 * cells - 1)


def weight_matrix_bytes(features: int, cells: int) -> int:
    return 8 * features * cells


def sync_count(method: str, levels: int = 0) -> int:
    return 2 if method == "ssb" else levels


def modelled_round_s(compute_s: float, bytes_: float, bandwidth: float) -> float:
    """A model, not a measurement: no throttle is available."""
    return compute_s + bytes_ / bandwidth


def choose_forward(density: float) -> str:
    """Sparse kernels pay off above 98.5 % zeros."""
    return "sparse" if 1 - density > 0.985 else "dense"


def speedup(t_ref: float, t: float) -> float:
    return t_ref / t


def scaling_ratio(times: Sequence[float]) -> list[float]:
    return [t / times[0] for t in times]


def ideal_ratio(machines: Sequence[int]) -> list[float]:
    return [machines[0] / s for s in machines]


def nnz_budget(row_nnz: Sequence[int], batches: int) -> tuple[int, int]:
    """Non-zeros and rows of a batch: the largest row or an equal share; rows from the lower quartile of row sizes.

    The quotient by the number of all rows that was also proposed is no row count; see row_cap.
    """
    budget = max(max(row_nnz), math.ceil(sum(row_nnz) / batches))
    quartile = max(sorted(row_nnz)[len(row_nnz) // 4], 1)
    return budget, math.ceil(budget / quartile)


class RoundTimer:
    """Wall seconds of rounds: mean and sample sd, the first round left out as warm-up."""

    def __init__(self):
        self.samples: list[float] = []

    def __call__(self, round_: int, wall: float) -> None:
        self.samples.append(wall)

    def time(self, fn) -> float:
        began = time.perf_counter()
        fn()
        self.samples.append(time.perf_counter() - began)
        return self.samples[-1]

    def summary(self) -> dict[str, float]:
        kept = self.samples[1:] or self.samples
        return {"mean_s": statistics.fmean(kept), "sd_s": statistics.stdev(kept) if len(kept) > 1 else 0.0, "rounds": len(kept)}
