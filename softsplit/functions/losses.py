"""Losses by their first and second derivatives, in numpy for the kernels and as Catalyst expressions."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, functions as F

FLOOR = 1e-6  # least curvature


def sigmoid(s: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-np.clip(s, -500, 500)))


@dataclass(frozen=True)
class Loss:
    """grad_hess(score (n x C), y) -> g, h (n x C); value -> mean loss."""

    name: str
    fn: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None

    @staticmethod
    def custom(fn: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> Loss:
        """A loss of one score given by its row values; derivatives by central differences."""
        return Loss("custom", fn)

    def grad_hess(self, score: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if self.name == "squared":
            return score - y[:, None], np.ones_like(score)
        if self.name == "logistic":
            p = sigmoid(score)
            return p - y[:, None], np.maximum(p * (1 - p), FLOOR)
        if self.name == "poisson":
            e = np.exp(np.clip(score, -30, 30))
            return e - y[:, None], np.maximum(e, FLOOR)
        if self.name == "softmax":
            q = np.exp(score - score.max(1, keepdims=True))
            q /= q.sum(1, keepdims=True)
            g = q.copy()
            g[np.arange(len(y)), y.astype(np.int64)] -= 1
            return g, np.maximum(q * (1 - q), FLOOR)
        if self.fn is not None:
            s, e = score[:, 0], 1e-4
            up, mid, low = self.fn(s + e, y), self.fn(s, y), self.fn(s - e, y)
            g, h = (up - low) / (2 * e), (up - 2 * mid + low) / (e * e)
            return g[:, None], np.maximum(h, FLOOR)[:, None]
        raise ValueError(f"unknown loss {self.name!r}")

    def value(self, score: np.ndarray, y: np.ndarray) -> np.ndarray:
        """The loss of each row."""
        if self.name == "squared":
            return 0.5 * (score[:, 0] - y) ** 2
        if self.name == "logistic":
            return np.logaddexp(0, score[:, 0]) - y * score[:, 0]
        if self.name == "poisson":
            return np.exp(np.clip(score[:, 0], -30, 30)) - y * score[:, 0]
        if self.name == "softmax":
            top = score.max(1)
            return top + np.log(np.exp(score - top[:, None]).sum(1)) - score[np.arange(len(y)), y.astype(np.int64)]
        return self.fn(score[:, 0], y)

    def columns(self, y: int) -> int:
        return y if self.name == "softmax" else 1


def logistic_expr(score: Column, y: Column) -> tuple[Column, Column]:
    p = F.lit(1.0) / (F.lit(1.0) + F.exp(-score))
    return p - y, F.greatest(p * (1 - p), F.lit(FLOOR))


def squared_expr(score: Column, y: Column) -> tuple[Column, Column]:
    return score - y, F.lit(1.0)


def poisson_expr(score: Column, y: Column) -> tuple[Column, Column]:
    return F.exp(score) - y, F.greatest(F.exp(score), F.lit(FLOOR))


def softmax_expr(scores: Column, y: Column) -> tuple[Column, Column]:
    """Arrays of g and h over the classes."""
    top = F.array_max(scores)
    total = F.aggregate(scores, F.lit(0.0), lambda acc, s: acc + F.exp(s - top))
    q = F.transform(scores, lambda s: F.exp(s - top) / total)
    g = F.transform(q, lambda v, k: v - F.when(k == y, 1.0).otherwise(0.0))
    return g, F.transform(q, lambda v: F.greatest(v * (1 - v), F.lit(FLOOR)))
