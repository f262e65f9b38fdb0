"""Functions for SQL: an expression for weights, a vectorised assignment, a scorer, a table function, a Gram aggregate."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators.model import SSBModel
from ..plans.kernel import Block
from .hashing import hash_weight


@F.udtf(returnType="word: string")
class ExplodeFeatures:
    """The distinct lower-case words of a text, a row each."""

    def eval(self, text: str):
        seen = dict.fromkeys(w for w in (text or "").lower().replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" ") if w)
        for w in seen:
            yield (w,)


@F.udtf(returnType="j: int, k: int")
class TriangleIndex:
    """The pairs j <= k below K."""

    def eval(self, cells: int):
        for j in range(cells):
            for k in range(j, cells):
                yield j, k


@F.pandas_udf("array<double>")
def soft_assign_udf(z: pd.Series) -> pd.Series:
    """Softmax of each array."""
    if not len(z):
        return z
    x = np.vstack(z.to_numpy())
    x = np.exp(x - x.max(1, keepdims=True))
    return pd.Series(list(x / x.sum(1, keepdims=True)))


@F.pandas_udf("array<double>")
def gram_udaf(p: pd.Series, h: pd.Series) -> list:
    """Upper triangle of sum h p p' of a group, for up to about 64 cells."""
    x = np.vstack(p.to_numpy())
    a = (x * h.to_numpy()[:, None]).T @ x
    return a[np.triu_indices(len(a))].tolist()


def ssb_score(model: SSBModel):
    """A vectorised scorer of dense features for SQL."""

    @F.pandas_udf("array<double>")
    def score(x: pd.Series) -> pd.Series:
        (_, s), = model.scores(Block(len(x), x=np.vstack(x.to_numpy()))) if len(x) else ((0, np.zeros((0, 1))),)
        return pd.Series(list(s))

    return score


def solve_groups(sums: DataFrame, cells: int, lam: float) -> DataFrame:
    """(cls, w) from rows (cls, v): systems of many classes solved side by side."""
    from ..operators.solve import solve_scores
    from ..plans.kernel import gram_parts

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            w = [solve_scores(*gram_parts(np.array(v), cells), lam)[0].tolist() for v in pdf["v"]]
            yield pd.DataFrame({"cls": pdf["cls"], "w": w})

    return sums.mapInPandas(run, "cls int, w array<double>")


def register(spark: SparkSession, model: SSBModel | None = None) -> None:
    spark.udtf.register("explode_features", ExplodeFeatures)
    spark.udtf.register("tri_index", TriangleIndex)
    spark.udf.register("soft_assign_udf", soft_assign_udf)
    if model is not None:
        spark.udf.register("ssb_score", ssb_score(model))


def hash_weight_expr(feature: str, round_: int, cell: str):
    """The weight of a feature column for a cell column, as an expression."""
    return hash_weight(F.col(feature), round_, F.col(cell))
