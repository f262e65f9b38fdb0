"""Grid search over model size, shrinkage and ridge, and the choice of the best round."""

from __future__ import annotations

import itertools
import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions import metrics
from ..plans.kernel import Spec
from .boost import fit


def grid_table(spark: SparkSession, space: dict[str, list], folds: int | DataFrame = 1) -> DataFrame:
    """All combinations of the parameters with fold numbers, or with a table of folds, by cross joins of small tables."""
    out = None
    for name, values in space.items():
        kind = "int" if all(isinstance(v, int) for v in values) else "double"
        one = spark.createDataFrame([(v,) for v in values], f"{name} {kind}")
        out = one if out is None else out.crossJoin(one)
    numbered = spark.range(folds).select(F.col("id").cast("int").alias("fold")) if isinstance(folds, int) else folds
    return out.crossJoin(numbered)


def grid_search(
    train: DataFrame, valid: DataFrame, spec: Spec, space: dict[str, list], rounds: int, loss: str = "logistic", classes: int = 1,
    metric: str = "auc", budget_s: float = 86_400.0, large_rows: int = 1_000_000, engine: str = "local",
) -> list[dict]:
    """A row for each combination: best value and round on `valid`, or state `skipped`.

    Above `large_rows` training rows the ridge is set to 0. A combination is skipped when the rounds, at the
    pace of the size tried before, would take longer than `budget_s`.
    """
    n = train.count()
    lams = [0.0] if n > large_rows else space.get("lam", [1.0])
    out = []
    for cells in space.get("cells", [64]):
        pace = 0.0
        for eta, lam in itertools.product(space.get("eta", [0.3]), lams):
            row = {"cells": cells, "eta": eta, "lam": lam}
            if pace * rounds > budget_s:
                out.append({**row, "state": "skipped", "best_value": None, "best_round": None})
                continue
            began = time.perf_counter()
            model = fit(train, replace(spec, cells=cells), loss, rounds, lam, eta, classes, engine=engine)
            pace = (time.perf_counter() - began) / rounds
            best = metrics.best_round(metrics.curve(model.staged(valid), metric)).first()
            out.append({**row, "state": "done", "best_value": best["best_value"], "best_round": best["best_round"]})
    return out
