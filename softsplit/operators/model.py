"""The fitted model: what each round's soft splitter and cell scores need, as a small table."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

from ..functions.losses import Loss
from ..plans.kernel import Block, Spec, Work, assign, forward


@dataclass
class Round:
    round: int
    mu: np.ndarray
    sd: np.ndarray
    w: np.ndarray  # classes x cells
    solver: str = ""
    dead_cells: int = 0


@dataclass
class SSBModel:
    spec: Spec
    loss: Loss
    eta: float
    classes: int
    base_score: float = 0.0
    rounds: list[Round] = field(default_factory=list)
    history: list[dict] = field(default_factory=list)
    share: bool = True

    def scores(self, block: Block, upto: int | None = None, every: int | None = None) -> Iterator[tuple[int, np.ndarray]]:
        """(rounds done, scores) at the end, or after each `every` rounds."""
        score = np.full((block.n, self.classes), self.base_score)
        last = len(self.rounds) if upto is None else min(upto, len(self.rounds))
        for k, r in enumerate(self.rounds[:last], 1):
            score = score + self.eta * round_values(block, self.spec, r, self.share)
            if every and k % every == 0 and k < last:
                yield k, score
        yield last, score

    def transform(self, df: DataFrame, upto: int | None = None) -> DataFrame:
        """df (rid and features) with score array<double>: all rounds replayed in one narrow stage, mu and sd as trained."""
        model = df.sparkSession.sparkContext.broadcast(self)
        keep = [c for c in df.columns if c not in ("x", "codes", "vals")]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                (_, score), = model.value.scores(Block.of(batch, model.value.spec), upto)
                cols = [batch.column(c) for c in keep]
                cols.append(pa.array(list(score), pa.list_(pa.float64())) if batch.num_rows else pa.array([], pa.list_(pa.float64())))
                yield pa.RecordBatch.from_arrays(cols, names=[*keep, "score"])

        return df.mapInArrow(run, df.select(*keep).schema.add("score", T.ArrayType(T.DoubleType())))

    def staged(self, df: DataFrame, every: int = 1) -> DataFrame:
        """(columns kept, round, score) after each `every` rounds."""
        model = df.sparkSession.sparkContext.broadcast(self)
        keep = [c for c in df.columns if c not in ("x", "codes", "vals")]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for k, score in model.value.scores(Block.of(batch, model.value.spec), None, every):
                    cols = [batch.column(c) for c in keep] + [pa.array(np.full(batch.num_rows, k, np.int32)), pa.array(list(score), pa.list_(pa.float64()))]
                    yield pa.RecordBatch.from_arrays(cols, names=[*keep, "round", "score"])

        return df.mapInArrow(run, df.select(*keep).schema.add("round", T.IntegerType()).add("score", T.ArrayType(T.DoubleType())))

    def save(self, spark: SparkSession, path: str) -> None:
        rows = [
            (r.round, c, r.mu.tolist(), r.sd.tolist(), r.w[c].tolist(), r.solver, r.dead_cells)
            for r in self.rounds
            for c in range(len(r.w))
        ]
        head = {"spec": asdict(self.spec), "loss": self.loss.name, "eta": self.eta, "classes": self.classes, "base_score": self.base_score, "share": self.share}
        schema = "round int, cls int, mu array<double>, sd array<double>, w array<double>, solver string, dead_cells int"
        table = spark.createDataFrame(rows, schema).withColumn("head", F.lit(json.dumps(head)))
        table.coalesce(1).write.mode("overwrite").parquet(path)

    @staticmethod
    def load(spark: SparkSession, path: str) -> SSBModel:
        rows = spark.read.parquet(path).orderBy("round", "cls").collect()
        if not rows:
            raise ValueError(f"no model at {path}")
        head = json.loads(rows[0]["head"])
        spec = Spec(**{k: tuple(v) if isinstance(v, list) else v for k, v in head["spec"].items()})
        model = SSBModel(spec, Loss(head["loss"]), head["eta"], head["classes"], head["base_score"], share=head["share"])
        for r in rows:
            if r["cls"] == 0:
                model.rounds.append(Round(r["round"], np.array(r["mu"]), np.array(r["sd"]), np.zeros((0, len(r["w"]))), r["solver"], r["dead_cells"]))
            model.rounds[-1].w = np.vstack([model.rounds[-1].w, r["w"]])
        return model


def round_values(block: Block, spec: Spec, r: Round, share: bool = True, work: Work | None = None) -> np.ndarray:
    """f of a round for each class (n x classes); without sharing each class has cells of its own."""
    if share:
        return assign(forward(block, spec, r.round, work=work), r.mu, r.sd, spec) @ r.w.T
    k = spec.cells
    out = [
        assign(forward(block, spec, r.round, c, work=work), r.mu[c * k : (c + 1) * k], r.sd[c * k : (c + 1) * k], spec) @ r.w[c]
        for c in range(len(r.w))
    ]
    return np.array(out).T
