"""Trainers of soft-split boosting. All make the same sums in different places.

A round needs two global steps: {row count, sums and sums of squares of the raw outputs} and {Gram matrix,
gradient}. Only these cross the network, and their size depends on the cells and classes, never on rows or
features. The first one needs no label or score, so the jobs engine takes it for many rounds in one scan.

engine="jobs"     driver loop; rows are packed in blocks once, and a round is one pass over them that adds the
                  last round's scores and makes the next sums; only block numbers and scores are kept anew
engine="barrier"  one stage holds all partitions; sums are exchanged by allGather
engine="local"    one process streams a partition in blocks, with work arrays allocated once
"""

from __future__ import annotations

import base64
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import BarrierTaskContext, StorageLevel, TaskContext
from pyspark.sql import DataFrame, functions as F

from ..functions.losses import Loss
from ..plans.kernel import Block, Spec, Work, assign, draw_splitter, forward, gram, gram_parts, moments, statistics
from .model import Round, SSBModel, round_values
from .solve import round_objective, solve_scores

#: Bytes of one global step's vectors (partitions x numbers) above which they are summed on executors first.
DRIVER_SUM_BYTES = 256 << 20
#: Rows whose scores may be kept on the driver.
DRIVER_ROWS = 1_000_000
#: Dense features up to which statistics of all rounds come from one scan of their second moments.
MOMENT_FEATURES = 512


def pin(df: DataFrame, partitions: int) -> DataFrame:
    """The training layout: rows dealt once to `partitions` by rid; features are never moved again."""
    return df.repartition(partitions, "rid")


def _memberships(
    block: Block, spec: Spec, round_: int, mu: np.ndarray, sd: np.ndarray, classes: int, share: bool, work: Work | None = None
) -> list[np.ndarray]:
    if share:
        return [assign(forward(block, spec, round_, work=work), mu, sd, spec)]
    k = spec.cells
    return [assign(forward(block, spec, round_, c, work=work), mu[c * k : (c + 1) * k], sd[c * k : (c + 1) * k], spec) for c in range(classes)]


def _raw_stats(block: Block, spec: Spec, round_: int, classes: int, share: bool, work: Work | None = None) -> np.ndarray:
    """[n, sums, sums of squares], the cells of all classes after each other."""
    own = [statistics(forward(block, spec, round_, c, work=work)) for c in range(1 if share else classes)]
    k = spec.cells
    return np.concatenate([own[0][:1], *[x[1 : k + 1] for x in own], *[x[k + 1 :] for x in own]])


def _grams(ps: list[np.ndarray], g: np.ndarray, h: np.ndarray) -> np.ndarray:
    if len(ps) == 1:
        return gram(ps[0], g, h)
    return np.vstack([gram(p, g[:, c : c + 1], h[:, c : c + 1]) for c, p in enumerate(ps)])


def _solve_round(round_: int, total: np.ndarray, mu: np.ndarray, sd: np.ndarray, cells: int, lam: float) -> tuple[Round, float]:
    ws, paths, objective = [], [], 0.0
    for vector in total:
        a, b = gram_parts(vector, cells)
        w, path = solve_scores(a, b, lam)
        ws.append(w)
        paths.append(path)
        objective += round_objective(a, b, w, lam)
    return Round(round_, mu, sd, np.array(ws), ",".join(sorted(set(paths))), int((sd == 0).sum())), objective


def _vector_sum(parts: DataFrame, numbers: int, n_parts: int | None = None) -> tuple[np.ndarray, int]:
    """Sum of the float64 vectors in column v; many or large ones are summed in groups on executors first."""
    n_parts = n_parts or parts.rdd.getNumPartitions()

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = None
        for batch in batches:
            for v in batch.column("v").to_pylist():
                total = np.frombuffer(v).copy() if total is None else total + np.frombuffer(v)
        if total is not None:
            yield _emit(total)

    while n_parts > 16 and n_parts * numbers * 8 > DRIVER_SUM_BYTES:
        n_parts = -(-n_parts // 16)
        parts = parts.repartition(n_parts, "pid").mapInArrow(add, "pid long, v binary")
    rows = parts.collect()
    rows.sort(key=lambda r: r["pid"])
    sent = sum(len(r["v"]) for r in rows)
    if not rows:
        return np.zeros(numbers), 0
    return np.sum([np.frombuffer(r["v"]) for r in rows], axis=0), sent


def _emit(vector: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(
        [pa.array([TaskContext.get().partitionId()], pa.int64()), pa.array([np.ascontiguousarray(vector, np.float64).tobytes()], pa.binary())],
        names=["pid", "v"],
    )


def cell_stats_block(df: DataFrame, spec: Spec, rounds: list[int], classes: int = 1, share: bool = True) -> tuple[np.ndarray, int]:
    """Statistics of several rounds in one scan (rounds x numbers), and the bytes sent."""
    width = 2 * spec.cells * (1 if share else classes) + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, work = np.zeros((len(rounds), width)), Work(spec)
        for batch in batches:
            for block in _blocks_of(batch, spec):
                for k, r in enumerate(rounds):
                    total[k] += _raw_stats(block, spec, r, classes, share, work)
        yield _emit(total.ravel())

    cols = _PACKED if "bid" in df.columns else ["x"] if spec.kind == "dense" else ["codes", "vals"]
    total, sent = _vector_sum(df.select(*cols).mapInArrow(run, "pid long, v binary"), len(rounds) * width)
    return total.reshape(len(rounds), width), sent


def _blocks_of(batch: pa.RecordBatch, spec: Spec) -> Iterator[Block]:
    """Prepared blocks of a batch of rows or of packed blocks."""
    if "bid" in batch.schema.names:
        for row in batch.to_pylist():
            yield _unpacked(row, spec)
        return
    whole = Block.of(batch, spec)
    for a, b in whole.parts(spec):
        yield whole.prepared(a, b)


def moment_stats(df: DataFrame, spec: Spec, rounds: list[int], classes: int = 1, share: bool = True) -> tuple[np.ndarray, int]:
    """The same statistics from one scan of sum x and sum x x' for any rounds (dense, no hidden layers), and the bytes sent: z is linear in x."""
    m = spec.m

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 + m + m * m)
        for batch in batches:
            for block in _blocks_of(batch, spec):
                total += np.concatenate([[block.n], block.x.sum(0), (block.x.T @ block.x).ravel()])
        yield _emit(total)

    cols = _PACKED if "bid" in df.columns else ["x"]
    total, sent = _vector_sum(df.select(*cols).mapInArrow(run, "pid long, v binary"), 1 + m + m * m)
    square = total[m + 1 :].reshape(m, m)
    out = []
    for r in rounds:
        ws = [draw_splitter(spec, r, c) for c in range(1 if share else classes)]
        out.append(np.concatenate([[total[0]], *[total[1 : m + 1] @ w for w in ws], *[((square @ w) * w).sum(0) for w in ws]]))
    return np.array(out), sent


_PACKED = ["bid", "n", "y", "rid", "x", "offsets", "feats", "back", "vals"]
_PACKED_SCHEMA = "bid long, n int, y binary, rid binary, x binary, offsets binary, feats binary, back binary, vals binary"


def pack(rows: DataFrame, spec: Spec, parts: int) -> DataFrame:
    """Rows (rid, y and features) as prepared blocks, dealt by block number bid.

    Rows are dealt by rid and put in its order first, so that a lost block is made again with the same rows;
    the features of a block never move after that. Block numbers are chosen so that dealing by bid puts the
    blocks of a partition into one partition again.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        numbers = numbers_dealt_to(TaskContext.get().partitionId(), parts)
        for batch in batches:
            whole, y, rid = Block.of(batch, spec), _labels(batch), _numbers(batch)
            for a, b in whole.parts(spec):
                block = whole.prepared(a, b)
                parts_ = (block.x, block.offsets, block.feats, block.back, block.vals)
                kinds = (np.float64, np.int32, np.int64, np.int32, np.float64)
                held = [None if v is None else np.ascontiguousarray(v, k).tobytes() for v, k in zip(parts_, kinds)]
                row = [next(numbers), b - a, y[a:b].tobytes(), rid[a:b].tobytes(), *held]
                types = [pa.int64(), pa.int32()] + [pa.binary()] * 7
                yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, types)], names=_PACKED)

    return pin(rows, parts).sortWithinPartitions("rid", "y").mapInArrow(run, _PACKED_SCHEMA).repartition(parts, "bid")


def numbers_dealt_to(part: int, parts: int) -> Iterator[int]:
    """Ascending numbers from 0 on that repartition(parts, number) deals to a partition: those whose murmur3 hash falls there."""
    at, step = 0, max(1024, 64 * parts)
    while True:
        given = np.arange(at, at + step)
        yield from given[murmur3(given) % parts == part].tolist()
        at += step


def murmur3(values: np.ndarray) -> np.ndarray:
    """Spark's hash() of bigint values."""
    turn = lambda x, by: (x << np.uint32(by)) | (x >> np.uint32(32 - by))
    h = np.full(len(values), 42, np.uint32)
    bits = values.astype(np.int64).view(np.uint64)
    for half in (bits, bits >> np.uint64(32)):
        k = (half & np.uint64(0xFFFFFFFF)).astype(np.uint32) * np.uint32(0xCC9E2D51)
        h = turn(h ^ turn(k, 15) * np.uint32(0x1B873593), 13) * np.uint32(5) + np.uint32(0xE6546B64)
    h ^= np.uint32(8)
    for by, times in ((16, 0x85EBCA6B), (13, 0xC2B2AE35)):
        h = (h ^ (h >> np.uint32(by))) * np.uint32(times)
    return (h ^ (h >> np.uint32(16))).view(np.int32).astype(np.int64)


def _unpacked(row: dict, spec: Spec) -> Block:
    if row["x"] is not None:
        return Block(row["n"], x=np.frombuffer(row["x"]).reshape(row["n"], -1))
    vals = None if row["vals"] is None else np.frombuffer(row["vals"])
    offsets = np.frombuffer(row["offsets"], np.int32).astype(np.int64)
    return Block(row["n"], offsets=offsets, vals=vals, feats=np.frombuffer(row["feats"], np.int64), back=np.frombuffer(row["back"], np.int32))


def _numbers(batch: pa.RecordBatch) -> np.ndarray:
    """A 64-bit number of each row's rid."""
    rid = batch.column("rid")
    if pa.types.is_integer(rid.type):
        return rid.fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)
    import xxhash

    return np.array([xxhash.xxh3_64_intdigest(str(x)) for x in rid.to_pylist()], np.uint64).view(np.int64)


def fit(
    df: DataFrame,
    spec: Spec,
    loss: str | Loss = "logistic",
    rounds: int = 20,
    lam: float = 1.0,
    eta: float = 0.3,
    classes: int = 1,
    engine: str = "jobs",
    share: bool = True,
    partitions: int | None = None,
    lookahead: int = 16,
    checkpoint_every: int = 10,
    base_score: float = 0.0,
    subsample: float = 1.0,
    on_round: Callable[[int, float], None] | None = None,
    state: str = "blocks",
) -> SSBModel:
    """Fits a model on df (rid, y and the features of spec).

    state says where the jobs engine keeps scores between rounds: `blocks` in a table (bid, score) beside
    blocks of packed rows that stay as they are, `carry` in a column of the persisted rows, `side` in a table (rid, score) joined by rid to rows that stay as they are, `driver` in the driver's
    memory (at most DRIVER_ROWS rows). The barrier engine keeps them in its tasks. checkpoint_every=0 never
    cuts lineage. rid must be unique for side and driver.

    Rows with a null label are left out of training. history has for each round the wall seconds, the bytes
    its global steps sent, the objective of its quadratic model, the solver path and the mean loss before it.
    """
    loss = Loss(loss) if isinstance(loss, str) else loss
    classes = classes if loss.name == "softmax" else 1
    model = SSBModel(spec, loss, eta, classes, base_score, share=share)
    df = df.filter(F.col("y").isNotNull())
    engines = {"jobs": _fit_jobs, "barrier": _fit_barrier, "local": _fit_local}
    if engine not in engines:
        raise ValueError(f"unknown engine {engine!r}; one of {sorted(engines)}")
    if engine == "jobs":
        _fit_jobs(model, df, rounds, lam, partitions, lookahead, checkpoint_every, subsample, on_round, state)
    else:
        engines[engine](model, df, rounds, lam, partitions, subsample, on_round)
    return model


def _keep_rows(rid: np.ndarray, round_: int, seed: int, share: float) -> np.ndarray:
    """A draw for each row and round from the row's own number, whatever batch it is in."""
    x = rid.view(np.uint64) + np.uint64((round_ * 0x9E3779B97F4A7C15 + seed * 0xC2B2AE3D27D4EB4F) % (1 << 64))
    for by, times in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(by))) * np.uint64(times)
    return ((x ^ (x >> np.uint64(31))) >> np.uint64(11)).astype(np.float64) * 2.0**-53 < share


def _block_step(
    model: SSBModel, block: Block, y: np.ndarray, score: np.ndarray, r: Round | None, next_: tuple | None, subsample: float,
    rid: np.ndarray | None = None, work: Work | None = None,
):
    """Adds round r to the scores and makes the Gram sums of the next round."""
    spec, total, lost = model.spec, None, 0.0
    if r is not None:
        score = score + model.eta * round_values(block, spec, r, model.share, work)
    if next_ is not None:
        round_, mu, sd = next_
        g, h = model.loss.grad_hess(score, y)
        lost = float(model.loss.value(score, y).sum())
        if subsample < 1:
            some = _keep_rows(rid, round_, spec.seed, subsample) / subsample
            g, h = g * some[:, None], h * some[:, None]
        total = _grams(_memberships(block, spec, round_, mu, sd, model.classes, model.share, work), g, h)
    return score, total, lost


def _columns(spec: Spec) -> list[str]:
    return ["rid", "y", "x"] if spec.kind == "dense" else ["rid", "y", "codes", "vals"]


class _State:
    """Rows with their scores between rounds, by strategy."""

    def __init__(self, base: DataFrame, start: list[float], strategy: str, partitions: int | None, checkpoint_every: int):
        if strategy not in ("carry", "side", "driver"):
            raise ValueError(f"unknown state strategy {strategy!r}")
        self.strategy, self.every, self.base = strategy, checkpoint_every, base
        self.parts = partitions or base.rdd.getNumPartitions()
        first = F.array(*[F.lit(float(x)) for x in start])
        if strategy == "carry":
            self.rows = base.withColumn("score", first).persist(StorageLevel.MEMORY_AND_DISK)
            return
        if strategy == "driver" and base.count() > DRIVER_ROWS:
            raise ValueError(f"more than {DRIVER_ROWS} rows: their scores are not kept on the driver")
        self.base = base.repartition(self.parts, "rid").persist(StorageLevel.MEMORY_AND_DISK)
        self.side = self.base.select("rid", first.alias("score"))
        self.rows = self._joined()

    def _joined(self) -> DataFrame:
        return self.base.join(self.side, "rid").select(*self.base.columns, "score")

    def advance(self, t: int, update: Callable) -> Callable[[], None]:
        """Rows after an update of their scores; what it returns frees the old ones once the new are made."""
        cut = self.every and t % self.every == 0 and self.base.sparkSession.sparkContext.getCheckpointDir()
        schema = self.rows.schema
        new = self.rows.mapInArrow(update, schema)
        if self.strategy == "carry":
            old = self.rows
            self.rows = (new.checkpoint(eager=True) if cut else new).persist(StorageLevel.MEMORY_AND_DISK)
            return old.unpersist
        old = self.side
        if self.strategy == "driver":
            self.side = self.base.sparkSession.createDataFrame(new.select("rid", "score").toArrow(), new.select("rid", "score").schema)
        else:
            moved = new.select("rid", "score").repartition(self.parts, "rid")
            self.side = (moved.checkpoint(eager=True) if cut else moved).persist(StorageLevel.MEMORY_AND_DISK)
        self.rows = self._joined()
        return old.unpersist

    def close(self) -> None:
        self.rows.unpersist()
        self.base.unpersist()


def _ahead(rows: DataFrame, spec: Spec, span: list[int], classes: int, share: bool, lookahead: int) -> tuple[dict[int, np.ndarray], int]:
    """Statistics of rounds to come and the bytes they took."""
    if spec.kind == "dense" and not spec.layers and spec.m <= MOMENT_FEATURES and lookahead > 1:
        stats, sent = moment_stats(rows, spec, span, classes, share)
    else:
        stats, sent = cell_stats_block(rows, spec, span[:lookahead], classes, share)
    return dict(zip(span, stats)), sent


def _fit_jobs(model, df, rounds, lam, partitions, lookahead, checkpoint_every, subsample, on_round, strategy) -> None:
    if strategy == "blocks":
        _fit_blocks(model, df, rounds, lam, partitions, lookahead, checkpoint_every, subsample, on_round)
    else:
        _fit_rows(model, df, rounds, lam, partitions, lookahead, checkpoint_every, subsample, on_round, strategy)


def _fit_blocks(model, df, rounds, lam, partitions, lookahead, checkpoint_every, subsample, on_round) -> None:
    """A round is one pass over the packed blocks: it adds the scores of the round before and makes the sums of this one.

    What a round keeps are rows (bid, score, v): a block's scores, or a partition's sums. Blocks and scores
    are dealt alike by bid, so neither the features nor the joined rows move.
    """
    spec, classes, share = model.spec, model.classes, model.share
    numbers = classes * (spec.cells * (spec.cells + 1) // 2 + spec.cells) + 2
    rows = df.select(*_columns(spec))
    parts = partitions or max(rows.rdd.getNumPartitions(), df.sparkSession.sparkContext.defaultParallelism)
    blocks = pack(rows, spec, parts).persist(StorageLevel.MEMORY_AND_DISK)
    schema = "bid long, score binary, v binary"
    ahead: dict[int, np.ndarray] = {}
    r: Round | None = None
    kept: DataFrame | None = None
    for t in range(rounds):
        began = time.perf_counter()
        sent = 0
        if t not in ahead:
            ahead, sent = _ahead(blocks, spec, list(range(t, rounds)), classes, share, lookahead)
        mu, sd = moments(ahead.pop(t), spec.norm)

        def step(batches: Iterator[pa.RecordBatch], t=t, mu=mu, sd=sd, r=r) -> Iterator[pa.RecordBatch]:
            total, lost, n, work = np.zeros((classes, spec.cells * (spec.cells + 1) // 2 + spec.cells)), 0.0, 0, Work(spec)
            for batch in batches:
                for row in batch.to_pylist():
                    y, rid = np.frombuffer(row["y"]), np.frombuffer(row["rid"], np.int64)
                    score = np.frombuffer(row["score"]).reshape(-1, classes) if r is not None else np.full((row["n"], classes), model.base_score)
                    score, part, loss_ = _block_step(model, _unpacked(row, spec), y, score, r, (t, mu, sd), subsample, rid, work)
                    total, lost, n = total + part, lost + loss_, n + len(y)
                    yield _kept(row["bid"], score, None)
            yield _kept(-1 - TaskContext.get().partitionId(), None, np.concatenate([total.ravel(), [lost, n]]))

        if kept is None:
            source = blocks
        else:
            scores = kept.filter(F.col("score").isNotNull()).select(F.col("bid").alias("b"), "score")
            source = blocks.join(scores.hint("shuffle_hash"), F.col("bid") == F.col("b")).drop("b")
        new = source.mapInArrow(step, schema).repartition(parts, "bid")
        if checkpoint_every and t % checkpoint_every == checkpoint_every - 1 and df.sparkSession.sparkContext.getCheckpointDir():
            new = new.checkpoint(eager=True)
        new = new.persist(StorageLevel.MEMORY_AND_DISK)
        total, more = _vector_sum(new.filter(F.col("v").isNotNull()).select(F.col("bid").alias("pid"), "v"), numbers, parts)
        if kept is not None:
            kept.unpersist()
        kept = new
        sent += more
        r, objective = _solve_round(t, total[:-2].reshape(classes, -1), mu, sd, spec.cells, lam)
        model.rounds.append(r)
        _log(model, t, began, sent, objective, total[-2] / max(total[-1], 1), on_round)
    if kept is not None:
        kept.unpersist()
    blocks.unpersist()


def _kept(bid: int, score: np.ndarray | None, v: np.ndarray | None) -> pa.RecordBatch:
    held = [pa.array([None if x is None else np.ascontiguousarray(x, np.float64).tobytes()], pa.binary()) for x in (score, v)]
    return pa.RecordBatch.from_arrays([pa.array([bid], pa.int64()), *held], names=["bid", "score", "v"])


def _fit_rows(model, df, rounds, lam, partitions, lookahead, checkpoint_every, subsample, on_round, strategy) -> None:
    """The same rounds with scores by row, in two passes each; kept to compare places for the scores."""
    spec, classes, share = model.spec, model.classes, model.share
    numbers = classes * (spec.cells * (spec.cells + 1) // 2 + spec.cells) + 2
    base = df.select(*_columns(spec))
    base = pin(base, partitions) if partitions else base
    state = _State(base, [model.base_score] * classes, strategy, partitions, checkpoint_every)
    fields = state.rows.columns
    ahead: dict[int, np.ndarray] = {}
    r: Round | None = None
    for t in range(rounds):
        began = time.perf_counter()
        sent = 0
        if t not in ahead:
            ahead, sent = _ahead(state.rows, spec, list(range(t, rounds)), classes, share, lookahead)
        mu, sd = moments(ahead.pop(t), spec.norm)

        def update(batches: Iterator[pa.RecordBatch], r=r) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                block = Block.of(batch, spec)
                score, _, _ = _block_step(model, block, None, _scores(batch, classes), r, None, 1.0)
                cols = [batch.column(c) for c in fields[:-1]] + [_list_array(score)]
                yield pa.RecordBatch.from_arrays(cols, names=fields)

        def sums(batches: Iterator[pa.RecordBatch], t=t, mu=mu, sd=sd) -> Iterator[pa.RecordBatch]:
            total, lost, n = np.zeros((classes, spec.cells * (spec.cells + 1) // 2 + spec.cells)), 0.0, 0
            for batch in batches:
                block, y = Block.of(batch, spec), _labels(batch)
                _, part, loss_ = _block_step(model, block, y, _scores(batch, classes), None, (t, mu, sd), subsample, _numbers(batch))
                total, lost, n = total + part, lost + loss_, n + len(y)
            yield _emit(np.concatenate([total.ravel(), [lost, n]]))

        free = state.advance(t, update) if r is not None else None
        total, more = _vector_sum(state.rows.mapInArrow(sums, "pid long, v binary"), numbers)
        if free is not None:
            free()
        sent += more
        r, objective = _solve_round(t, total[:-2].reshape(classes, -1), mu, sd, spec.cells, lam)
        model.rounds.append(r)
        _log(model, t, began, sent, objective, total[-2] / max(total[-1], 1), on_round)
    state.close()


def _log(model: SSBModel, t: int, began: float, sent: int, objective: float, lost: float, on_round) -> None:
    wall = time.perf_counter() - began
    model.history.append({"round": t, "wall_s": wall, "bytes": sent, "objective": objective, "loss": lost, "solver": model.rounds[-1].solver})
    if on_round:
        on_round(t, wall)


def _labels(batch: pa.RecordBatch) -> np.ndarray:
    return batch.column("y").to_numpy(zero_copy_only=False).astype(np.float64)


def _scores(batch: pa.RecordBatch, classes: int) -> np.ndarray:
    return batch.column("score").flatten().to_numpy(zero_copy_only=False).reshape(-1, classes)


def _list_array(score: np.ndarray) -> pa.Array:
    flat = pa.array(np.ascontiguousarray(score).ravel())
    return pa.ListArray.from_arrays(pa.array(np.arange(len(score) + 1, dtype=np.int32) * score.shape[1]), flat)


class _Task:
    """One partition held in memory: prepared blocks with even non-zeros, labels, scores and one set of work arrays."""

    def __init__(self, model: SSBModel, batches: Iterator[pa.RecordBatch]):
        self.model, self.blocks, self.y, self.rid, self.score = model, [], [], [], []
        self.work = Work(model.spec)
        for batch in batches:
            whole, y, rid = Block.of(batch, model.spec), _labels(batch), _numbers(batch)
            for a, b in whole.parts(model.spec):
                self.blocks.append(whole.prepared(a, b))
                self.y.append(y[a:b])
                self.rid.append(rid[a:b])
                self.score.append(np.full((b - a, model.classes), model.base_score))

    def stats(self, t: int) -> np.ndarray:
        spec, m = self.model.spec, self.model
        width = 2 * spec.cells * (1 if m.share else m.classes) + 1
        return sum((_raw_stats(b, spec, t, m.classes, m.share, self.work) for b in self.blocks), np.zeros(width))

    def sums(self, t: int, mu: np.ndarray, sd: np.ndarray, subsample: float) -> np.ndarray:
        k, m = self.model.spec.cells, self.model
        total, lost, n = np.zeros((m.classes, k * (k + 1) // 2 + k)), 0.0, 0
        for b, y, s, rid in zip(self.blocks, self.y, self.score, self.rid):
            _, part, loss_ = _block_step(m, b, y, s, None, (t, mu, sd), subsample, rid, self.work)
            total, lost, n = total + part, lost + loss_, n + len(y)
        return np.concatenate([total.ravel(), [lost, n]])

    def add(self, r: Round) -> None:
        for i, b in enumerate(self.blocks):
            self.score[i] = self.score[i] + self.model.eta * round_values(b, self.model.spec, r, self.model.share, self.work)


def _rounds_together(task: _Task, rounds: int, lam: float, subsample: float, reduce_: Callable[[np.ndarray], tuple[np.ndarray, int]], on_round) -> None:
    """The same loop in every task; reduce_ gives all tasks the same sum in the same order."""
    model = task.model
    for t in range(rounds):
        began = time.perf_counter()
        stats, sent = reduce_(task.stats(t))
        mu, sd = moments(stats, model.spec.norm)
        total, more = reduce_(task.sums(t, mu, sd, subsample))
        r, objective = _solve_round(t, total[:-2].reshape(model.classes, -1), mu, sd, model.spec.cells, lam)
        model.rounds.append(r)
        task.add(r)
        _log(model, t, began, sent + more, objective, total[-2] / max(total[-1], 1), on_round)


def _fit_barrier(model, df, rounds, lam, partitions, subsample, on_round) -> None:
    """One barrier stage; partitions must fit the slots that run at once. The loop restarts as a whole on failure."""
    slots = df.sparkSession.sparkContext.defaultParallelism
    parts = partitions or slots
    if parts > slots:
        raise ValueError(f"the barrier engine needs {parts} slots at once and {slots} are there; use engine='jobs'")
    pinned = df.select(*_columns(model.spec)).repartition(parts, "rid")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        context = BarrierTaskContext.get()
        own = SSBModel(model.spec, model.loss, model.eta, model.classes, model.base_score, share=model.share)
        task = _Task(own, batches)

        def reduce_(v: np.ndarray) -> tuple[np.ndarray, int]:
            said = context.allGather(base64.b64encode(v.astype(np.float64).tobytes()).decode())
            return np.sum([np.frombuffer(base64.b64decode(x)) for x in said], axis=0), 8 * len(v) * len(said)

        _rounds_together(task, rounds, lam, subsample, reduce_, None)
        if context.partitionId() == 0:
            for r, log in zip(own.rounds, own.history):
                cols = [
                    pa.array([r.round], pa.int32()), pa.array([r.mu.tolist()]), pa.array([r.sd.tolist()]), pa.array([r.w.ravel().tolist()]),
                    pa.array([r.solver]), pa.array([r.dead_cells], pa.int32()), pa.array([log["wall_s"]]), pa.array([log["bytes"]], pa.int64()),
                    pa.array([log["objective"]]), pa.array([log["loss"]]),
                ]
                yield pa.RecordBatch.from_arrays(cols, names=["round", "mu", "sd", "w", "solver", "dead_cells", "wall_s", "bytes", "objective", "loss"])

    schema = (
        "round int, mu array<double>, sd array<double>, w array<double>, solver string, dead_cells int, wall_s double, "
        "bytes long, objective double, loss double"
    )
    for row in sorted(pinned.mapInArrow(run, schema, barrier=True).collect(), key=lambda x: x["round"]):
        w = np.array(row["w"]).reshape(model.classes, -1)
        model.rounds.append(Round(row["round"], np.array(row["mu"]), np.array(row["sd"]), w, row["solver"], row["dead_cells"]))
        model.history.append({k: row[k] for k in ("round", "wall_s", "bytes", "objective", "loss", "solver")})
        if on_round:
            on_round(row["round"], row["wall_s"])


def _fit_local(model, df, rounds, lam, partitions, subsample, on_round) -> None:
    """The stand-alone trainer for data that fit the driver; the same blocks, no exchange."""
    task = _Task(model, df.select(*_columns(model.spec)).toArrow().to_batches())
    _rounds_together(task, rounds, lam, subsample, lambda v: (v, 0), on_round)


def fit_federated(
    df: DataFrame, client_col: str, spec: Spec, loss: str = "logistic", rounds: int = 5, lam: float = 1.0, eta: float = 0.3, classes: int = 1
) -> tuple[SSBModel, list[dict]]:
    """Rounds in which each client sends only its sums; the model and a log of messages (round, step, client, bytes).

    Mathematically the central fit: the server adds the clients' sums. No protection of the sums is claimed.
    """
    loss_ = Loss(loss)
    classes = classes if loss == "softmax" else 1
    model = SSBModel(spec, loss_, eta, classes)
    rows = df.filter(F.col("y").isNotNull()).select(F.col(client_col).cast("string").alias("client"), *_columns(spec)).persist()
    messages: list[dict] = []

    def by_client(step: str, t: int, make: Callable[[Block, np.ndarray], np.ndarray]) -> np.ndarray:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[str | None, np.ndarray] = {}
            for batch in batches:
                client = np.array(batch.column("client").to_pylist(), object)
                for c in {*client.tolist()}:
                    own = batch.filter(pa.array(client == c))
                    v = make(Block.of(own, spec), _labels(own))
                    sums[c] = sums[c] + v if c in sums else v
            if sums:
                yield pa.RecordBatch.from_arrays([pa.array(list(sums)), pa.array([v.tobytes() for v in sums.values()], pa.binary())], names=["client", "v"])

        got: dict[str, np.ndarray] = {}
        for r in rows.mapInArrow(run, "client string, v binary").collect():
            v = np.frombuffer(r["v"])
            got[r["client"]] = got[r["client"]] + v if r["client"] in got else v
        for c in sorted(got, key=str):
            messages.append({"round": t, "step": step, "client": c, "bytes": got[c].nbytes})
        return np.sum([got[c] for c in sorted(got, key=str)], axis=0)

    for t in range(rounds):
        began = time.perf_counter()
        mu, sd = moments(by_client("statistics", t, lambda b, y, t=t: _raw_stats(b, spec, t, classes, True)), spec.norm)

        def sums(block: Block, y: np.ndarray, t=t, mu=mu, sd=sd) -> np.ndarray:
            (_, score), = model.scores(block)
            _, total, lost = _block_step(model, block, y, score, None, (t, mu, sd), 1.0)
            return np.concatenate([total.ravel(), [lost, len(y)]])

        total = by_client("sums", t, sums)
        r, objective = _solve_round(t, total[:-2].reshape(classes, -1), mu, sd, spec.cells, lam)
        model.rounds.append(r)
        _log(model, t, began, sum(x["bytes"] for x in messages if x["round"] == t), objective, total[-2] / total[-1], None)
    rows.unpersist()
    return model, messages


def fit_squared_block(df: DataFrame, spec: Spec, rounds: int, lam: float = 1.0, eta: float = 0.3) -> SSBModel:
    """Squared loss only: curvature is one, so the cross-Grams of all rounds in one scan give every round's scores.

    b of round t is -P_t'y + eta * sum over earlier s of P_t'P_s w_s; (rounds x cells)^2 numbers are sent.
    """
    stats, _ = cell_stats_block(df.filter(F.col("y").isNotNull()), spec, list(range(rounds)))
    ms = [moments(s, spec.norm) for s in stats]
    wide = rounds * spec.cells

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(wide * wide + wide)
        for batch in batches:
            block, y = Block.of(batch, spec), _labels(batch)
            p = np.hstack([assign(forward(block, spec, t), *ms[t], spec) for t in range(rounds)])
            total += np.concatenate([(p.T @ p).ravel(), p.T @ y])
        yield _emit(total)

    total, _ = _vector_sum(df.filter(F.col("y").isNotNull()).select(*_columns(spec)).mapInArrow(run, "pid long, v binary"), wide * wide + wide)
    cross, py = total[: wide * wide].reshape(wide, wide), total[wide * wide :]
    model = SSBModel(spec, Loss("squared"), eta, 1)
    done = np.zeros(wide)
    for t in range(rounds):
        own = slice(t * spec.cells, (t + 1) * spec.cells)
        b = cross[own] @ done - py[own]
        w, path = solve_scores(cross[own, own], b, lam)
        done[own] = eta * w
        model.rounds.append(Round(t, *ms[t], w[None], path, int((ms[t][1] == 0).sum())))
    return model
