"""LM scoring: a hashed maximum-entropy model with n-gram and skip features and a class-factored softmax.

A token's class (5 bits of its hash) is predicted from the previous token, the previous two and the one
before the previous (a skip), its group inside the class (5 more bits) from the previous token, and the
token inside its group from corpus counts with one added:

    p(token | context) = p(class | context) * p(group | class, previous) * (c + 1) / (N_group + V_group + 1)

where the last factor leaves 1 / (N_group + V_group + 1) for tokens of the group never seen, so the
probabilities of a group sum to one over its known tokens and one unknown. Weights are trained by
gradient steps in blocks of texts and averaged, row by row, by how often each row was used.

Counts are made by one shuffle of tokens that are counted before it. Frequent tokens, of which there are
fewer than a fixed number, are broadcast with their counts; the others meet their counts by a join, in
which no token has more rows than an equal share of all tokens.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, functions as F

from ._store import Workspace
from ._text import raw, slices, words
from .langid import crc_fold
from .near_dedup import _runs

CLASS_BITS = GROUP_BITS = 5
C, G = 1 << CLASS_BITS, 1 << GROUP_BITS
FEATURE_BITS, GROUP_FEATURE_BITS = 14, 9
N_FEATURES = 1 << FEATURE_BITS
#: Rows of the one weight table: class bias, three kinds of class features, then (feature, class) rows of groups.
ROWS = 1 + 3 * N_FEATURES + (C << GROUP_FEATURE_BITS)
END, BEGIN = np.uint64(0x5851F42D4C957F2D), np.uint64(0x14057B7EF767814F)
_MULTIPLIERS = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD)]
STEP = 1 << 14  # tokens of a gradient step
#: Frequent tokens are those that make up at least this share of all; so there are at most as many.
FREQUENT = 1 << 19


def tokens_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Token hashes of all rows, each row's words and one end, their two predecessors, row offsets and row of each."""
    buf, offsets = raw(column)
    _, _, hashes, at = words(buf, offsets)
    sizes = np.diff(at) + 1
    first = np.concatenate([[0], np.cumsum(sizes)])
    n = len(sizes)
    padded = np.full(int(first[-1]) + 2 * n, BEGIN, np.uint64)
    owner = np.repeat(np.arange(n), sizes)
    place = np.arange(int(first[-1])) + 2 * (owner + 1)
    ends = first[1:] - 1
    is_word = np.ones(int(first[-1]), bool)
    is_word[ends] = False
    padded[place[is_word]] = hashes
    padded[place[ends]] = END
    return padded[place], padded[place - 1], padded[place - 2], first, owner


def features(one: np.ndarray, two: np.ndarray, cls: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """Table rows of the class features and of the group feature."""
    m, down = _MULTIPLIERS, np.uint64(64 - FEATURE_BITS)
    kinds = (one * m[0], (one * m[1]) ^ (two * m[2]), two * m[3])
    kinds = [1 + k * N_FEATURES + ((x ^ (x >> np.uint64(29))) * m[4] >> down).astype(np.int64) for k, x in enumerate(kinds)]
    group = (one * m[4] >> np.uint64(64 - GROUP_FEATURE_BITS)).astype(np.int64)
    return kinds, 1 + 3 * N_FEATURES + group * C + cls


def _softmax(z: np.ndarray) -> np.ndarray:
    z -= z.max(1, keepdims=True)
    np.exp(z, out=z)
    z /= z.sum(1, keepdims=True)
    return z


def _move(table: np.ndarray, used: np.ndarray, rows: np.ndarray, base: int, grad: np.ndarray, rate: float, most: float) -> None:
    """A step of each row against the mean of its gradients, its length falling with the row's uses.

    The rows lie in the 2**16 rows from base on, so they are sorted as 16-bit numbers, by radix.
    """
    order = np.argsort((rows - base).astype(np.uint16), kind="stable")
    own = rows[order]
    at = np.concatenate([[0], np.flatnonzero(own[1:] != own[:-1]) + 1])
    n = np.diff(np.append(at, len(own))).astype(np.float32)
    own = own[at]
    had = used[own]
    size = np.minimum(2 * rate * (np.sqrt(had + n) - np.sqrt(had)), most) / n
    table[own] -= np.add.reduceat(grad[order], at, axis=0) * size[:, None]
    used[own] = had + n


def descend(table: np.ndarray, used: np.ndarray, column: pa.Array, rate: float, most: float) -> None:
    """Gradient steps over all tokens of a column of texts."""
    tok, one, two, _, _ = tokens_of(column)
    for at in range(0, len(tok), STEP):
        h = tok[at : at + STEP]
        n = np.arange(len(h))
        cls = (h >> np.uint64(64 - CLASS_BITS)).astype(np.int64)
        group = (h >> np.uint64(64 - CLASS_BITS - GROUP_BITS)).astype(np.int64) & (G - 1)
        kinds, inner = features(one[at : at + STEP], two[at : at + STEP], cls)
        p = _softmax(table[0] + table[kinds[0]] + table[kinds[1]] + table[kinds[2]])
        p[n, cls] -= 1
        for k, rows in enumerate(kinds):
            _move(table, used, rows, 1 + k * N_FEATURES, p, rate, most)
        table[0] -= p.mean(0) * most
        used[0] += len(h)
        q = _softmax(table[inner])
        q[n, group] -= 1
        _move(table, used, inner, 1 + 3 * N_FEATURES, q, rate, 2 * most)


def context_score(table: np.ndarray, tok: np.ndarray, one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """log10 of p(class) p(group) of each token."""
    out = np.empty(len(tok))
    for at in range(0, len(tok), STEP):
        h = tok[at : at + STEP]
        n = np.arange(len(h))
        cls = (h >> np.uint64(64 - CLASS_BITS)).astype(np.int64)
        group = (h >> np.uint64(64 - CLASS_BITS - GROUP_BITS)).astype(np.int64) & (G - 1)
        kinds, inner = features(one[at : at + STEP], two[at : at + STEP], cls)
        p = _softmax(table[0] + table[kinds[0]] + table[kinds[1]] + table[kinds[2]])[n, cls]
        out[at : at + STEP] = np.log10(p.astype(np.float64)) + np.log10(_softmax(table[inner])[n, group].astype(np.float64))
    return out


def train(learn: DataFrame, rounds: int = 2, rate: float = 0.4, most: float = 2.0, pieces: int = 64, block_bytes: int = 24 << 20) -> np.ndarray:
    """The weight table (ROWS x C) after `rounds` rounds, each over its own fold of the rows (doc_id, text).

    A row's block is drawn by hash of id and text, and there is a block for each `block_bytes` of a round's
    texts, so neither cores nor partitions change the result. A block starts from the last round's weights
    and goes through its texts in order of id. It sends its table in pieces, rows weighted by use; sums are
    made by piece and only the finished table, of a size set by the constants, reaches the driver.
    """
    spark = learn.sparkSession
    size = -(-ROWS // pieces)
    table = np.zeros((ROWS, C), np.float32)
    place = F.xxhash64("doc_id", "text")
    weight = learn.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, round(weight / rounds / block_bytes))
    dealt = learn.select("doc_id", "text", F.pmod(place, F.lit(rounds)).alias("fold"), F.pmod(F.shiftright(place, 8), F.lit(blocks)).alias("block"))

    for k in range(rounds):
        shared = spark.sparkContext.broadcast(table)

        def learn_blocks(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            def texts_of(batch_runs: Iterator[tuple[int, pa.RecordBatch]]) -> Iterator[tuple[int, pa.Array | None]]:
                """Texts of each block in slices that depend on the block's rows alone, and None after a block."""
                now, held, weight = None, [], 0
                for block, run in batch_runs:
                    if now is not None and block != now:
                        yield from ((now, x.column("text")) for x in slices(_joined(held), "text"))
                        yield now, None
                        held, weight = [], 0
                    now = block
                    held.append(run)
                    weight += run.nbytes
                    if weight > 8 << 20:
                        parts = list(slices(_joined(held), "text"))
                        yield from ((now, x.column("text")) for x in parts[:-1])
                        held, weight = [parts[-1]], 0
                if now is not None:
                    yield from ((now, x.column("text")) for x in slices(_joined(held), "text"))
                    yield now, None

            def runs() -> Iterator[tuple[int, pa.RecordBatch]]:
                for batch in batches:
                    if batch.num_rows:
                        block = batch.column("block").to_numpy()
                        at = _runs(block)
                        for a, b in zip(at[:-1], at[1:]):
                            yield int(block[a]), batch.slice(a, b - a)

            own, used = shared.value.copy(), np.zeros(ROWS, np.float32)
            for _, texts in texts_of(runs()):
                if texts is not None:
                    descend(own, used, texts, rate, most)
                    continue
                for b in range(pieces):
                    part = slice(b * size, (b + 1) * size)
                    sent = (own[part] - shared.value[part]) * used[part, None]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([b], pa.int32()), pa.array([used[part].tobytes()], pa.binary()), pa.array([sent.tobytes()], pa.binary())],
                        names=["piece", "used", "sent"],
                    )
                own, used = shared.value.copy(), np.zeros(ROWS, np.float32)

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[int, list[np.ndarray]] = {}
            for batch in batches:
                for b, used, sent in zip(*(batch.column(c).to_pylist() for c in ("piece", "used", "sent"))):
                    u, s = np.frombuffer(used, np.float32), np.frombuffer(sent, np.float32)
                    if b in sums:
                        sums[b][0] += u
                        sums[b][1] += s
                    else:
                        sums[b] = [u.astype(np.float64), s.astype(np.float64)]
            for b, (u, s) in sums.items():
                mean = (s.reshape(-1, C) / np.maximum(u, 1)[:, None]).astype(np.float32)
                yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([mean.tobytes()], pa.binary())], names=["piece", "sent"])

        fold = dealt.filter(F.col("fold") == k).select("doc_id", "text", "block").repartition(blocks, "block")
        sent = fold.sortWithinPartitions("block", "doc_id", "text").mapInArrow(learn_blocks, "piece int, used binary, sent binary")
        table = table.copy()
        for r in sent.repartition(pieces, "piece").mapInArrow(add, "piece int, sent binary").collect():
            rows = slice(r["piece"] * size, (r["piece"] + 1) * size)
            table[rows] += np.frombuffer(r["sent"], np.float32).reshape(-1, C)
        shared.unpersist()
    return table


def _joined(batches: list[pa.RecordBatch]) -> pa.RecordBatch:
    return batches[0] if len(batches) == 1 else pa.Table.from_batches(batches).combine_chunks().to_batches()[0]


def count_tokens(docs: DataFrame) -> DataFrame:
    """(token, c, n): how often each token stands in the rows (held_out, text) not held out, and in all rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        size = 0

        def merged() -> tuple[np.ndarray, ...]:
            token, c, n = (np.concatenate(x) for x in zip(*held))
            token, back = np.unique(token, return_inverse=True)
            return token, *(np.bincount(back, x, len(token)).astype(np.int64) for x in (c, n))

        def sent(token: np.ndarray, c: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(token.view(np.int64)), pa.array(c), pa.array(n)], names=["token", "c", "n"])

        for whole in batches:
            for batch in slices(whole, "text"):
                tok, _, _, first, _ = tokens_of(batch.column("text"))
                taught = ~np.array(batch.column("held_out").to_pylist(), bool)
                token, back, n = np.unique(tok, return_inverse=True, return_counts=True)
                held.append((token, np.bincount(back, np.repeat(taught, np.diff(first)), len(token)).astype(np.int64), n))
                size += len(token)
                if size > 1 << 21:
                    held = [merged()]
                    size = len(held[0][0])
                    if size > 1 << 20:
                        yield sent(*held[0])
                        held, size = [], 0
        if held:
            yield sent(*merged())

    counted = docs.select("held_out", "text").mapInArrow(run, "token long, c long, n long")
    return counted.groupBy("token").agg(F.sum("c").alias("c"), F.sum("n").alias("n"))


_SCORED = (
    "row long, doc_id long, held_out boolean, n_tokens long, known long, log_count double, context double, "
    "rare array<long>, times array<int>"
)


def score_parts(docs: DataFrame, table: np.ndarray, token: np.ndarray, c: np.ndarray, group_log: np.ndarray) -> DataFrame:
    """What each row of docs (doc_id, held_out, text) gets from the weights and the frequent tokens, and its other tokens.

    token (ascending) and c: the frequent tokens and their counts; group_log: log10(N + V + 1) of each group.
    known and log_count are sums over the frequent tokens; rare and times are the distinct others.
    """
    shared = docs.sparkSession.sparkContext.broadcast((table, token, c, group_log))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights, frequent, count, group_log = shared.value
        log_count = np.log10(count + 1.0)
        row = TaskContext.get().partitionId() << 33
        for whole in batches:
            for batch in slices(whole, "text"):
                tok, one, two, first, owner = tokens_of(batch.column("text"))
                n = batch.num_rows
                inner = context_score(weights, tok, one, two) - group_log[(tok >> np.uint64(64 - CLASS_BITS - GROUP_BITS)).astype(np.int64)]
                place = np.minimum(np.searchsorted(frequent, tok), max(len(frequent) - 1, 0))
                hit = frequent[place] == tok if len(frequent) else np.zeros(len(tok), bool)
                known = np.bincount(owner[hit], count[place[hit]] > 0, n).astype(np.int64)
                logs = np.bincount(owner[hit], log_count[place[hit]], n).astype(np.float64)
                h, doc = tok[~hit], owner[~hit]
                order = np.lexsort((h, doc))
                h, doc = h[order], doc[order]
                new = np.ones(len(h), bool)
                new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
                at = np.flatnonzero(new)
                edge = np.searchsorted(doc[at], np.arange(n + 1)).astype(np.int32)
                times = np.diff(np.append(at, len(h))).astype(np.int32)
                cols = [
                    pa.array(np.arange(row, row + n)), batch.column("doc_id"), batch.column("held_out"), pa.array(np.diff(first)), pa.array(known),
                    pa.array(logs), pa.array(np.add.reduceat(inner, first[:-1])),
                    pa.ListArray.from_arrays(pa.array(edge), pa.array(h[at].view(np.int64))), pa.ListArray.from_arrays(pa.array(edge), pa.array(times)),
                ]
                row += n
                yield pa.RecordBatch.from_arrays(cols, names=[x.split()[0] for x in _SCORED.split(", ")])

    return docs.mapInArrow(run, _SCORED)


def score_texts(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", folds: int = 7, held_fold: int = 2, rounds: int = 2, frequent: int = FREQUENT
) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score of each row.

    Tokens are the words of a text (A-Z folded) and one end. Counts and weights come from the rows whose
    crc32(id) modulo `folds` is not `held_fold`; a null id falls into fold 0. Null texts are empty: one
    token. Repeated rows count as often as they stand; an empty table gives no rows; other columns are
    not read. Tokens are told apart by 64-bit hashes. A text is scored in one task, with work arrays of
    about 40 bytes for each of its bytes. Counts, n_known and weights do not depend on partitions.
    """
    ws = Workspace(docs.sparkSession, "maxent")
    held = (crc_fold(F.col("doc_id"), folds) == held_fold).alias("held_out")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).select("doc_id", held, "text")
    counts = ws.save(count_tokens(rows), "counts")
    group = F.shiftrightunsigned("token", 64 - CLASS_BITS - GROUP_BITS)
    by_group = counts.groupBy(group.alias("g")).agg(F.sum("c").alias("c"), F.sum((F.col("c") > 0).cast("long")).alias("v"), F.sum("n").alias("n")).collect()
    group_log = np.zeros(C * G)
    for r in by_group:
        group_log[r["g"]] = np.log10(r["c"] + r["v"] + 1.0)
    total, kinds, all_tokens = (sum(r[k] for r in by_group) for k in ("c", "v", "n"))
    least = max(1, -(-all_tokens // frequent))
    often = counts.filter(F.col("n") >= least).select("token", "c").toArrow()
    token, c = often.column("token").to_numpy().view(np.uint64), often.column("c").to_numpy()
    order = np.argsort(token)
    table = train(rows.filter(~F.col("held_out")).select("doc_id", "text"), rounds)
    scored = ws.save(score_parts(rows, table, token[order], c[order], group_log), "scored")
    rare = scored.select("row", F.explode(F.arrays_zip("rare", "times")).alias("x")).select("row", F.col("x.rare").alias("token"), "x.times")
    counted = counts.filter((F.col("n") < least) & (F.col("c") > 0)).select("token", "c")
    sums = rare.join(counted, "token").groupBy("row").agg(
        F.sum("times").alias("more_known"), F.sum(F.col("times") * F.log10(F.col("c") + 1.0)).alias("more_log")
    )
    log_count = F.col("log_count") + F.coalesce("more_log", F.lit(0.0))
    return scored.join(sums, "row", "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("known") + F.coalesce("more_known", F.lit(0))).alias("n_known"), F.lit(total).cast("long").alias("train_tokens"),
        (log_count - F.col("n_tokens") * float(np.log10(total + kinds + 1.0))).alias("base_score"), (F.col("context") + log_count).alias("score"),
    )
