"""Second-order boosted trees: depth-bounded (level-wise) and leaf-bounded (best leaf first).

A row carries its features as array<double> x (dense) or map<string,double> (sparse, absent is 0), its
scores and its node. A level is one aggregate: features are spread, sums of g and h are made for each
(node, feature, value), running sums over values give every split's gain, and one best split a node goes
back to the driver. What is shuffled grows with nodes, features and values; that is what soft splits avoid.

Dense tables of up to COLUMN_ROWS rows are searched by columns instead. Up to TASK_NUMBERS numbers, one task sorts the
columns once, keeps each open node's rows in every column's order and grows all rounds. Above, blocks of columns are dealt
to tasks, sorted and cached once; a level is one job without a shuffle, which gets each row's node and gives each node's
best split with a bit a row, and a leaf-wise tree asks for all its open leaves at once. All search every value; the two
by columns add in the same order and give the same trees.
"""

from __future__ import annotations

import heapq
import pickle
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import RDD, StorageLevel, TaskContext
from pyspark.sql import Column, DataFrame, Window, functions as F, types as T

from ..functions.losses import Loss, logistic_expr, softmax_expr, squared_expr

COLUMN_ROWS = 1_000_000
TASK_NUMBERS = 1 << 23  # rows times features: 12 bytes each stay in the task, and the other methods' tasks run beside it
SEARCHED = 1 << 15  # numbers whose sums and gains are held at once
MANY_SPLITS = 64
BLOCK_COLUMNS = 4  # columns of a block that a task holds sorted: 48 bytes a row
SCORED_ROWS = 1 << 16  # rows whose derivatives by all classes are held at once


def leaf_value(g: float, h: float, lam: float) -> float:
    return -g / (h + lam)


def split_gain(gl: Column, hl: Column, g: Column, h: Column, lam: float, gamma: float = 0.0) -> Column:
    score = lambda a, b: a * a / (b + lam)
    return 0.5 * (score(gl, hl) + score(g - gl, h - hl) - score(g, h)) - gamma


@dataclass
class Tree:
    """Nodes by number; children of n are 2n+1 and 2n+2; a split sends value <= threshold to the left."""

    splits: dict[int, tuple] = field(default_factory=dict)  # node -> (feature, threshold)
    values: dict[int, float] = field(default_factory=dict)  # leaf -> value


@dataclass
class GBDTModel:
    kind: str
    eta: float
    classes: int
    trees: list[list[Tree]] = field(default_factory=list)  # round -> class -> tree
    history: list[dict] = field(default_factory=list)

    def transform(self, df: DataFrame, upto: int | None = None) -> DataFrame:
        """df with score array<double>; many splits of dense rows are replayed in numpy, since nested conditions outgrow compiled code."""
        if self.kind == "dense" and sum(len(tree.splits) for trees in self.trees[:upto] for tree in trees) > MANY_SPLITS:
            return self._replayed(df.drop("score"), upto)
        total = [F.lit(0.0)] * self.classes
        for trees in self.trees[:upto]:
            total = [t + self.eta * tree_value(tree, self.kind) for t, tree in zip(total, trees)]
        return df.withColumn("score", F.array(*total))

    def _replayed(self, df: DataFrame, upto: int | None) -> DataFrame:
        used = self.trees[:upto]
        m = 1 + max(int(f) for trees in used for tree in trees for f, _ in tree.splits.values())
        eta, classes, place = self.eta, self.classes, df.columns.index("x")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                x = _matrix(batch.column(place), m)
                score = np.zeros((batch.num_rows, classes))
                for trees in used:
                    score += eta * np.stack([_outputs(x, tree) for tree in trees], 1)
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(score.tolist(), pa.list_(pa.float64()))], names=[*batch.schema.names, "score"])

        return df.mapInArrow(run, T.StructType([*df.schema.fields, T.StructField("score", T.ArrayType(T.DoubleType()))]))


def _value_of(kind: str, feature) -> Column:
    if kind == "dense":
        return F.element_at("x", int(feature) + 1)
    return F.coalesce(F.element_at("feats", F.lit(feature)), F.lit(0.0))


def tree_value(tree: Tree, kind: str, node: int = 0) -> Column:
    if node in tree.splits:
        feature, threshold = tree.splits[node]
        return F.when(_value_of(kind, feature) <= threshold, tree_value(tree, kind, 2 * node + 1)).otherwise(tree_value(tree, kind, 2 * node + 2))
    return F.lit(float(tree.values.get(node, 0.0)))


def candidate_sums(rows: DataFrame, kind: str, node: str = "node") -> DataFrame:
    """(node, f, v, g, h): sums over the rows of each value; absent sparse values are one candidate, 0."""
    if kind == "dense":
        return rows.select(node, "g", "h", F.posexplode("x").alias("f", "v")).groupBy(node, "f", "v").agg(F.sum("g").alias("g"), F.sum("h").alias("h"))
    long = rows.select(node, "g", "h", F.explode("feats").alias("f", "v")).filter("v != 0")
    given = long.groupBy(node, "f", "v").agg(F.sum("g").alias("g"), F.sum("h").alias("h"))
    totals = rows.groupBy(node).agg(F.sum("g").alias("tg"), F.sum("h").alias("th"))
    zero = (
        given.groupBy(node, "f").agg(F.sum("g").alias("g"), F.sum("h").alias("h"))
        .join(F.broadcast(totals), node)  # one row a node
        .select(node, "f", F.lit(0.0).alias("v"), (F.col("tg") - F.col("g")).alias("g"), (F.col("th") - F.col("h")).alias("h"))
    )
    return given.unionByName(zero)


def best_splits(sums: DataFrame, lam: float, gamma: float = 0.0, least_h: float = 1e-3, node: str = "node") -> DataFrame:
    """(node, f, threshold, gain, gl, hl, g, h): each node's best split; ties by feature, then threshold.

    Thresholds lie midway between successive values.
    """
    along = Window.partitionBy(node, "f").orderBy("v")
    whole = Window.partitionBy(node, "f")
    run = along.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    walked = sums.select(
        node, "f", "v", F.lead("v").over(along).alias("next"), F.sum("g").over(run).alias("gl"), F.sum("h").over(run).alias("hl"),
        F.sum("g").over(whole).alias("g"), F.sum("h").over(whole).alias("h"),
    ).filter((F.col("next").isNotNull()) & (F.col("hl") >= least_h) & (F.col("h") - F.col("hl") >= least_h))
    gained = walked.withColumn("gain", split_gain(F.col("gl"), F.col("hl"), F.col("g"), F.col("h"), lam, gamma))
    gained = gained.withColumn("threshold", (F.col("v") + F.col("next")) / 2).filter("gain > 0")
    order = F.struct((-F.col("gain")).alias("o"), "f", "threshold", "gain", "gl", "hl", "g", "h")
    return gained.groupBy(node).agg(F.min(order).alias("b")).select(node, "b.f", "b.threshold", "b.gain", "b.gl", "b.hl", "b.g", "b.h")


def quantile_bins(df: DataFrame, m: int, bins: int = 256, accuracy: int = 10_000) -> list[list[float]]:
    """Upper edges of at most `bins` bins of each dense feature."""
    asked = [i / bins for i in range(1, bins)]
    row = df.agg(*[F.percentile_approx(F.element_at("x", k + 1), asked, accuracy).alias(f"q{k}") for k in range(m)]).first()
    return [sorted(set(row[k])) for k in range(m)]


def to_bins(x: str, edges: list[list[float]]) -> Column:
    """The first features of the dense vector with each value replaced by the upper edge of its bin."""
    def upper(k: int, own: list[float]) -> Column:
        value = F.element_at(x, k + 1)
        above = F.filter(F.array(*[F.lit(float(e)) for e in own]), lambda e: e >= value)
        return F.coalesce(F.try_element_at(above, F.lit(1)), F.lit((own[-1] if own else 0.0) + 1.0))

    return F.array(*[upper(k, own) for k, own in enumerate(edges)])


def _grad(loss: str, c: int) -> tuple[Column, Column]:
    y = F.col("y").cast("double")
    if loss == "softmax":
        g, h = softmax_expr(F.col("score"), F.col("y").cast("int"))
        return g[c], h[c]
    return {"logistic": logistic_expr, "squared": squared_expr}[loss](F.col("score")[0], y)


def _totals(rows: DataFrame) -> tuple[float, float]:
    r = rows.agg(F.sum("g"), F.sum("h")).first()
    return float(r[0] or 0), float(r[1] or 0)


def _descend(tree: Tree, kind: str, nodes: list[int]) -> Column:
    node = F.col("node")
    for n in nodes:
        feature, threshold = tree.splits[n]
        node = F.when(F.col("node") == n, F.when(_value_of(kind, feature) <= threshold, 2 * n + 1).otherwise(2 * n + 2)).otherwise(node)
    return node


def _grow_levels(rows: DataFrame, kind: str, depth: int, lam: float, gamma: float, least_h: float) -> Tree:
    tree = Tree()
    g, h = _totals(rows)
    tree.values[0] = leaf_value(g, h, lam)
    rows = rows.withColumn("node", F.lit(0))
    open_ = [0]
    for _ in range(depth):
        found = best_splits(candidate_sums(rows.filter(F.col("node").isin(open_)), kind), lam, gamma, least_h).collect()
        open_ = []
        for b in found:
            n = b["node"]
            tree.splits[n] = (b["f"], b["threshold"])
            tree.values[2 * n + 1] = leaf_value(b["gl"], b["hl"], lam)
            tree.values[2 * n + 2] = leaf_value(b["g"] - b["gl"], b["h"] - b["hl"], lam)
            open_ += [2 * n + 1, 2 * n + 2]
        if not found:
            break
        rows = rows.withColumn("node", _descend(tree, kind, [b["node"] for b in found]))
    return tree


def _grow_leaves(rows: DataFrame, kind: str, leaves: int, lam: float, gamma: float, least_h: float) -> Tree:
    """Best leaf first: a heap of leaves by gain; a split asks for the best splits of its two children."""
    tree = Tree()
    g, h = _totals(rows)
    tree.values[0] = leaf_value(g, h, lam)
    rows = rows.withColumn("node", F.lit(0).cast("long"))
    heap: list = []

    def ask(nodes: list[int]) -> None:
        for b in best_splits(candidate_sums(rows.filter(F.col("node").isin(nodes)), kind), lam, gamma, least_h).collect():
            heapq.heappush(heap, (-b["gain"], b["node"], b.asDict()))

    ask([0])
    count = 1
    while heap and count < leaves:
        _, n, b = heapq.heappop(heap)
        tree.splits[n] = (b["f"], b["threshold"])
        tree.values[2 * n + 1] = leaf_value(b["gl"], b["hl"], lam)
        tree.values[2 * n + 2] = leaf_value(b["g"] - b["gl"], b["h"] - b["hl"], lam)
        rows = rows.withColumn("node", _descend(tree, kind, [n]))
        count += 1
        if count < leaves:
            ask([2 * n + 1, 2 * n + 2])
    return tree


def _matrix(column: pa.Array, m: int) -> np.ndarray:
    """Rows of m numbers; missing ones are not a number, which no split sends to the left."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    sizes = np.asarray(column.value_lengths().fill_null(0))
    out = np.full((len(column), max(m, int(sizes.max(initial=0)))), np.nan)
    out[np.arange(out.shape[1]) < sizes[:, None]] = column.flatten().to_numpy(zero_copy_only=False)
    return out[:, :m]


def _nodes(x: np.ndarray, splits: dict[int, tuple]) -> np.ndarray:
    node = np.zeros(len(x), np.int64)
    for n in sorted(splits):  # parents come before their children
        at = np.flatnonzero(node == n)
        feature, threshold = splits[n]
        node[at] = np.where(x[at, int(feature)] <= threshold, 2 * n + 1, 2 * n + 2)
    return node


def _outputs(x: np.ndarray, tree: Tree) -> np.ndarray:
    return np.vectorize(lambda n: tree.values.get(n, 0.0), otypes=[float])(_nodes(x, tree.splits)) if len(x) else np.zeros(0)


def _best_of(o: np.ndarray, v: np.ndarray, g: np.ndarray, h: np.ndarray, lam: float, gamma: float, least_h: float) -> tuple | None:
    """(gain, threshold, gl, hl, column) of the best split of a node; rows o and values v of each column in the order of v; ties by column, then threshold."""
    best = None
    step = max(1, SEARCHED // max(1, v.shape[1]))
    for first in range(0, len(v) if v.shape[1] > 1 else 0, step):
        rows, low, high = o[first : first + step], v[first : first + step, :-1], v[first : first + step, 1:]
        gl, hl = np.cumsum(g.take(rows), 1), np.cumsum(h.take(rows), 1)
        tg, th = gl[:, -1:], hl[:, -1:]
        gl, hl = gl[:, :-1], hl[:, :-1]
        free = (low < high) & (hl >= least_h) & (th - hl >= least_h)  # never beside what is not a number, which comes last
        with np.errstate(divide="ignore", invalid="ignore"):
            gain = 0.5 * (gl * gl / (hl + lam) + (tg - gl) ** 2 / (th - hl + lam) - tg * tg / (th + lam)) - gamma
        np.copyto(gain, -np.inf, where=~free)
        at = gain.argmax(1)
        most = gain[np.arange(len(at)), at]
        c = int(np.where(most > 0, most, -np.inf).argmax())
        k = at[c]
        if most[c] > 0 and (best is None or most[c] > best[0]):
            best = *map(float, (most[c], (low[c, k] + high[c, k]) / 2, gl[c, k], hl[c, k])), first + c
    return best


def _arranged(v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each column, rows and values in the order of values."""
    order = np.empty(v.shape, np.int32)
    for o, column in zip(order, v):
        o[:] = np.argsort(column, kind="stable")  # what is not a number comes last
    return order, np.take_along_axis(v, order, 1)


def _sorted_columns(rows: DataFrame, m: int) -> tuple[RDD, np.ndarray]:
    """Cached blocks (first, order, values) of columns and the labels.

    Rows are numbered by the hash of rid in every block and in the labels; a block has the numbers of its rows by value.
    """

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId() << 32
        for number, batch in enumerate(batches, part):
            x = _matrix(batch.column("x"), m)
            firsts = [-1, *range(0, m, BLOCK_COLUMNS)]  # the labels go as a block of their own
            blocks = [np.asarray(batch.column("y"), float).tobytes(), *[np.ascontiguousarray(x[:, f : f + BLOCK_COLUMNS].T).tobytes() for f in firsts[1:]]]
            k, keys = len(firsts), np.asarray(batch.column("key")).tobytes()
            yield pa.RecordBatch.from_arrays([pa.array(firsts, pa.int32()), pa.array([number] * k, pa.int64()), pa.array([keys] * k, pa.binary()), pa.array(blocks, pa.binary())], names=["first", "number", "keys", "v"])

    def sort(block: tuple) -> tuple:
        first, parts = block
        parts = sorted(parts)
        keys = [np.frombuffer(k, np.int64) for _, k, _ in parts]
        v = np.concatenate([np.frombuffer(b).reshape(-1, len(k)) for (_, _, b), k in zip(parts, keys)], 1)[:, np.argsort(np.concatenate(keys), kind="stable")]
        if first < 0:
            return first, None, v[0]
        return first, *_arranged(v)

    dealt = rows.select(F.xxhash64("rid").alias("key"), "y", "x").mapInArrow(spread, "first int, number long, keys binary, v binary").rdd
    parts = min(1 + -(-m // BLOCK_COLUMNS), dealt.context.defaultParallelism)
    blocks = dealt.map(lambda r: (r[0], (r[1], bytes(r[2]), bytes(r[3])))).groupByKey(parts, lambda first: first // BLOCK_COLUMNS + 1).map(sort)
    blocks.persist(StorageLevel.MEMORY_AND_DISK)
    ((_, _, y),) = blocks.filter(lambda b: b[0] < 0).collect()
    return blocks, y


class _Blocks:
    """Best splits of a tree's nodes by a job that asks every block of columns."""

    def __init__(self, blocks: RDD, g: np.ndarray, h: np.ndarray, terms: tuple):
        self.blocks, self.size, self.terms = blocks, len(g), terms
        self.held = blocks.context.broadcast((g, h))

    def __call__(self, nodes: list[int], rows: dict[int, np.ndarray]) -> dict[int, tuple]:
        size, count, held, terms = self.size, len(nodes), self.held, self.terms
        place = np.full(size, -1, np.int16 if count < 1 << 15 else np.int32)
        for k, n in enumerate(nodes):
            place[rows[n]] = k
        ends = np.cumsum([size - sum(len(rows[n]) for n in nodes), *[len(rows[n]) for n in nodes]]).tolist()

        def best(blocks: Iterator[tuple]) -> Iterator[tuple]:
            g, h = held.value
            found: dict[int, tuple] = {}
            for first, order, values in blocks:
                if first < 0:
                    continue
                by_node = np.argsort(place[order], 1, kind="stable")
                o, v = np.take_along_axis(order, by_node, 1), np.take_along_axis(values, by_node, 1)
                for k, (a, b) in enumerate(zip(ends, ends[1:])):
                    got = _best_of(o[:, a:b], v[:, a:b], g, h, *terms)
                    if got and (k not in found or (got[0], -first - got[4]) > (found[k][0], -found[k][4])):
                        c = got[4]
                        found[k] = (*got[:4], first + c, o[c, a : a + int(np.searchsorted(v[c, a:b], got[1], "right"))])
            if found:
                left = np.zeros(size, bool)
                left[np.concatenate([b[5] for b in found.values()])] = True
                yield {k: b[:5] for k, b in found.items()}, np.packbits(left).tobytes()

        parts = self.blocks.mapPartitions(best).collect()
        lefts = [np.unpackbits(np.frombuffer(bits, np.uint8), count=size).astype(bool) for _, bits in parts]
        out = {}
        for k, n in enumerate(nodes):
            if tried := [(b[0], -b[4], i) for i, (found, _) in enumerate(parts) if (b := found.get(k))]:
                i = max(tried)[2]
                out[n] = (*parts[i][0][k], lefts[i][rows[n]])
        return out

    def close(self) -> None:
        self.held.destroy()


class _Columns:
    """Best splits of a tree's nodes by all columns at hand: rows and values of a node stay in each column's order."""

    def __init__(self, order: np.ndarray, values: np.ndarray, g: np.ndarray, h: np.ndarray, terms: tuple):
        self.g, self.h, self.terms = g, h, terms
        self.nodes = {0: (order, values)}

    def __call__(self, nodes: list[int], rows: dict[int, np.ndarray]) -> dict[int, tuple]:
        out, inside = {}, np.zeros(len(self.g), bool)
        for n in nodes:
            if n not in self.nodes:
                up = (n - 1) // 2
                order, values = self.nodes.pop(up)
                inside[:] = False
                inside[rows[2 * up + 1]] = True
                left = inside.take(order).ravel()
                for child, own in ((2 * up + 1, np.flatnonzero(left)), (2 * up + 2, np.flatnonzero(~left))):
                    self.nodes[child] = order.take(own).reshape(len(order), -1), values.take(own).reshape(len(order), -1)
            order, values = self.nodes[n]
            if got := _best_of(order, values, self.g, self.h, *self.terms):
                f = got[4]
                inside[:] = False
                inside[order[f, : int(np.searchsorted(values[f], got[1], "right"))]] = True
                out[n] = (*got, inside[rows[n]])
        return out

    def close(self) -> None:
        self.nodes = {}


class _Search:
    """Best splits of one tree's nodes; holds the rows of each node.

    search(nodes) -> node -> its sums g and h and, if one gains, its best split; ties by feature, then threshold. A node
    other than the root is a child of one that was found before. ask(nodes, rows) gives the best splits with a bit a row.
    """

    def __init__(self, ask: Callable, g: np.ndarray, h: np.ndarray):
        self.ask, self.g, self.h = ask, g, h
        self.rows: dict[int, np.ndarray] = {0: np.arange(len(g), dtype=np.int32)}
        self.left: dict[int, np.ndarray] = {}  # of the rows of a node that can be split

    def __call__(self, nodes: list[int]) -> dict[int, dict]:
        for n in nodes:
            if n not in self.rows:
                up = (n - 1) // 2
                own, left = self.rows.pop(up), self.left.pop(up)
                self.rows |= {2 * up + 1: own[left], 2 * up + 2: own[~left]}
        best = self.ask(nodes, self.rows)
        out: dict[int, dict] = {}
        for n in nodes:
            own = self.rows[n]
            if len(own):
                out[n] = {"node": n, "gain": None, "g": float(self.g[own].sum()), "h": float(self.h[own].sum())}
            if n in best:
                gain, threshold, gl, hl, f, self.left[n] = best[n]
                out[n] |= {"f": f, "threshold": threshold, "gain": gain, "gl": gl, "hl": hl}
        return out

    def outputs(self, tree: Tree) -> np.ndarray:
        """The tree's value of each row; nodes that were asked ahead and are not in the tree count as the leaf above them."""
        out = np.zeros(len(self.g))
        for n, own in self.rows.items():
            if n in tree.splits:
                out[own] = np.where(self.left[n], tree.values[2 * n + 1], tree.values[2 * n + 2])
                continue
            while n and (n - 1) // 2 not in tree.splits:
                n = (n - 1) // 2
            out[own] = tree.values.get(n, 0.0)
        return out


def _split(tree: Tree, n: int, b: dict, lam: float) -> None:
    tree.splits[n] = (b["f"], b["threshold"])
    tree.values[2 * n + 1] = leaf_value(b["gl"], b["hl"], lam)
    tree.values[2 * n + 2] = leaf_value(b["g"] - b["gl"], b["h"] - b["hl"], lam)


def _levels_by_columns(search: Callable, depth: int, lam: float) -> Tree:
    tree = Tree()
    open_ = [0]
    for level in range(max(depth, 1)):
        found = search(open_)
        if level == 0:
            tree.values[0] = leaf_value(found[0]["g"], found[0]["h"], lam) if found else 0.0
        gaining = {n: b for n, b in found.items() if b["gain"]} if depth else {}
        for n, b in gaining.items():
            _split(tree, n, b, lam)
        if not (open_ := [k for n in gaining for k in (2 * n + 1, 2 * n + 2)]):
            break
    return tree


def _leaves_by_columns(search: Callable, leaves: int, lam: float) -> Tree:
    """Best leaf first. Where a leaf's children are asked for, those of all open leaves are: their splits depend on no other leaf."""
    tree = Tree()
    known = search([0])
    tree.values[0] = leaf_value(known[0]["g"], known[0]["h"], lam) if known else 0.0
    ahead: set[int] = set()
    heap = [(-b["gain"], n) for n, b in known.items() if b["gain"]]
    count = 1
    while heap and count < leaves:
        _, n = heapq.heappop(heap)
        _split(tree, n, known[n], lam)
        count += 1
        if count < leaves:
            if n not in ahead:
                new = [k for k in (n, *[k for _, k in heap]) if k not in ahead]
                ahead |= set(new)
                known |= search([child for k in new for child in (2 * k + 1, 2 * k + 2)])
            for child in (2 * n + 1, 2 * n + 2):
                if child in known and known[child]["gain"]:
                    heapq.heappush(heap, (-known[child]["gain"], child))
    return tree


def _boost(model: GBDTModel, y: np.ndarray, loss: str, rounds: int, grow: Callable, asked: Callable) -> None:
    """All rounds; asked(g, h) gives what a tree's search asks."""
    score = np.zeros((len(y), model.classes))
    some = [slice(k, k + SCORED_ROWS) for k in range(0, len(y), SCORED_ROWS)]
    for _ in range(rounds):
        began = time.perf_counter()
        trees, outs = [], []
        for c in range(model.classes):
            g, h = map(np.concatenate, zip(*[[d[:, c] for d in Loss(loss).grad_hess(score[s], y[s])] for s in some]))
            ask = asked(g, h)
            search = _Search(ask, g, h)
            trees.append(grow(search))
            outs.append(search.outputs(trees[-1]))
            ask.close()
        model.trees.append(trees)
        for c, out in enumerate(outs):
            score[:, c] += model.eta * out
        model.history.append({"round": len(model.history), "wall_s": time.perf_counter() - began})


def _fit_columns(model: GBDTModel, rows: DataFrame, m: int, loss: str, rounds: int, grow: Callable, terms: tuple) -> None:
    """Columns are dealt and sorted once; labels, scores and nodes of rows, not their features, are on the driver."""
    blocks, y = _sorted_columns(rows, m)
    _boost(model, y, loss, rounds, grow, lambda g, h: _Blocks(blocks, g, h, terms))
    blocks.unpersist()


def _fit_in_task(model: GBDTModel, rows: DataFrame, m: int, loss: str, rounds: int, grow: Callable, terms: tuple) -> None:
    """The same rounds in one task, which has all columns; the driver gets the trees."""
    own = GBDTModel(model.kind, model.eta, model.classes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [(np.asarray(b.column("key")), np.asarray(b.column("y"), float), _matrix(b.column("x"), m)) for b in batches]
        if not parts:
            return
        key, y, x = map(np.concatenate, zip(*parts))
        del parts
        by_key = np.argsort(key, kind="stable")
        x = np.ascontiguousarray(x[by_key].T)
        order, values = _arranged(x)
        del x
        _boost(own, y[by_key], loss, rounds, grow, lambda g, h: _Columns(order, values, g, h, terms))
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps((own.trees, own.history))], pa.binary())], names=["model"])

    dealt = rows.select(F.xxhash64("rid").alias("key"), "y", "x").repartition(1)
    ((made,),) = dealt.mapInArrow(run, "model binary").collect()
    model.trees, model.history = pickle.loads(made)


def _fit(df, kind, loss, classes, rounds, eta, grow, by_columns, terms, checkpoint_every=5) -> GBDTModel:
    classes = classes if loss == "softmax" else 1
    model = GBDTModel(kind, eta, classes)
    features = "x" if kind == "dense" else "feats"
    base = df.filter(F.col("y").isNotNull()).select("rid", "y", features)
    if kind == "dense":
        wide = base.select("rid", F.col("y").cast("double").alias("y"), F.col("x").cast("array<double>").alias("x"))
        kept = df.storageLevel.useMemory or df.storageLevel.useDisk
        wide = wide if kept else wide.persist(StorageLevel.MEMORY_AND_DISK)
        n, m = wide.agg(F.count(F.lit(1)), F.max(F.size("x"))).first()
        if by_column := n <= COLUMN_ROWS and m and m > 0:
            (_fit_in_task if n * m <= TASK_NUMBERS else _fit_columns)(model, wide, m, loss, rounds, by_columns, terms)
        if not kept:
            wide.unpersist()
        if by_column:
            return model
    state = base.withColumn("score", F.array(*[F.lit(0.0)] * classes)).persist(StorageLevel.MEMORY_AND_DISK)
    for t in range(rounds):
        began = time.perf_counter()
        trees = []
        for c in range(classes):
            g, h = _grad(loss, c)
            trees.append(grow(state.withColumns({"g": g, "h": h}).select(features, "g", "h")))
        model.trees.append(trees)
        add = F.array(*[F.col("score")[c] + eta * tree_value(tree, kind) for c, tree in enumerate(trees)])
        old, state = state, state.withColumn("score", add)
        if t % checkpoint_every == checkpoint_every - 1 and df.sparkSession.sparkContext.getCheckpointDir():
            state = state.checkpoint(eager=True)
        state = state.persist(StorageLevel.MEMORY_AND_DISK)
        state.count()
        old.unpersist()
        model.history.append({"round": t, "wall_s": time.perf_counter() - began})
    state.unpersist()
    return model


def fit_gbdt_depth(
    df: DataFrame, kind: str = "dense", depth: int = 3, rounds: int = 10, eta: float = 0.3, lam: float = 1.0, gamma: float = 0.0,
    least_h: float = 1e-3, loss: str = "logistic", classes: int = 1, candidates: str = "exact", bins: int = 256,
) -> GBDTModel:
    """Level-wise trees of at most `depth` levels; candidates "exact" takes every value, "hist" quantile bins of dense features."""
    if candidates == "hist":
        m = len(df.select("x").first()["x"])
        df = df.withColumn("x", to_bins("x", quantile_bins(df, m, bins)))
    grow = lambda rows: _grow_levels(rows, kind, depth, lam, gamma, least_h)
    return _fit(df, kind, loss, classes, rounds, eta, grow, lambda search: _levels_by_columns(search, depth, lam), (lam, gamma, least_h))


def fit_gbdt_leaf(
    df: DataFrame, kind: str = "dense", leaves: int = 8, rounds: int = 10, eta: float = 0.3, lam: float = 1.0, gamma: float = 0.0,
    least_h: float = 1e-3, loss: str = "logistic", classes: int = 1,
) -> GBDTModel:
    """Leaf-wise trees of at most `leaves` leaves and any depth."""
    grow = lambda rows: _grow_leaves(rows, kind, leaves, lam, gamma, least_h)
    return _fit(df, kind, loss, classes, rounds, eta, grow, lambda search: _leaves_by_columns(search, leaves, lam), (lam, gamma, least_h))


def fit_random_trees(df: DataFrame, depth: int, rounds: int, m: int, seed: int = 0) -> list[tuple[Tree, DataFrame]]:
    """Trees of random splits that no label sets, shared by all targets: each with (leaf, n, mean of y)."""
    low_high = df.agg(*[F.min(F.element_at("x", k + 1)).alias(f"l{k}") for k in range(m)], *[F.max(F.element_at("x", k + 1)).alias(f"h{k}") for k in range(m)]).first()
    rng = np.random.default_rng(seed)
    out = []
    for _ in range(rounds):
        tree = Tree()
        for node in range(2**depth - 1):
            k = int(rng.integers(m))
            tree.splits[node] = (k, float(rng.uniform(low_high[k], low_high[m + k])))
        leaf = _leaf_number(tree, 0)
        out.append((tree, df.groupBy(leaf.alias("leaf")).agg(F.count(F.lit(1)).alias("n"), F.avg("y").alias("mean"))))
    return out


def _leaf_number(tree: Tree, node: int) -> Column:
    if node not in tree.splits:
        return F.lit(node)
    feature, threshold = tree.splits[node]
    return F.when(_value_of("dense", feature) <= threshold, _leaf_number(tree, 2 * node + 1)).otherwise(_leaf_number(tree, 2 * node + 2))


def fit_prior(df: DataFrame) -> DataFrame:
    """(y, share): the chance level."""
    n = df.filter(F.col("y").isNotNull())
    total = Window.partitionBy(F.lit(0))
    return n.groupBy("y").count().select("y", (F.col("count") / F.sum("count").over(total)).alias("share"))
