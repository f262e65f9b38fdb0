"""Numpy kernels of one block of rows: forward pass, cell statistics, assignment, Gram sums, scores.

A block comes from an Arrow batch. Rows are cut into blocks by non-zeros as well as by rows, so that the
work arrays stay within a budget whatever the rows hold.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa

from ..functions.hashing import law_np, md5_weights_np, mix_code_np, sym_np


#: Numbers of a work array that fit a core's cache, and of one that a task holds for a block.
CACHED, HELD = 1 << 15, 1 << 22


@dataclass(frozen=True)
class Spec:
    """What fixes the soft splitters of a run.

    kind `dense` reads x array<double>, `sparse` reads codes array<long> and vals array<double>. keep is
    the share of dense weights that are not zeroed. norm: unit | none | as_printed; assign: soft | hard.
    hash_fn "md5" draws uniform dense weights by md5 of "feature|round|cell", as SQL can.
    """

    kind: str
    cells: int
    m: int = 0
    init: str = "uniform"
    keep: float = 1.0
    seed: int = 0
    norm: str = "unit"
    temp: float = 1.0
    assign: str = "soft"
    layout: str = "column"
    row_norm: str = "none"
    layers: tuple[int, ...] = ()
    block_nnz: int = 1 << 16
    block_rows: int = 1 << 14
    hash_fn: str = "mix"

    def with_cells(self, cells: int) -> Spec:
        return replace(self, cells=cells)


def draw_splitter(spec: Spec, round_: int, cls: int = 0) -> np.ndarray:
    """The dense weights (m x cells) of a round; rounds are independent of the order they are drawn in."""
    if spec.hash_fn == "md5":
        return md5_weights_np(spec.m, round_, spec.cells)
    rng = np.random.default_rng(np.random.SeedSequence([spec.seed, round_, cls]))
    shape = (spec.layers[-1] if spec.layers else spec.m, spec.cells)
    weights = law_np(rng.uniform(-1, 1, shape), rng.uniform(-1, 1, shape), spec.init, spec.m)
    if spec.keep < 1:
        weights = weights * (rng.random(shape) < spec.keep)
    return weights


def hidden_layers(spec: Spec, round_: int) -> list[np.ndarray]:
    rng = np.random.default_rng(np.random.SeedSequence([spec.seed, round_, 7919]))
    sizes = [spec.m, *spec.layers]
    return [rng.uniform(-1, 1, (a, b)) / np.sqrt(a) for a, b in zip(sizes[:-1], sizes[1:])]


def hashed_weights(spec: Spec, codes: np.ndarray, round_: int, cls: int = 0) -> np.ndarray:
    """Weights (codes x cells) from feature codes; nothing is stored. Made in runs that stay in a core's cache."""
    cells = np.arange(spec.cells)
    seed = spec.seed + 31 * cls
    out = np.empty((len(codes), spec.cells))
    step = max(1, CACHED // spec.cells)
    for at in range(0, len(codes), step):
        own = codes[at : at + step]
        first = sym_np(mix_code_np(own, round_, cells, seed))
        if spec.init != "uniform":
            first = law_np(first, sym_np(mix_code_np(own, round_, cells, seed + 500_009)), spec.init, max(spec.m, 1))
        out[at : at + step] = first
    return out


@dataclass
class Block:
    """Rows of a batch: x (n x m), or offsets, codes and vals of a sparse block.

    A prepared sparse block has its distinct codes in feats and each entry's place among them in back; vals
    is None where all are one.
    """

    n: int
    x: np.ndarray | None = None
    offsets: np.ndarray | None = None
    codes: np.ndarray | None = None
    vals: np.ndarray | None = None
    feats: np.ndarray | None = None
    back: np.ndarray | None = None

    @staticmethod
    def of(batch: pa.RecordBatch, spec: Spec) -> Block:
        if spec.kind == "dense":
            x = batch.column("x")
            flat = np.nan_to_num(x.flatten().to_numpy(zero_copy_only=False).astype(np.float64))
            return Block(batch.num_rows, x=flat.reshape(batch.num_rows, -1) if batch.num_rows else np.zeros((0, spec.m)))
        codes, vals = batch.column("codes"), batch.column("vals")
        offsets = codes.offsets.to_numpy().astype(np.int64)
        block = Block(
            batch.num_rows,
            offsets=offsets - offsets[0],
            codes=codes.flatten().to_numpy(zero_copy_only=False),
            vals=vals.flatten().to_numpy(zero_copy_only=False).astype(np.float64),
        )
        if spec.row_norm == "l2":
            size = np.sqrt(_row_sums(block.vals[:, None] ** 2, block.offsets)[:, 0])
            block.vals = block.vals / np.repeat(np.maximum(size, 1e-12), np.diff(block.offsets))
        return block

    def parts(self, spec: Spec):
        """Row ranges within the row and non-zero budgets, which fall with the cells; a part closes on whichever is hit first."""
        rows = min(spec.block_rows, max(1, HELD // 4 // spec.cells))
        entries = min(spec.block_nnz, max(1, HELD // spec.cells))
        at = 0
        while at < self.n:
            stop = min(at + rows, self.n)
            if self.offsets is not None:
                fit = int(np.searchsorted(self.offsets, self.offsets[at] + entries, "right")) - 1
                stop = min(stop, max(fit, at + 1))
            yield at, stop
            at = stop

    def prepared(self, a: int, b: int) -> Block:
        """Rows a to b with what every round needs: distinct features and places among them."""
        if self.x is not None:
            return Block(b - a, x=self.x[a:b])
        i, j = self.offsets[a], self.offsets[b]
        feats, back = np.unique(self.codes[i:j], return_inverse=True)
        vals = self.vals[i:j]
        return Block(b - a, offsets=self.offsets[a : b + 1] - i, vals=None if (vals == 1).all() else vals, feats=feats, back=back.astype(np.int32))


class Work:
    """Arrays that a task allocates once and uses for all its blocks and rounds."""

    def __init__(self, spec: Spec):
        self.entries = max(1, 8 * CACHED // spec.cells)
        self.gathered = np.empty((self.entries, spec.cells))
        self.z = np.empty((0, spec.cells))

    def rows(self, n: int) -> np.ndarray:
        if n > len(self.z):
            self.z = np.empty((n, self.z.shape[1]))
        return self.z[:n]


def _row_sums(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    n = len(offsets) - 1
    each = len(values) // n if n else 0
    if each and (offsets[1:] - offsets[:-1] == each).all():  # one-hot rows: as many entries in each
        return values.reshape(n, each, -1).sum(1)
    out = np.zeros((n, values.shape[1]))
    full = np.flatnonzero(np.diff(offsets) > 0)
    if len(full):
        out[full] = np.add.reduceat(values, offsets[full], axis=0)
    return out


def forward(block: Block, spec: Spec, round_: int, cls: int = 0, weights: np.ndarray | None = None, work: Work | None = None) -> np.ndarray:
    """z (n x cells) of a block; with `work` the array is used again by the next call."""
    if spec.kind == "dense":
        x = block.x
        for hidden in hidden_layers(spec, round_) if spec.layers else ():
            x = np.tanh(x @ hidden)
        weights = draw_splitter(spec, round_, cls) if weights is None else weights
        return x @ weights if work is None else np.matmul(x, weights, out=work.rows(len(x)))
    if block.back is not None:
        return _sums_of(hashed_weights(spec, block.feats, round_, cls), block, work or Work(spec))
    out = np.zeros((block.n, spec.cells))
    for a, b in block.parts(spec):
        i, j = block.offsets[a], block.offsets[b]
        codes, vals = block.codes[i:j], block.vals[i:j]
        if spec.layout == "column":  # each distinct feature is hashed once
            codes, back = np.unique(codes, return_inverse=True)
            w = hashed_weights(spec, codes, round_, cls)[back]
        else:
            w = hashed_weights(spec, codes, round_, cls)
        if not (vals == 1).all():
            w *= vals[:, None]
        out[a:b] = _row_sums(w, block.offsets[a : b + 1] - i)
    return out


def _sums_of(w: np.ndarray, block: Block, work: Work) -> np.ndarray:
    """z of a prepared block; a row's weights are gathered and summed in runs of rows that fit the work array."""
    z, at = work.rows(block.n), 0
    while at < block.n:
        stop = int(np.searchsorted(block.offsets, block.offsets[at] + work.entries, "right")) - 1
        stop = min(max(stop, at + 1), block.n)
        i, j = block.offsets[at], block.offsets[stop]
        if j - i > work.entries:  # one row of more entries
            z[at] = w[block.back[i:j]].sum(0) if block.vals is None else block.vals[i:j] @ w[block.back[i:j]]
        else:
            got = np.take(w, block.back[i:j], axis=0, out=work.gathered[: j - i], mode="clip")
            if block.vals is not None:
                got *= block.vals[i:j, None]
            z[at:stop] = _row_sums(got, block.offsets[at : stop + 1] - i)
        at = stop
    return z


def statistics(z: np.ndarray) -> np.ndarray:
    """[n, sums, sums of squares] as one vector, additive over blocks."""
    return np.concatenate([[len(z)], z.sum(0), (z * z).sum(0)])


def moments(total: np.ndarray, norm: str = "unit") -> tuple[np.ndarray, np.ndarray]:
    """mu and sd of each cell; a cell without spread has sd 0."""
    cells = (len(total) - 1) // 2
    n, s, ss = total[0], total[1 : cells + 1], total[cells + 1 :]
    if norm == "none" or n < 2:
        return np.zeros(cells), np.ones(cells) if norm == "none" else np.zeros(cells)
    mu = s / n
    spread = ss - n * mu**2 if norm == "unit" else ss / n - mu**2  # as_printed: too small by sqrt(n)
    var = np.maximum(spread, 0) / (n - 1)
    scale = np.abs(ss).max(initial=0) * 1e-14 / max(n - 1, 1)
    return mu, np.where(var > scale, np.sqrt(var), 0.0)


def assign(z: np.ndarray, mu: np.ndarray, sd: np.ndarray, spec: Spec) -> np.ndarray:
    """Memberships p (n x cells), rows sum to one; cells with sd 0 get the normalised value 0."""
    zt = np.where(sd > 0, (z - mu) / np.where(sd > 0, sd, 1), 0.0) * spec.temp
    if spec.assign == "hard":
        return np.eye(z.shape[1])[zt.argmax(1)]
    zt -= zt.max(1, keepdims=True)
    np.exp(zt, out=zt)
    zt /= zt.sum(1, keepdims=True)
    return zt


def gram(p: np.ndarray, g: np.ndarray, h: np.ndarray) -> np.ndarray:
    """For each class the upper triangle of sum h p p' and sum g p, as one vector (classes x numbers)."""
    k = p.shape[1]
    upper = np.triu_indices(k)
    rows = [np.concatenate([((p * h[:, c : c + 1]).T @ p)[upper], p.T @ g[:, c]]) for c in range(g.shape[1])]
    return np.array(rows)


def gram_parts(vector: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    a = np.zeros((k, k))
    upper = np.triu_indices(k)
    a[upper] = vector[: len(upper[0])]
    return a + np.triu(a, 1).T, vector[len(upper[0]) :]
