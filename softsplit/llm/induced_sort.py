"""External induced suffix sorting with common-prefix values.

Suffix tuples (position, common prefix with the suffix before) wait in a monotone priority queue keyed by
their first symbol: tuples of one symbol arrive in their final order, so a queue of each symbol is a file
that is appended and read once. Tuples beyond a memory budget lie on disk. A pass in ascending order of
symbols induces the suffixes that are larger than their successor, one in descending order the others;
both start from the leftmost smaller suffixes, whose order comes from sorting the reduced string of their
substrings' names, by the same way while its alphabet is small. Common prefixes are carried along: two
suffixes of one first symbol share one symbol more than the least common prefix between their successors.
All steps work on blocks of tuples.
"""

from __future__ import annotations

import os
import tempfile
from collections import deque

import numpy as np

#: Symbols above which a reduced string is sorted by doubling instead of by queues of each symbol.
MOST_SYMBOLS = 1024
#: Tuples that small blocks are merged to before they are processed.
MERGED = 1 << 20


class TupleQueue:
    """First-in-first-out queues of (positions, prefixes) blocks by symbol; blocks beyond the budget are on disk."""

    def __init__(self, symbols: int, budget: int, folder: str | None = None):
        self.blocks: list[deque] = [deque() for _ in range(symbols)]
        self.budget, self.held = budget, 0
        self.folder, self.file = folder, None

    def push(self, symbol: int, pos: np.ndarray, lcp: np.ndarray) -> None:
        if self.held + pos.nbytes + lcp.nbytes > self.budget:
            if self.file is None:
                self.file = tempfile.TemporaryFile(dir=self.folder)
            self.file.seek(0, os.SEEK_END)
            at = self.file.tell()
            self.file.write(pos.tobytes())
            self.file.write(lcp.tobytes())
            self.blocks[symbol].append((at, len(pos), pos.dtype))
        else:
            self.held += pos.nbytes + lcp.nbytes
            self.blocks[symbol].append((pos, lcp))

    def _load(self, block) -> tuple[np.ndarray, np.ndarray]:
        if len(block) == 2:
            self.held -= block[0].nbytes + block[1].nbytes
            return block
        at, n, kind = block
        self.file.seek(at)
        pos = np.frombuffer(self.file.read(n * kind.itemsize), kind)
        return pos, np.frombuffer(self.file.read(n), np.uint8)

    def pop(self, symbol: int, last: bool = False) -> tuple[np.ndarray, np.ndarray] | None:
        """The first (or last) waiting blocks of a symbol as one block, about MERGED tuples of them."""
        blocks, got, n = self.blocks[symbol], [], 0
        while blocks and n < MERGED:
            got.append(self._load(blocks.pop() if last else blocks.popleft()))
            n += len(got[-1][0])
        if last:
            got.reverse()
        if len(got) < 2:
            return got[0] if got else None
        return np.concatenate([p for p, _ in got]), np.concatenate([x for _, x in got])

    def close(self) -> None:
        if self.file is not None:
            self.file.close()


def _larger(text: np.ndarray) -> np.ndarray:
    """Whether each suffix is larger than its successor; the end of the text is smaller than all."""
    n = len(text)
    cuts = np.append(np.flatnonzero(text[1:] != text[:-1]), n - 1)  # last place of each run
    after = np.append(text[cuts[:-1] + 1] < text[cuts[:-1]], True)
    return np.repeat(after, np.diff(np.append(-1, cuts)))


def _run_length(text: np.ndarray, p: int, most: int) -> int:
    piece = text[p : p + max(most, 1)]
    other = np.flatnonzero(piece != piece[0])
    return int(other[0]) if len(other) else len(piece)


class _Minima:
    """Range minima of a block of uint8 values."""

    def __init__(self, values: np.ndarray):
        self.levels = [values]
        width = 1
        while 2 * width <= len(values):
            last = self.levels[-1]
            self.levels.append(np.minimum(last[:-width], last[width:]))
            width *= 2

    def least(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Minimum of values[lo:hi], hi > lo."""
        out = np.empty(len(lo), np.uint8)
        level = np.log2(hi - lo).astype(np.int64)
        level[(1 << level) > hi - lo] -= 1
        for k in np.unique(level):
            own = level == k
            row = self.levels[k]
            out[own] = np.minimum(row[lo[own]], row[hi[own] - (1 << k)])
        return out


class _Inducer:
    """Sends each block of processed tuples on to its predecessors' queues; without a cap no prefixes are carried."""

    def __init__(self, text: np.ndarray, wanted: np.ndarray, queue: TupleQueue, symbols: int, cap: int):
        self.text, self.wanted, self.queue, self.cap = text, wanted, queue, cap
        self.since = np.zeros(symbols, np.uint8)  # least prefix value seen since the symbol's last tuple

    def send(self, pos: np.ndarray, lcp: np.ndarray) -> None:
        before = pos - 1
        ok = np.flatnonzero(before >= 0)
        ok = ok[self.wanted[before[ok]]]
        if len(ok):
            symbol = self.text[before[ok]]
            order = np.argsort(symbol, kind="stable")
            at, symbol = ok[order], symbol[order]
            heads = np.concatenate([[0], np.flatnonzero(symbol[1:] != symbol[:-1]) + 1])
            ends = np.append(heads[1:], len(at))
            if not self.cap:
                none = np.zeros(len(at), np.uint8)
                for a, b in zip(heads.tolist(), ends.tolist()):
                    self.queue.push(int(symbol[a]), before[at[a:b]], none[a:b])
                return
            minima = _Minima(lcp)
            previous = np.empty(len(at), np.int64)
            previous[1:] = at[:-1]
            previous[heads] = -1
            shared = minima.least(previous + 1, at + 1)
            shared[heads] = np.minimum(shared[heads], self.since[symbol[heads]])
            shared = np.minimum(shared.astype(np.int64) + 1, self.cap).astype(np.uint8)
            lows = np.full(len(heads), self.cap, np.uint8)
            lasts = at[ends - 1]
            rest = lasts + 1 < len(lcp)
            if rest.any():
                lows[rest] = minima.least(lasts[rest] + 1, np.full(rest.sum(), len(lcp)))
            np.minimum(self.since, lcp.min(), out=self.since)
            self.since[symbol[heads]] = lows
            for a, b in zip(heads.tolist(), ends.tolist()):
                self.queue.push(int(symbol[a]), before[at[a:b]], shared[a:b])
        else:
            np.minimum(self.since, lcp.min(), out=self.since)


def _induce(text, larger, seeds, seed_lcp, symbols, cap, budget, folder, emit) -> None:
    """Both passes. seeds: leftmost smaller suffixes in order, seed_lcp with the one before in its bucket.

    emit(positions, prefixes) gets the suffixes of each symbol in ascending order.
    """
    kind = seeds.dtype
    queue, done = TupleQueue(symbols, budget, folder), TupleQueue(symbols, budget, folder)
    up = _Inducer(text, larger, queue, symbols, cap)
    queue.push(int(text[-1]), np.array([len(text) - 1], kind), np.zeros(1, np.uint8))
    cuts = np.searchsorted(text[seeds], np.arange(symbols + 1))
    for c in range(symbols):
        last = -1
        first = True
        while (block := queue.pop(c)) is not None:
            pos, lcp = block
            if first:
                lcp = lcp.copy()
                lcp[0] = 0
                first = False
            done.push(c, pos, lcp)
            up.send(pos, lcp)
            last = int(pos[-1])
        a, b = cuts[c], cuts[c + 1]
        if a < b:
            lcp = seed_lcp[a:b].copy()
            lcp[0] = min(_run_length(text, last, cap), _run_length(text, int(seeds[a]), cap)) if last >= 0 else 0
            up.send(seeds[a:b], lcp)
    down_queue = TupleQueue(symbols, budget, folder)
    down = _Inducer(text, ~larger, down_queue, symbols, cap)
    out: list = []
    for c in reversed(range(symbols)):
        smaller: list[tuple[np.ndarray, np.ndarray]] = []  # descending
        last = -1
        while (block := down_queue.pop(c)) is not None:
            pos, lcp = block
            if last < 0:
                lcp = lcp.copy()
                lcp[0] = 0
            smaller.append((pos, lcp))
            down.send(pos, lcp)
            last = int(pos[-1])
        bigger: list[tuple[np.ndarray, np.ndarray]] = []
        edge = None  # prefix of the tuple processed just before with the next one
        if last >= 0:
            edge = -1
        while (block := done.pop(c, last=True)) is not None:
            pos, lcp = block
            bigger.append((pos, lcp))
            back = np.empty(len(lcp), np.uint8)
            back[1:] = lcp[:0:-1]
            if edge is None:
                back[0] = 0
            elif edge < 0:
                back[0] = min(_run_length(text, last, cap), _run_length(text, int(pos[-1]), cap))
            else:
                back[0] = edge
            if edge == -1:
                join = back[0]
            edge = int(lcp[0])
            down.send(pos[::-1], back)
        positions = [p for p, _ in reversed(bigger)]
        prefixes = [x for _, x in reversed(bigger)]
        if smaller:
            pos = np.concatenate([p for p, _ in smaller])[::-1]
            desc = np.concatenate([x for _, x in smaller])
            asc = np.empty(len(desc), np.uint8)
            asc[1:] = desc[:0:-1]
            asc[0] = join if bigger else 0
            positions.append(pos)
            prefixes.append(asc)
        if positions:
            out.append((np.concatenate(positions), np.concatenate(prefixes)))
    for pos, lcp in reversed(out):
        emit(pos, lcp)
    for q in (queue, done, down_queue):
        q.close()


def _doubling(text: np.ndarray, depth: int) -> np.ndarray:
    """Ranks of the suffixes of a string by their first `depth` symbols at least; equal ones share a rank."""
    rank = np.unique(text, return_inverse=True)[1].astype(np.int64) + 1
    width = 1
    while width < depth and rank.max() < len(rank):
        later = np.zeros(len(rank), np.int64)
        if width < len(rank):
            later[:-width] = rank[width:]
        rank = np.unique(rank * (len(rank) + 1) + later, return_inverse=True)[1].astype(np.int64) + 1
        width *= 2
    return rank


def _names(text: np.ndarray, lms: np.ndarray, order: np.ndarray) -> np.ndarray:
    """Names of the substrings from each leftmost smaller position to the next one, equal for equal substrings.

    order: the positions' numbers in order of their substrings. Neighbours are compared symbol by symbol.
    """
    length = np.append(np.diff(lms) + 1, len(text) - lms[-1])
    a, b = order[:-1], order[1:]
    same = length[a] == length[b]
    same[(a == len(lms) - 1) | (b == len(lms) - 1)] = False  # the last ends with the text
    live = np.flatnonzero(same)
    k = 0
    while len(live):
        equal = text[lms[a[live]] + k] == text[lms[b[live]] + k]
        same[live[~equal]] = False
        k += 1
        live = live[equal]
        live = live[length[a[live]] > k]
    name = np.empty(len(lms), np.int64)
    name[order] = np.concatenate([[0], np.cumsum(~same)])
    return name


def common_prefix(text: np.ndarray, a: np.ndarray, b: np.ndarray, cap: int) -> np.ndarray:
    out = np.zeros(len(a), np.uint8)
    live, n = np.arange(len(a)), len(text)
    for k in range(cap):
        live = live[(a[live] + k < n) & (b[live] + k < n)]
        live = live[text[a[live] + k] == text[b[live] + k]]
        if not len(live):
            break
        out[live] = k + 1
    return out


def sort_suffixes(text: np.ndarray, cap: int, emit, budget: int = 64 << 20, folder: str | None = None, symbols: int | None = None) -> None:
    """Gives emit the suffixes of a text of small symbols in ascending order with common prefixes, block by block.

    The order is exact for the first `cap` symbols (suffixes equal there may stand in any order), and
    common prefixes are capped at `cap` (at most 255). A block holds all suffixes of one first symbol.
    """
    n = len(text)
    if not n:
        return
    kind = np.int32 if n < 2**31 else np.int64
    symbols = symbols or int(text.max()) + 1
    text = text.astype(np.uint16 if symbols <= 65536 else np.uint32)
    larger = _larger(text)
    lms = np.flatnonzero(~larger[1:] & larger[:-1]).astype(kind) + kind(1)
    if not len(lms):
        _induce(text, larger, lms, np.zeros(0, np.uint8), symbols, cap, budget, folder, emit)
        return
    # order of the substrings between leftmost smaller positions: induced from their first symbols
    by_first = lms[np.argsort(text[lms], kind="stable")]
    got: list[np.ndarray] = []
    is_lms = np.zeros(n, bool)
    is_lms[lms] = True
    _induce(text, larger, by_first, np.zeros(len(lms), np.uint8), symbols, 0, budget, folder, lambda p, _: got.append(p[is_lms[p]]))
    number = np.zeros(n, kind)
    number[lms] = np.arange(len(lms), dtype=kind)
    name = _names(text, lms, number[np.concatenate(got)])
    kinds = int(name.max()) + 1
    if kinds == len(lms):
        rank = name
    elif kinds > MOST_SYMBOLS or len(lms) < MOST_SYMBOLS:
        rank = _doubling(name, -(-cap // 2) + 1)  # a substring adds two symbols at least
    else:
        parts: list[np.ndarray] = []
        sort_suffixes(name, min(255, cap), lambda p, _: parts.append(p), budget, folder, kinds)
        rank = np.empty(len(lms), np.int64)
        rank[np.concatenate(parts)] = np.arange(len(lms))
    seeds = lms[np.argsort(rank, kind="stable")]
    seed_lcp = np.concatenate([np.zeros(1, np.uint8), common_prefix(text, seeds[:-1], seeds[1:], cap)])
    _induce(text, larger, seeds, seed_lcp, symbols, cap, budget, folder, emit)
