"""Suffix-array dedup: bytes covered by a string of 100 bytes that also starts earlier are removed.

Every window of 100 bytes goes to the shard of its least 32-byte hash, so equal windows meet in one
shard. Successive windows that share the last place of their least hash travel as one segment, in which
no window equals another. Segments that stand alone need nothing more; of segments with equal text the first keeps its windows and the others' windows are all
repeats; only first segments that share a hash with different ones are sorted, by external induced
suffix sorting with common-prefix values, which finds their equal windows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ._store import Workspace
from ._text import PIECE, mix, raw, slices
from .induced_sort import sort_suffixes
from .near_dedup import _grouped

GRAM = 32
#: Odd multiplier of the rolling hash of GRAM bytes; 32 bytes are too few for sums of powers modulo 2**64 to cancel by form.
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_CODE = np.random.default_rng(20240607).integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_powers: dict[int, np.ndarray] = {}
_PLACE = np.uint64((1 << 23) - 1)  # above the bytes of a piece


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64, kept and grown by doubling."""
    have = _powers.get(base)
    if have is None:
        have = np.ones(1, np.uint64)
    while len(have) < n:
        step = np.uint64(pow(base, len(have), 1 << 64))
        have = np.concatenate([have, have * step])
    _powers[base] = have
    return have[:n]


def _segment_hashes(gram: np.ndarray, start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """A hash of each segment from those of its successive GRAM bytes, the last ones ending with it."""
    h, k = mix(size.astype(np.uint64)), 0
    live = np.arange(len(start))
    while len(live):
        place = np.minimum(start[live] + k, start[live] + size[live] - GRAM)
        h[live] = mix(h[live] * np.uint64(0xC2B2AE3D27D4EB4F) ^ gram[place])
        k += GRAM
        live = live[size[live] > k]
    return h


def _sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each `width` successive values."""
    have, out = 1, values
    while 2 * have <= width:
        out = np.minimum(out[:-have], out[have:])
        have *= 2
    return np.minimum(out[: len(out) - (width - have)], out[width - have :]) if have < width else out


def segments_of(buf: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, ...]:
    """(row, start in the row, windows, least hash, hash of the segment's bytes) of all segments of rows.

    The rows' bytes are taken in pieces; a piece's end ends a segment.
    """
    out: list[tuple[np.ndarray, ...]] = []
    last = offsets[1:] - width  # last window start of each row
    at = 0
    while at + width <= len(buf):
        stop = min(at + PIECE, len(buf))  # windows starting in [at, stop)
        piece = buf[at : min(stop + width - 1, len(buf))]
        n = len(piece) - width + 1
        if n <= 0:
            break
        sums = np.zeros(len(piece) + 1, np.uint64)
        np.cumsum(_CODE[piece] * powers(_BASE, len(piece)), out=sums[1:])
        back = powers(_INVERSE, len(piece))
        gram = mix((sums[GRAM:] - sums[:-GRAM]) * back[: len(piece) - GRAM + 1])
        # high bits of the hash, then the place from the end, so that the last of equal ones is least
        places = _PLACE - np.arange(len(gram), dtype=np.uint64)
        last_least = _PLACE - (_sliding_min(gram & ~_PLACE | places, width - GRAM + 1) & _PLACE)
        row = np.searchsorted(offsets, np.arange(at, at + n), "right") - 1
        valid = np.arange(at, at + n) <= last[row]
        new = valid.copy()
        new[1:] &= (last_least[1:] != last_least[:-1]) | (row[1:] != row[:-1]) | ~valid[:-1]
        start = np.flatnonzero(new)
        if len(start):
            ends = valid.copy()
            ends[:-1] &= new[1:] | ~valid[1:]
            count = np.flatnonzero(ends) + 1 - start
            size = count + width - 1
            text = _segment_hashes(gram, start, size)
            out.append((row[start], start + at - offsets[row[start]], count, gram[last_least[start].astype(np.int64)], text))
        at = stop
    if not out:
        return tuple(np.zeros(0, np.int64) for _ in range(3)) + tuple(np.zeros(0, np.uint64) for _ in range(2))
    return tuple(np.concatenate(x) for x in zip(*out))


def later_copies(m: np.ndarray, s: np.ndarray, ids: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Whether a segment with the same m and s and a smaller (id, start) is among those given."""
    both = mix(m) + s
    _, back, count = np.unique(both, return_inverse=True, return_counts=True)
    some = np.flatnonzero(count[back] > 1)
    order = some[np.lexsort((start[some], ids[some], s[some], m[some]))]
    out = np.zeros(len(m), bool)
    out[order[1:]] = (m[order[1:]] == m[order[:-1]]) & (s[order[1:]] == s[order[:-1]])
    return out


def segments(docs: DataFrame, width: int) -> DataFrame:
    """(m, s, sure, doc_id, start, windows) of all segments of docs (doc_id, text).

    A segment that repeats one with a smaller start of the same slice of rows is a sure repeat. It needs no
    company of its hash, so its m is drawn from its place, which keeps large groups of copies apart.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text"):
                row, start, count, m, s = segments_of(*raw(batch.column("text")), width)
                ids = batch.column("doc_id").take(pa.array(row))
                number = np.asarray(ids.fill_null(-(2**63)).to_numpy(zero_copy_only=False), np.int64)
                sure = later_copies(m, s, number, start)
                m = np.where(sure, mix(mix(number.view(np.uint64)) + start.astype(np.uint64)), m)
                cols = [pa.array(m.view(np.int64)), pa.array(s.view(np.int64)), pa.array(sure), ids, pa.array(start), pa.array(count)]
                yield pa.RecordBatch.from_arrays(cols, names=["m", "s", "sure", "doc_id", "start", "windows"])

    return docs.mapInArrow(run, "m long, s long, sure boolean, doc_id long, start long, windows long")


def cut_out(docs: DataFrame) -> DataFrame:
    """(m, doc_id, start, seg): the bytes of wanted segments of docs (doc_id, text, wanted)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text"):
                buf, offsets = raw(batch.column("text"))
                wanted = batch.column("wanted")
                flat = wanted.flatten()
                row = np.repeat(np.arange(batch.num_rows), np.diff(wanted.offsets.to_numpy()))
                m, start, size = (flat.field(k).to_numpy(zero_copy_only=False) for k in ("m", "start", "size"))
                begin = offsets[row] + start
                text = buf.tobytes()
                segs = [text[a : a + n] for a, n in zip(begin.tolist(), size.tolist())]
                cols = [pa.array(m), batch.column("doc_id").take(pa.array(row)), pa.array(start), pa.array(segs, pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, names=["m", "doc_id", "start", "seg"])

    return docs.mapInArrow(run, "m long, doc_id long, start long, seg binary")


def repeated_windows(segs: list[bytes], width: int, budget: int, folder: str | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(segment, place) of each window that equals one at an earlier place; segments stand in order of first start."""
    text = np.frombuffer(b"\0".join(segs) + b"\0", np.uint8).astype(np.uint16)
    sizes = np.array([len(s) for s in segs])
    first = np.concatenate([[0], np.cumsum(sizes + 1)])
    text += 1
    text[first[1:] - 1] = 0
    ends = np.repeat(first[1:] - 1, sizes + 1)
    found: list[np.ndarray] = []

    def emit(pos: np.ndarray, lcp: np.ndarray) -> None:
        fits = pos + width <= ends[pos]
        group = np.cumsum(lcp < width)[fits]
        pos = pos[fits]
        if len(pos) > 1:
            heads = np.concatenate([[0], np.flatnonzero(group[1:] != group[:-1]) + 1])
            earliest = np.repeat(np.minimum.reduceat(pos, heads), np.diff(np.append(heads, len(pos))))
            found.append(pos[pos != earliest].astype(np.int64))

    sort_suffixes(text, width, emit, budget, folder, 257)
    pos = np.sort(np.concatenate(found)) if found else np.zeros(0, np.int64)
    seg = np.searchsorted(first, pos, "right") - 1
    return seg, pos - first[seg]


def sorted_repeats(cut: DataFrame, width: int, shard_bytes: int, budget: int) -> DataFrame:
    """(doc_id, a, b): byte ranges of repeats among segments (m, doc_id, start, seg), found by suffix sorting in shards.

    A shard is filled with whole groups of m up to `shard_bytes`; a larger group is a shard of its own,
    whose tuples beyond `budget` bytes are on disk.
    """

    def solve(held: list[pa.Table]) -> Iterator[pa.RecordBatch]:
        table = pa.concat_tables(held).combine_chunks()
        ids, start = table.column("doc_id").combine_chunks(), table.column("start").to_numpy()
        seg, place = repeated_windows(table.column("seg").to_pylist(), width, budget)
        if len(seg):
            new = np.concatenate([[0], np.flatnonzero((seg[1:] != seg[:-1]) | (place[1:] != place[:-1] + 1)) + 1])
            end = np.append(new[1:], len(seg)) - 1
            a = start[seg[new]] + place[new]
            b = start[seg[end]] + place[end] + width
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(seg[new])), pa.array(a), pa.array(b)], names=["doc_id", "a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for table in _grouped(batches, "m"):
            held.append(table)
            size += table.column("seg").nbytes
            if size >= shard_bytes:
                yield from solve(held)
                held, size = [], 0
        if held:
            yield from solve(held)

    ordered = cut.repartition("m").sortWithinPartitions("m", F.col("doc_id").asc_nulls_first(), "start")
    return ordered.mapInArrow(run, "doc_id long, a long, b long")


def strip(docs: DataFrame) -> DataFrame:
    """The digest of docs (doc_id, text, gone: array of (a, b) in any order, or null)."""
    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, "text"):
                buf, offsets = raw(batch.column("text"))
                gone = batch.column("gone")
                flat, at = gone.flatten(), gone.offsets.to_numpy()
                at = at - at[0]
                a_all, b_all = (flat.field(k).to_numpy(zero_copy_only=False) for k in ("a", "b"))
                text, out = buf.tobytes(), []
                for i in range(batch.num_rows):
                    own = text[offsets[i] : offsets[i + 1]]
                    a, b = a_all[at[i] : at[i + 1]], b_all[at[i] : at[i + 1]]
                    if not len(a):
                        out.append((len(own), 0, 0, hashlib.sha256(own).hexdigest()))
                        continue
                    order = np.argsort(a, kind="stable")
                    a, reach = a[order], np.maximum.accumulate(b[order])
                    new = np.concatenate([[0], np.flatnonzero(a[1:] > reach[:-1]) + 1])
                    begin, end = a[new], np.append(reach[new[1:] - 1], reach[-1])
                    kept, last = hashlib.sha256(), 0
                    for x, y in zip(begin.tolist(), end.tolist()):
                        kept.update(own[last:x])
                        last = y
                    kept.update(own[last:])
                    out.append((len(own), int((end - begin).sum()), len(begin), kept.hexdigest()))
                n, removed, spans, sha = zip(*out)
                cols = [batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(spans, pa.int64()), pa.array(sha)]
                yield pa.RecordBatch.from_arrays(cols, names=[x.split()[0] for x in schema.split(", ")])

    return docs.mapInArrow(run, schema)


def remove_repeats(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    width: int = 100,
    shard_bytes: int = 2 << 20,
    budget: int = 64 << 20,
) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and kept_sha256 of each document.

    A byte is removed when a string of `width` bytes over it also starts earlier: in a smaller id, or
    earlier in the same document. Null texts are empty. Ids must be unique for exact results: rows that
    repeat an id count as copies whose ranges are removed from every row of the id; a null id is smaller
    than all others. An empty table gives no rows; other columns are not read. Whole segments are told
    apart by 128 bits of hash; windows of different segments by their bytes.
    """
    ws = Workspace(docs.sparkSession, "suffix-dedup")
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(text_col, F.lit("")).alias("text"))
    long_enough = texts.filter(F.octet_length("text") >= width)
    first = Window.partitionBy("m", "s").orderBy(F.col("doc_id").asc_nulls_first(), "start")
    group = Window.partitionBy("m")
    marked = (
        segments(long_enough, width)
        .withColumn("nth", F.row_number().over(first))
        .withColumn("many", F.min("s").over(group) != F.max("s").over(group))
        .filter("sure or nth > 1 or many")
        .select("m", "doc_id", "start", (F.col("windows") + width - 1).alias("size"), (F.col("sure") | (F.col("nth") > 1)).alias("repeat"))
    )
    marked = ws.save(marked, "marked")
    wanted = (
        marked.filter("not repeat").groupBy("doc_id").agg(F.collect_list(F.struct("m", "start", "size")).alias("wanted"))
        .withColumnRenamed("doc_id", "id")
    )
    cut = cut_out(texts.join(wanted, F.col("doc_id").eqNullSafe(F.col("id"))).select("doc_id", "text", "wanted"))
    repeats = sorted_repeats(cut, width, shard_bytes, budget)
    whole = marked.filter("repeat").select("doc_id", F.col("start").alias("a"), (F.col("start") + F.col("size")).alias("b"))
    gone = (
        repeats.unionByName(whole).groupBy(F.col("doc_id").alias("id")).agg(F.collect_list(F.struct("a", "b")).alias("gone"))
    )
    gone = ws.save(gone, "gone")
    none = F.expr("CAST(array() AS array<struct<a:bigint,b:bigint>>)")
    joined = texts.join(gone, F.col("doc_id").eqNullSafe(F.col("id")), "left")
    return strip(joined.select("doc_id", "text", F.coalesce("gone", none).alias("gone")))
