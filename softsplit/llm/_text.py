"""Vectorised tokenising of Arrow string columns: words as 64-bit hashes, without Python strings."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash

#: Bytes of the six ASCII white-space characters.
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
#: Text bytes handled at once; bounds the work arrays.
PIECE = 1 << 20

#: Bytes of a span above which it is hashed by xxhash instead of in steps over all spans.
LONG_SPAN = 256
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_LOW = np.array([(1 << 8 * k) - 1 for k in range(8)] + [2**64 - 1], np.uint64)
_STEP, _SIZE = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def eights(buf: np.ndarray) -> np.ndarray:
    """The eight bytes from each place of buf on as a little-endian number, zeros after the end."""
    padded = np.concatenate([buf, np.zeros(8, np.uint8)])
    return np.ndarray((len(buf) + 1,), np.dtype("<u8"), padded.data, 0, (1,))


def span_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the bytes of each span.

    Eight bytes at a time go through a full mix, so that, unlike in a sum of powers, no text is known by
    its form to share a hash with another one. Spans of at most eight bytes and equal length never collide.
    """
    size = ends - starts
    at = eights(buf)
    h = mix(size.astype(np.uint64) * _SIZE ^ (at[starts] & _LOW[np.minimum(size, 8)]))
    live, k = np.flatnonzero((size > 8) & (size <= LONG_SPAN)), 8
    while len(live):
        left = np.minimum(size[live] - k, 8)
        h[live] = mix(h[live] * _STEP ^ (at[starts[live] + k] & _LOW[left]))
        k += 8
        live = live[size[live] > k]
    for i in np.flatnonzero(size > LONG_SPAN):
        h[i] = xxhash.xxh3_64_intdigest(buf[starts[i] : ends[i]])
    return h


def raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All text bytes of a string column and the offsets of its rows; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
    if column.null_count:
        column = column.fill_null(b"")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, at, data = column.buffers()
    offsets = np.frombuffer(at, np.int64)[column.offset : column.offset + len(column) + 1]
    buf = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return buf[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(batch: pa.RecordBatch, column: str, most: int = 2 * PIECE) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows with about `most` text bytes each; a longer text is a run of its own."""
    _, offsets = raw(batch.column(column))
    start = 0
    while start < batch.num_rows:
        stop = int(np.searchsorted(offsets, offsets[start] + most, "right")) - 1
        stop = min(max(stop, start + 1), batch.num_rows)
        yield batch.slice(start, stop - start)
        start = stop


def _piece(buf: np.ndarray, fresh: np.ndarray, fold: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    word = ~SPACE[buf]
    begins = word.copy()
    begins[1:] &= ~word[:-1] | fresh[1:]
    starts = np.flatnonzero(begins)
    if not len(starts):
        return starts, starts, np.zeros(0, np.uint64)
    stops = word.copy()
    stops[:-1] &= ~word[1:] | fresh[1:]
    ends = np.flatnonzero(stops) + 1
    return starts, ends, span_hashes(_FOLD[buf] if fold else buf, starts, ends)


def words(buf: np.ndarray, offsets: np.ndarray, fold: bool = True) -> tuple[np.ndarray, ...]:
    """Word starts, ends (bytes) and hashes of rows, and the offsets of each row's words.

    A word is a run of bytes that are no ASCII white space, which for UTF-8 is the same as a run of
    such characters. Equal words (A-Z folded when `fold`) have equal hashes whatever surrounds them.
    """
    fresh = np.zeros(len(buf) + 1, bool)
    fresh[offsets[:-1]] = True
    found, at = [], 0
    while at < len(buf):
        stop = min(at + PIECE, len(buf))
        if stop < len(buf):  # cut where no word is cut
            cut = np.flatnonzero(SPACE[buf[at:stop]] | fresh[at:stop])
            cut = cut[cut > 0]
            while not len(cut) and stop < len(buf):
                more = min(stop + PIECE, len(buf))
                cut = np.flatnonzero(SPACE[buf[stop:more]] | fresh[stop:more])[:1] + (stop - at)
                stop = more
            stop = at + int(cut[-1]) if len(cut) else len(buf)
        starts, ends, hashes = _piece(buf[at:stop], fresh[at:stop], fold)
        found.append((starts + at, ends + at, hashes))
        at = stop
    if not found:
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
    starts, ends, hashes = (np.concatenate(x) for x in zip(*found))
    return starts, ends, hashes, np.searchsorted(starts, offsets)


def windows(hashes: np.ndarray, n: int) -> np.ndarray:
    """A hash of each n successive values."""
    if len(hashes) < n:
        return np.zeros(0, np.uint64)
    out = np.zeros(len(hashes) - n + 1, np.uint64)
    for j in range(n):
        out = out * np.uint64(0xD6E8FEB86659FD93) + hashes[j : len(hashes) - n + 1 + j]
    return mix(out)
