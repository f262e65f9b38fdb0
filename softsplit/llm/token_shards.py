"""Token-ID output: shards of token ids as wavelet matrices, one compressed file each.

A wavelet matrix keeps one bit-plane for each bit of an id, highest first; after each plane the ids are
parted stably, zeros before ones. With counts of ones before each block (rank) and a search over them
(select), single ids, counts of an id in a range and the places of an id are found without decoding.
"""

from __future__ import annotations

import json
import struct
import zlib
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, functions as F

from ._store import Workspace, shuffle_partitions
from ._text import _LOW, eights, raw, slices, span_hashes

MAGIC = b"WVMX1\n"
BLOCK = 512  # bits of a rank block


class WaveletMatrix:
    """Ids below 2**len(planes) as packed bit-planes with rank directories."""

    def __init__(self, n: int, zeros: Sequence[int], planes: list[np.ndarray], ranks: list[np.ndarray] | None = None):
        self.n, self.zeros, self.planes = n, list(zeros), planes
        self.ranks = ranks if ranks is not None else [self._directory(p) for p in planes]

    @staticmethod
    def build(ids: np.ndarray, bits: int) -> WaveletMatrix:
        ids = ids.astype(np.uint16 if bits <= 16 else np.uint32)
        zeros, planes = [], []
        for level in reversed(range(bits)):
            bit = (ids >> level & 1).astype(bool)
            planes.append(np.packbits(bit))
            ids = np.concatenate([ids[~bit], ids[bit]])
            zeros.append(len(bit) - int(bit.sum()))
        return WaveletMatrix(len(ids), zeros, planes)

    @staticmethod
    def _directory(plane: np.ndarray) -> np.ndarray:
        ones = np.bitwise_count(plane).astype(np.int64)
        width = BLOCK // 8
        sums = np.add.reduceat(ones, np.arange(0, len(ones), width)) if len(ones) else ones
        return np.concatenate([[0], np.cumsum(sums)]).astype(np.int64)

    def _rank1(self, level: int, i: np.ndarray) -> np.ndarray:
        """Ones of the plane before each place of i."""
        plane, width = self.planes[level], BLOCK // 8
        block, byte = i // BLOCK, i // 8
        out = self.ranks[level][block].copy()
        for k in range(width):
            at = block * width + k
            full = at < byte
            if not full.any():
                break
            out[full] += np.bitwise_count(plane[at[full]])
        part = (i % 8 > 0) & (byte < len(plane))
        out[part] += np.bitwise_count(plane[byte[part]] >> (8 - i[part] % 8).astype(np.uint8))
        return out

    def _select(self, level: int, k: np.ndarray, one: bool) -> np.ndarray:
        """The place of the k-th (from 0) one or zero of the plane."""
        have = self.ranks[level] if one else np.minimum(np.arange(len(self.ranks[level])) * BLOCK, self.n) - self.ranks[level]
        block = np.searchsorted(have, k, "right") - 1
        bits = np.zeros((len(k), BLOCK), np.uint8)
        width = BLOCK // 8
        plane = np.pad(self.planes[level], (0, -len(self.planes[level]) % width)).reshape(-1, width)
        bits[:] = np.unpackbits(plane[block], axis=1)
        seen = np.cumsum(bits if one else 1 - bits, axis=1)
        return block * BLOCK + (seen <= (k - have[block])[:, None]).sum(1)

    def access(self, places: Sequence[int]) -> np.ndarray:
        """The ids at places."""
        i, out = np.asarray(places, np.int64), np.zeros(len(places), np.int64)
        for level, plane in enumerate(self.planes):
            bit = (plane[i // 8] >> (7 - i % 8).astype(np.uint8) & 1).astype(bool)
            ones = self._rank1(level, i)
            i = np.where(bit, self.zeros[level] + ones, i - ones)
            out = out * 2 + bit
        return out

    def _range(self, symbol: int, lo: int, hi: int) -> tuple[int, int]:
        ends = np.array([lo, hi], np.int64)
        if symbol >> len(self.planes):
            return 0, 0
        for level in range(len(self.planes)):
            ones = self._rank1(level, ends)
            ends = self.zeros[level] + ones if symbol >> (len(self.planes) - 1 - level) & 1 else ends - ones
        return int(ends[0]), int(ends[1])

    def count(self, symbol: int, lo: int = 0, hi: int | None = None) -> int:
        """How often an id stands in [lo, hi)."""
        a, b = self._range(symbol, lo, self.n if hi is None else hi)
        return b - a

    def occurrences(self, symbol: int, lo: int = 0, hi: int | None = None) -> np.ndarray:
        """The places of an id in [lo, hi), ascending."""
        a, b = self._range(symbol, lo, self.n if hi is None else hi)
        i = np.arange(a, b)
        for level in reversed(range(len(self.planes))):
            one = bool(symbol >> (len(self.planes) - 1 - level) & 1)
            i = self._select(level, i - self.zeros[level] if one else i, one)
        return i

    def decode(self) -> np.ndarray:
        """All ids: the partings undone from the last plane to the first."""
        out = np.zeros(self.n, np.uint16 if len(self.planes) <= 16 else np.uint32)
        for level in reversed(range(len(self.planes))):
            bit = np.unpackbits(self.planes[level], count=self.n).astype(bool)
            up = np.empty_like(out)
            up[~bit] = out[: self.zeros[level]]
            up[bit] = out[self.zeros[level] :] | out.dtype.type(1 << (len(self.planes) - 1 - level))
            out = up
        return out


def pack(matrix: WaveletMatrix, doc_ids: pa.Array, lengths: np.ndarray) -> bytes:
    """One file: magic, header length, JSON header, then compressed sections (document table, planes, ranks)."""
    nulls = np.array(doc_ids.is_null().to_pylist(), np.uint8)
    ids = np.asarray(doc_ids.fill_null(0).to_numpy(zero_copy_only=False), np.int64)
    parts = [ids.tobytes(), nulls.tobytes(), lengths.astype("<i8").tobytes()]
    parts += [p.tobytes() for p in matrix.planes] + [r.astype("<i8").tobytes() for r in matrix.ranks]
    small = [pa.compress(x, codec="zstd", asbytes=True) for x in parts]
    head = {"n": matrix.n, "zeros": matrix.zeros, "raw": [len(x) for x in parts], "packed": [len(x) for x in small]}
    head_b = json.dumps(head).encode()
    return MAGIC + struct.pack("<I", len(head_b)) + head_b + b"".join(small)


def unpack(data: bytes) -> tuple[WaveletMatrix, pa.Array, np.ndarray]:
    if data[: len(MAGIC)] != MAGIC:
        raise ValueError("no wavelet matrix file")
    (n_head,) = struct.unpack_from("<I", data, len(MAGIC))
    at = len(MAGIC) + 4
    head = json.loads(data[at : at + n_head])
    at += n_head
    parts = []
    for size, packed in zip(head["raw"], head["packed"]):
        parts.append(pa.decompress(data[at : at + packed], size, codec="zstd", asbytes=True) if size else b"")
        at += packed
    ids = pa.array(np.frombuffer(parts[0], np.int64), mask=np.frombuffer(parts[1], np.uint8).astype(bool))
    bits = len(head["zeros"])
    planes = [np.frombuffer(x, np.uint8) for x in parts[3 : 3 + bits]]
    ranks = [np.frombuffer(x, "<i8") for x in parts[3 + bits :]]
    return WaveletMatrix(head["n"], head["zeros"], planes, ranks), ids, np.frombuffer(parts[2], "<i8")


def _classes() -> np.ndarray:
    """Class of each code point below 0x500: 0 letter, 1 number, 2 other, 3 white space."""
    import regex

    kinds = [regex.compile(k) for k in (r"\p{L}", r"\p{N}", r"[^\s\p{L}\p{N}]")]
    return np.array([next((k for k, r in enumerate(kinds) if r.match(chr(c))), 3) for c in range(0x500)], np.uint8)


def piece_starts(buf: np.ndarray, fresh: np.ndarray, classes: np.ndarray) -> np.ndarray:
    """First bytes of the pieces that the vocabulary's pattern parts texts into.

    buf: UTF-8 bytes of texts whose characters lie below U+0500 and whose white space is ASCII; fresh marks
    each text's first byte. A run of letters, numbers or other characters takes one blank before it; of a
    run of white space the last character stays apart when text follows; after a lone apostrophe the
    endings s, t, re, ve, m, ll and d go with it.
    """
    n = len(buf)
    kind = classes[buf]  # right for ASCII
    lead = np.flatnonzero(buf >= 0xC2)
    kind[lead] = classes[(buf[lead].astype(np.int64) & 0x1F) << 6 | buf[lead + 1] & 0x3F]
    kind[lead + 1] = kind[lead]
    run = fresh.copy()
    run[1:] |= kind[1:] != kind[:-1]
    space = kind == 3
    text_after_space = np.zeros(n, bool)  # first byte of a run after white space of the same text
    text_after_space[1:] = run[1:] & ~fresh[1:] & ~space[1:] & space[:-1]
    blank_before = np.zeros(n, bool)
    blank_before[1:] = ~fresh[1:] & (buf[:-1] == 32)
    start = run & (space | ~blank_before)
    start[:-1] |= text_after_space[1:]
    lone = np.flatnonzero((buf == 39) & run & ~blank_before)
    lone = lone[lone + 1 < n]
    lone = lone[run[lone + 1] & ~fresh[lone + 1] & (kind[lone + 1] == 0)]
    if len(lone):
        last = len(buf) - 1
        a, b = buf[lone + 1], buf[np.minimum(lone + 2, last)]
        same = (lone + 2 <= last) & ~fresh[np.minimum(lone + 2, last)]
        two = same & ((((a == 114) | (a == 118)) & (b == 101)) | ((a == 108) & (b == 108)))
        one = np.isin(a, np.frombuffer(b"stmd", np.uint8))
        hit = one | two
        start[lone[hit] + 1] = False
        after = (lone + np.where(one, 2, 3))[hit]
        after = after[after < n]
        start[after[~run[after]]] = True  # letters left of the run
    return np.flatnonzero(start)


class PieceTable:
    """Numbers of 64-bit hashes in an open-addressing table; all look-ups of a block at once.

    The table doubles before more than three quarters of its slots are taken, so there always is a free one.
    """

    def __init__(self, bits: int = 21):
        self.n = 0
        self._empty(bits)

    def _empty(self, bits: int) -> None:
        self.mask = np.uint64((1 << bits) - 1)
        self.keys, self.values = np.zeros(1 << bits, np.uint64), np.zeros(1 << bits, np.int32)

    def find(self, h: np.ndarray) -> np.ndarray:
        """The number of each hash, -1 for unknown ones."""
        slot = (h & self.mask).astype(np.int64)
        key = self.keys[slot]
        out = np.where(key == h, self.values[slot], np.int32(-1))
        live = np.flatnonzero((key != h) & (key != 0))
        while len(live):
            slot[live] = (slot[live] + 1) & int(self.mask)
            key = self.keys[slot[live]]
            hit = key == h[live]
            out[live[hit]] = self.values[slot[live[hit]]]
            live = live[~hit & (key != 0)]
        return out

    def add(self, h: np.ndarray) -> None:
        """Numbers distinct new hashes on from those known."""
        number = np.arange(self.n, self.n + len(h), dtype=np.int32)
        self.n += len(h)
        bits = len(self.keys).bit_length() - 1
        while 4 * self.n > 3 << bits:
            bits += 1
        if 1 << bits > len(self.keys):
            taken = self.keys != 0
            keys, values = self.keys[taken], self.values[taken]
            self._empty(bits)
            self._place(keys, values)
        self._place(h, number)

    def _place(self, h: np.ndarray, number: np.ndarray) -> None:
        slot = (h & self.mask).astype(np.int64)
        live = np.arange(len(h))
        while len(live):
            free = live[self.keys[slot[live]] == 0]
            own, first = np.unique(slot[free], return_index=True)
            placed = free[first]
            self.keys[own], self.values[own] = h[placed], number[placed]
            left = np.ones(len(h), bool)
            left[placed] = False
            live = live[left[live]]
            taken = live[self.keys[slot[live]] != 0]
            slot[taken] = (slot[taken] + 1) & int(self.mask)


class Encoder:
    """Ids of whole texts by a byte-level BPE file of the tokenizers library, with a memory for pieces.

    The tokenizer parts a text into pieces first and encodes each on its own. Texts of characters below
    U+0500 are parted here in blocks, and each distinct piece, found by a 64-bit hash and compared byte by
    byte, is encoded once; other texts, and texts that may hold a special token or odd white space, are
    encoded whole.
    """

    hashes = staticmethod(span_hashes)
    _made: dict[str, Encoder] = {}

    def __init__(self, path: str, most: int = 1_200_000):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer, self.most, self.classes = Tokenizer.from_file(path), most, _classes()
        self.bits = max(1, int(self.tokenizer.get_vocab_size() - 1).bit_length())
        self._forget()

    @classmethod
    def at(cls, path: str) -> Encoder:
        if path not in cls._made:
            cls._made[path] = cls(path)
        return cls._made[path]

    def _forget(self) -> None:
        self.known = PieceTable()
        self.flat, self.first = np.zeros(0, np.uint32), np.zeros(1, np.int64)
        self.bytes, self.place = np.zeros(0, np.uint8), np.zeros(1, np.int64)

    def _learn(self, buf: np.ndarray, start: np.ndarray, end: np.ndarray) -> None:
        """Encodes pieces and keeps their ids and bytes, numbered on from those kept."""
        found, sizes, text = [np.zeros(0, np.uint32)], [np.zeros(0, np.int64)], buf.tobytes()
        for at in range(0, len(start), 64):  # short lists are the fastest
            part = [text[a:b].decode() for a, b in zip(start[at : at + 64].tolist(), end[at : at + 64].tolist())]
            got = self.tokenizer.encode(part, is_pretokenized=True, add_special_tokens=False)
            found.append(np.array(got.ids, np.uint32))
            sizes.append(np.bincount(np.array(got.word_ids, np.int64), minlength=len(part)))
        self.flat = np.concatenate([self.flat, *found])
        self.first = np.concatenate([self.first, self.first[-1] + np.cumsum(np.concatenate(sizes))])
        size = end - start
        done = np.concatenate([[0], np.cumsum(size)])
        self.bytes = np.concatenate([self.bytes, buf[np.repeat(start - done[:-1], size) + np.arange(done[-1])]])
        self.place = np.concatenate([self.place, self.place[-1] + done[1:]])

    def _equal(self, buf: np.ndarray, start: np.ndarray, end: np.ndarray, k: np.ndarray) -> np.ndarray:
        """Whether each piece has the bytes of the known piece k."""
        size = end - start
        at, own, begin = eights(buf), eights(self.bytes), self.place[k]
        same = size == self.place[k + 1] - begin
        live, back = np.flatnonzero(same), 0
        while len(live):
            low = _LOW[np.minimum(size[live] - back, 8)]
            equal = (at[start[live] + back] ^ own[begin[live] + back]) & low == 0
            same[live[~equal]] = False
            back += 8
            live = live[equal & (size[live] > back)]
        return same

    def _blocks(self, buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of texts fit for parting here, and each text's number of ids."""
        if self.known.n > self.most:
            self._forget()
        sizes = np.diff(offsets)
        if not len(buf):
            return self.flat[:0], np.zeros(len(sizes), np.int64)
        fresh = np.zeros(len(buf), bool)
        fresh[offsets[:-1][sizes > 0]] = True
        start = piece_starts(buf, fresh, self.classes)
        end = np.append(start[1:], len(buf))
        h = self.hashes(buf, start, end) | np.uint64(1)
        k = self.known.find(h)
        unknown = np.flatnonzero(k < 0)
        if len(unknown):
            new, first = np.unique(h[unknown], return_index=True)
            at = unknown[first]
            self._learn(buf, start[at], end[at])
            self.known.add(new)
            k[unknown] = self.known.find(h[unknown])
        other = np.flatnonzero(~self._equal(buf, start, end, k))
        if len(other):  # the hash of another piece: numbers of their own, out of the table
            self._learn(buf, start[other], end[other])
            k[other] = np.arange(self.known.n, self.known.n + len(other))
            self.known.n += len(other)
        head, size = self.first[k], self.first[k + 1] - self.first[k]
        done = np.concatenate([[0], np.cumsum(size)])
        ids = self.flat[np.repeat(head - done[:-1], size) + np.arange(done[-1])]
        edge = done[np.searchsorted(start, offsets)]
        return ids, np.diff(edge)

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts of a column, 0 after each, and each text's length with that end; nulls are empty."""
        buf, offsets = raw(column)
        n = len(offsets) - 1
        odd = buf >= 0xD4
        if len(buf) > 1:
            odd[:-1] |= ((buf[:-1] == 60) & (buf[1:] == 124)) | ((buf[:-1] == 0xC2) & ((buf[1:] == 0x85) | (buf[1:] == 0xA0)))
        bad = np.zeros(n, bool)
        bad[np.searchsorted(offsets, np.flatnonzero(odd), "right") - 1] = True
        if not bad.any():
            ids, lengths = self._blocks(buf, offsets)
        else:
            plain = column.filter(pa.array(~bad))
            ids_plain, len_plain = self._blocks(*raw(plain))
            lengths = np.zeros(n, np.int64)
            lengths[~bad] = len_plain
            whole = [np.array(self.tokenizer.encode(column[int(i)].as_py(), add_special_tokens=False).ids, np.uint32) for i in np.flatnonzero(bad)]
            lengths[bad] = [len(x) for x in whole]
            ids = np.zeros(int(lengths.sum()), np.uint32)
            from_bad = np.repeat(bad, lengths)
            ids[~from_bad] = ids_plain
            ids[from_bad] = np.concatenate(whole)
        lengths = lengths + 1
        out = np.zeros(int(lengths.sum()), np.uint32)
        inner = np.ones(len(out), bool)
        inner[np.cumsum(lengths) - 1] = False
        out[inner] = ids
        return out, lengths


def write_shards(docs: DataFrame, folder: str, tokenizer: str, shard_tokens: int = 8_000_000, partitions: int | None = None) -> list:
    """Writes the ids of docs (doc_id, text) in ascending doc_id order; rows (part, seq, path, n_docs, n_tokens).

    A file ends at `shard_tokens` ids, or after one longer document. Each task attempt writes files of
    its own names, and only reported files count, so a lost executor leaves no wrong shard.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        store, root = pafs.FileSystem.from_uri(folder)
        encoder = Encoder.at(tokenizer)
        ids: list[np.ndarray] = []
        docs_: list[pa.Array] = []
        lengths: list[np.ndarray] = []
        seq = 0

        def close() -> pa.RecordBatch:
            nonlocal ids, docs_, lengths, seq
            own = pa.concat_arrays(docs_)
            tokens = np.concatenate(ids)
            matrix = WaveletMatrix.build(tokens, encoder.bits)
            path = f"{root}/part-{task.partitionId():05d}-{task.taskAttemptId()}-{seq:04d}.wvm"
            store.create_dir(root, recursive=True)
            with store.open_output_stream(path) as f:
                f.write(pack(matrix, own, np.concatenate(lengths)))
            row = [task.partitionId(), seq, path, len(own), len(tokens)]
            ids, docs_, lengths, seq = [], [], [], seq + 1
            return pa.RecordBatch.from_arrays(
                [pa.array([x], t) for x, t in zip(row, (pa.int32(), pa.int32(), pa.string(), pa.int64(), pa.int64()))],
                names=["part", "seq", "path", "n_docs", "n_tokens"],
            )

        held = 0
        for whole in batches:
            for batch in slices(whole, "text"):
                got, sizes = encoder.encode(batch.column("text"))
                ids.append(got)
                docs_.append(batch.column("doc_id"))
                lengths.append(sizes)
                held += len(got)
                if held >= shard_tokens:
                    yield close()
                    held = 0
        if docs_:
            yield close()

    parts = partitions or shuffle_partitions(docs.sparkSession)
    ordered = docs.repartitionByRange(parts, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    rows = ordered.mapInArrow(run, "part int, seq int, path string, n_docs long, n_tokens long").collect()
    return sorted(rows, key=lambda r: (r["part"], r["seq"]))


def read_shards(spark: SparkSession, files: list, folder: str) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of each document, from the files."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, _ = pafs.FileSystem.from_uri(folder)
        for batch in batches:
            for path, base in zip(batch.column("path").to_pylist(), batch.column("base").to_pylist()):
                with store.open_input_stream(path) as f:
                    matrix, ids, lengths = unpack(f.read())
                tokens = matrix.decode().astype("<u4")
                ends = np.cumsum(lengths)
                crc = [zlib.crc32(tokens[e - n : e].data) for e, n in zip(ends, lengths)]
                yield pa.RecordBatch.from_arrays(
                    [ids, pa.array(base + ends - lengths), pa.array(lengths), pa.array(crc, pa.int64())],
                    names=["doc_id", "start", "n_tokens", "ids_crc32"],
                )

    base, rows = 0, []
    for r in files:
        rows.append((r["path"], base))
        base += r["n_tokens"]
    listed = spark.createDataFrame(rows, "path string, base long").repartition(max(1, min(len(rows), 4 * shuffle_partitions(spark))))
    return listed.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_files(docs: DataFrame, tokenizer: str | None = None, id_col: str = "doc_id", text_col: str = "text", **limits) -> DataFrame:
    """Writes docs as token shards and reads them back: doc_id, start, n_tokens, ids_crc32 of each row.

    Null texts are empty; every document ends with id 0. A null id comes first; rows that repeat an id
    follow each other in order of their text; an empty table gives no files and no rows; other columns
    are not read.
    """
    if tokenizer is None:
        import public_tokenizers

        tokenizer = public_tokenizers.path("byte_bpe_50k.json")
    ws = Workspace(docs.sparkSession, "token-shards")
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    files = write_shards(texts, f"{ws.root}/shards", tokenizer, **limits)
    return read_shards(docs.sparkSession, files, f"{ws.root}/shards")
