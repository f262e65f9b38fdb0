"""Language identification of mixed texts.

Script ranges narrow each word's candidate languages, byte n-grams score the word for every candidate,
and Viterbi with a switching penalty labels the words, so that a text falls into spans of one language.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, functions as F

from ._text import raw, slices, words

#: First code points of Unicode ranges and the script that letters there belong to.
RANGES = [
    (0x0041, "Latin"), (0x0370, "Greek"), (0x0400, "Cyrillic"), (0x0530, "Armenian"), (0x0590, "Hebrew"),
    (0x0600, "Arabic"), (0x0700, "Other"), (0x0900, "Devanagari"), (0x0980, "Bengali"), (0x0A00, "Gurmukhi"),
    (0x0A80, "Gujarati"), (0x0B00, "Other"), (0x0B80, "Tamil"), (0x0C00, "Telugu"), (0x0C80, "Kannada"),
    (0x0D00, "Malayalam"), (0x0D80, "Other"), (0x0E00, "Thai"), (0x0E80, "Other"), (0x10A0, "Georgian"),
    (0x1100, "Hangul"), (0x1200, "Ethiopic"), (0x13A0, "Other"), (0x1E00, "Latin"), (0x1F00, "Greek"),
    (0x2000, "Other"), (0x3040, "Kana"), (0x3100, "Other"), (0x3400, "Han"), (0xA000, "Other"),
    (0xAC00, "Hangul"), (0xD7B0, "Other"), (0xF900, "Han"), (0xFB00, "Latin"), (0xFB13, "Other"), (0xFB50, "Arabic"),
    (0xFE00, "Other"), (0xFE70, "Arabic"), (0xFF00, "Other"), (0x20000, "Han"), (0x30000, "Other"),
]
SCRIPTS = sorted({s for _, s in RANGES})
_FIRST = np.array([c for c, _ in RANGES], np.int64)
_SCRIPT_BIT = np.array([1 << SCRIPTS.index(s) for _, s in RANGES], np.int64)
ORDERS = (2, 3, 4)
BUCKETS = 1 << 16
_ASCII_LETTER = np.zeros(256, bool)
_ASCII_LETTER[65:91] = _ASCII_LETTER[97:123] = True


@dataclass
class Model:
    languages: list[str]
    weights: np.ndarray  # (len(ORDERS) * BUCKETS, languages), log probabilities
    scripts: np.ndarray  # the bits of each language's scripts


def _grams(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the n-grams that end at each word byte (orders x bytes), and each word's first byte among them.

    An n-gram reaches back to one blank before its word at most.
    """
    sizes = ends - starts
    first = np.concatenate([[0], np.cumsum(sizes)])
    place = np.arange(first[-1]) - np.repeat(first[:-1], sizes)
    at = np.repeat(starts, sizes) + place
    v = buf[at].astype(np.uint32)
    gram = v.copy()
    for back in (1, 2, 3):
        older = np.where(place >= back, buf[np.maximum(at - back, 0)], 32).astype(np.uint32)
        gram |= np.where(place >= back - 1, older, 0).astype(np.uint32) << np.uint32(8 * back)
    out = np.empty((len(ORDERS), len(gram)), np.int32)
    for k, n in enumerate(ORDERS):
        part = gram if n == 4 else gram & np.uint32((1 << 8 * n) - 1)
        out[k] = (part * np.uint32(2654435761) >> np.uint32(16)).astype(np.int32) + k * BUCKETS
    return out, first


def _letters(buf: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each word: its letters (any character of a script range) and the bits of their scripts."""
    latin = 1 << SCRIPTS.index("Latin")
    letter = _ASCII_LETTER[buf].astype(np.int64)
    script = letter * latin
    lead = np.flatnonzero(buf >= 0xC0)
    if len(lead):
        more = np.pad(buf, (0, 3)).astype(np.int64)
        b0, b1, b2, b3 = (more[lead + k] for k in range(4))
        two, three = b0 < 0xE0, b0 < 0xF0
        code = np.where(
            two, (b0 & 0x1F) << 6 | b1 & 0x3F,
            np.where(three, (b0 & 0x0F) << 12 | (b1 & 0x3F) << 6 | b2 & 0x3F, (b0 & 7) << 18 | (b1 & 0x3F) << 12 | (b2 & 0x3F) << 6 | b3 & 0x3F),
        )
        is_letter = code >= 0xAA
        bits = _SCRIPT_BIT[np.maximum(np.searchsorted(_FIRST, code, "right") - 1, 0)]
        letter[lead] = is_letter
        script[lead] = bits * is_letter
    if not len(starts):
        return starts, starts
    return np.add.reduceat(letter, starts), np.bitwise_or.reduceat(script, starts)


def _prepared(batch: pa.RecordBatch) -> tuple[np.ndarray, ...]:
    buf, offsets = raw(pc.utf8_lower(batch.column("text")))
    starts, ends, _, at = words(buf, offsets)
    return buf, starts, ends, at


def train(labelled: DataFrame, least_script: float = 0.01, smooth: float = 0.5) -> Model:
    """Counts n-grams and scripts of all rows (text, lang) with a language; the model is bounded by languages x buckets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for whole in batches:
            for batch in slices(whole, "text"):
                buf, starts, ends, at = _prepared(batch)
                grams, first = _grams(buf, starts, ends)
                letters, bits = _letters(buf, starts)
                langs = np.array(batch.column("lang").to_pylist(), object)
                owner = np.repeat(np.arange(len(langs)), np.diff(at))
                for lang in set(langs):
                    has = sums.setdefault(lang, np.zeros(len(ORDERS) * BUCKETS + len(SCRIPTS), np.int64))
                    own = (langs == lang)[owner]
                    byte_own = np.repeat(own, np.diff(first))
                    for k in range(len(ORDERS)):
                        has[: -len(SCRIPTS)] += np.bincount(grams[k][byte_own], minlength=len(ORDERS) * BUCKETS)
                    for s in range(len(SCRIPTS)):
                        has[s - len(SCRIPTS)] += letters[own & (bits >> s & 1 > 0)].sum()
        for lang, has in sums.items():
            some = np.flatnonzero(has)
            yield pa.RecordBatch.from_arrays(
                [pa.array([lang] * len(some), pa.string()), pa.array(some, pa.int32()), pa.array(has[some])], names=["lang", "bucket", "n"]
            )

    counted = labelled.select("text", "lang").mapInArrow(run, "lang string, bucket int, n long")
    got = counted.groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toArrow()
    langs = sorted(set(got.column("lang").to_pylist()))
    table = np.zeros((len(ORDERS) * BUCKETS + len(SCRIPTS), len(langs)))
    if langs:
        codes = pc.index_in(got.column("lang"), pa.array(langs)).to_numpy()
        table[got.column("bucket").to_numpy(), codes] = got.column("n").to_numpy()
    letters = table[-len(SCRIPTS) :]
    share = letters / np.maximum(letters.sum(0), 1)
    scripts = ((share >= least_script) * (1 << np.arange(len(SCRIPTS)))[:, None]).sum(0).astype(np.int64)
    if not langs:
        return Model([], np.zeros((len(ORDERS) * BUCKETS, 0), np.float32), scripts)
    grams = table[: -len(SCRIPTS)].reshape(len(ORDERS), BUCKETS, len(langs)) + smooth
    weights = np.log(grams / grams.sum(1, keepdims=True)).astype(np.float32).reshape(-1, len(langs))
    return Model(langs, weights, scripts)


def word_scores(model: Model, buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(words x languages) mean log probabilities over the orders, summed over a word; and the words' letters.

    A language that does not use a word's scripts is no candidate, unless none does.
    """
    grams, first = _grams(buf, starts, ends)
    n = len(model.languages)
    total = np.zeros((grams.shape[1] + 1, n))
    for at in range(0, grams.shape[1], 1 << 20):
        part = model.weights[grams[:, at : at + (1 << 20)]].sum(0) / len(ORDERS)
        np.cumsum(part, axis=0, out=total[at + 1 : at + 1 + len(part)], dtype=np.float64)
        total[at + 1 : at + 1 + len(part)] += total[at]
    scores = (total[first[1:]] - total[first[:-1]]).astype(np.float32)
    letters, bits = _letters(buf, starts)
    scores[letters == 0] = 0
    fits = (bits[:, None] & ~model.scripts[None, :]) == 0
    fits[~fits.any(1)] = True
    scores[~fits] -= 1e4
    return scores, letters


def _run_paths(scores: np.ndarray, starts: np.ndarray, sizes: np.ndarray, penalty: float, free: bool):
    """Best scores (exit label x entry label x runs) of runs of words, and what traces paths back.

    With `free` there is no label before the run, and one entry. Runs must be given longest first.
    """
    n = scores.shape[1]
    entries = 1 if free else n
    best = np.zeros((n, entries, len(starts)), np.float32)
    back: list = []
    live = len(starts)
    for t in range(int(sizes[0]) if len(sizes) else 0):
        while sizes[live - 1] <= t:
            live -= 1
        gain = scores[starts[:live] + t].T[:, None, :]
        if t == 0:
            first = np.zeros((n, 1), np.float32) if free else np.where(np.eye(n, dtype=bool), 0, -penalty).astype(np.float32)
            best[:, :, :live] = first[:, :, None] + gain
            back.append(None)
            continue
        now = best[:, :, :live]
        top = now.max(0)
        head = np.zeros(top.shape, np.uint8 if n < 256 else np.uint16)
        for k in range(1, n):
            head[now[k] == top] = k
        top -= penalty
        back.append((head, top > now))
        np.maximum(now, top, out=now)
        now += gain
    return best, back


def _trace(back: list, sizes: np.ndarray, starts: np.ndarray, entry: np.ndarray, leave: np.ndarray, out: np.ndarray) -> None:
    state = leave.copy()
    live = np.searchsorted(-sizes, -np.arange(len(back)), "left")  # runs longer than t
    for t in reversed(range(len(back))):
        k = live[t]
        out[starts[:k] + t] = state[:k]
        if t:
            rows = np.arange(k)
            head, moved = back[t]
            state[:k] = np.where(moved[state[:k], entry[:k], rows], head[entry[:k], rows], state[:k])


def viterbi(scores: np.ndarray, at: np.ndarray, penalty: float, run: int = 512) -> np.ndarray:
    """The best labels of each sequence at[i]:at[i+1]; a change of label costs `penalty`.

    All sequences step together. Longer ones are cut into runs whose best scores for every entry and
    exit label are joined, which gives the same path as one pass.
    """
    labels = np.zeros(len(scores), np.int64)
    sizes = np.diff(at)
    short = np.flatnonzero((sizes > 0) & (sizes <= run))
    short = short[np.argsort(-sizes[short], kind="stable")]
    if len(short):
        best, back = _run_paths(scores, at[short], sizes[short], penalty, True)
        _trace(back, sizes[short], at[short], np.zeros(len(short), np.int64), best[:, 0].argmax(0), labels)
    long = np.flatnonzero(sizes > run)
    if not len(long):
        return labels
    cuts = [np.arange(at[i], at[i + 1], run) for i in long]
    owner = np.repeat(np.arange(len(long)), [len(c) for c in cuts])
    cuts = np.concatenate(cuts)
    lens = np.minimum(cuts + run, at[long + 1][owner]) - cuts
    order = np.argsort(-lens, kind="stable")
    best, back = _run_paths(scores, cuts[order], lens[order], penalty, False)
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    entry, leave = np.zeros(len(order), np.int64), np.zeros(len(order), np.int64)
    edges = np.searchsorted(owner, np.arange(len(long) + 1))
    for a, b in zip(edges[:-1], edges[1:]):
        into, ways = np.zeros(scores.shape[1]), []  # before the first run any label is as good
        for k in range(a, b):
            paths = into[None, :] + best[:, :, place[k]]
            ways.append(paths.argmax(1))
            into = paths.max(1)
        state = int(into.argmax())
        for k in reversed(range(a, b)):
            leave[place[k]] = state
            entry[place[k]] = state = int(ways[k - a][state])
    _trace(back, lens[order], cuts[order], entry, leave, labels)
    return labels


def label_texts(docs: DataFrame, model: Model, penalty: float = 6.0, spans: bool = False) -> DataFrame:
    """doc_id, lang_pred and score of each row of docs (doc_id, text), and on demand its spans.

    lang_pred is the language with most letters on the best path and score its share of the letters. A
    text that is null or has no letter, and any text where no language was learned, is `und` with score
    0. A span is a run of words of one language as (first word, words, language).
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = "doc_id long, lang_pred string, score double"
    schema += ", spans array<struct<word: int, words: int, lang: string>>" if spans else ""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        names = np.array([*model.languages, "und"], object)
        n = len(model.languages)
        for whole in batches:
            for batch in slices(whole, "text"):
                rows = batch.num_rows
                pred, score = np.full(rows, n), np.zeros(rows)
                found: list = [[] for _ in range(rows)]
                if n:
                    buf, starts, ends, at = _prepared(batch)
                    scores, letters = word_scores(model, buf, starts, ends)
                    labels = viterbi(scores, at, penalty)
                    owner = np.repeat(np.arange(rows), np.diff(at))
                    mass = np.bincount(owner * n + labels, weights=letters, minlength=rows * n).reshape(rows, n)
                    total = mass.sum(1)
                    some = total > 0
                    # characters of a script range are letters for the measure; whether a text has one is asked exactly
                    ascii_sum = np.concatenate([[0], np.cumsum(_ASCII_LETTER[buf])])
                    edges = np.append(starts, len(buf))[at]
                    sure = ascii_sum[edges[1:]] > ascii_sum[edges[:-1]]
                    for i in np.flatnonzero(~sure):
                        some[i] = any(map(str.isalpha, batch.column("text")[i].as_py() or ""))
                    if some.any():
                        top = mass.argmax(1)
                        pred[some] = top[some]
                        score[some] = np.where(total > 0, mass[np.arange(rows), top] / np.maximum(total, 1), 1.0 / n)[some]
                    if spans:
                        for i in range(rows):
                            own = labels[at[i] : at[i + 1]]
                            cuts = np.concatenate([[0], np.flatnonzero(own[1:] != own[:-1]) + 1, [len(own)]]) if len(own) else []
                            found[i] = [(int(a), int(b - a), names[own[a]]) for a, b in zip(cuts[:-1], cuts[1:])] if len(own) else []
                out = [batch.column("doc_id"), pa.array(names[pred], pa.string()), pa.array(score)]
                if spans:
                    kind = pa.list_(pa.struct([("word", pa.int32()), ("words", pa.int32()), ("lang", pa.string())]))
                    out.append(pa.array([[dict(zip(("word", "words", "lang"), s)) for s in x] for x in found], kind))
                yield pa.RecordBatch.from_arrays(out, names=["doc_id", "lang_pred", "score"] + ["spans"] * spans)

    return docs.select("doc_id", "text").mapInArrow(run, schema)


def crc_fold(id_col: Column, n: int) -> Column:
    """crc32 of the id's text modulo n; a null id falls into fold 0."""
    return F.coalesce(F.crc32(id_col.cast("string")) % n, F.lit(0))


def language_id(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", folds: int = 5, penalty: float = 6.0, spans: bool = False
) -> DataFrame:
    """doc_id, held_out, lang_pred and score: learned outside fold 0 of `folds`, predicted for every row.

    Rows with a null language or in fold 0 (null ids too) teach nothing; repeated rows count as often as
    they stand; an empty table gives no rows; other columns are not read.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"))
    learn = rows.filter((crc_fold(F.col("doc_id"), folds) != 0) & F.col("lang").isNotNull())
    got = label_texts(rows.select("doc_id", "text"), train(learn), penalty, spans)
    return got.withColumn("held_out", crc_fold(F.col("doc_id"), folds) == 0)
