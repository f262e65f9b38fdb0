"""Quality rules: rule failures aggregated by host, shrunk with an empirical beta prior, joined back."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from ._store import Workspace
from ._text import SPACE, raw, slices, windows, words

SYMBOLS = np.zeros(256, bool)
SYMBOLS[np.frombuffer(b"#*$%&|<>", np.uint8)] = True  # fixed values: the counted symbols

MEASURES = T.StructType(
    [T.StructField(c, T.LongType()) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
)


def _repeat_words(hashes: np.ndarray, width: int) -> int:
    """Words inside windows of `width` words that occur at least twice."""
    found = windows(hashes, width)
    if len(found) < 2:
        return 0
    _, inverse, counts = np.unique(found, return_inverse=True, return_counts=True)
    twice = counts[inverse] > 1
    if not twice.any():
        return 0
    edge = np.zeros(len(hashes) + 1, np.int64)
    edge[:-width][twice] += 1
    edge[width:][twice] -= 1
    return int((np.cumsum(edge) > 0).sum())


def measure(column: pa.Array, width: int = 8) -> dict[str, np.ndarray]:
    """The rule measures of each text; a null text has none of anything."""
    buf, offsets = raw(column)
    n = len(offsets) - 1
    _, _, hashes, at = words(buf, offsets, fold=False)
    char_sum = np.concatenate([[0], np.cumsum(((buf & 0xC0) != 0x80) & ~SPACE[buf])])
    symbol_sum = np.concatenate([[0], np.cumsum(SYMBOLS[buf])])
    text = buf.tobytes()
    dup, repeat = np.zeros(n, np.int64), np.zeros(n, np.int64)
    for i in range(n):
        if at[i + 1] - at[i] > width:
            repeat[i] = _repeat_words(hashes[at[i] : at[i + 1]], width)
        lines = [x for x in text[offsets[i] : offsets[i + 1]].split(b"\n") if x.strip(b" \t\n\v\f\r")]
        dup[i] = len(lines) - len(set(lines))
    return {
        "n_words": np.diff(at),
        "word_chars": char_sum[offsets[1:]] - char_sum[offsets[:-1]],
        "n_symbols": symbol_sum[offsets[1:]] - symbol_sum[offsets[:-1]],
        "n_dup_lines": dup,
        "n_repeat_words": repeat,
    }


def text_measures(df: DataFrame, text_col: str, keep: list[str]) -> DataFrame:
    """The columns `keep` and the measures of the text; one row for each row."""
    schema = T.StructType([*df.select(*keep).schema.fields, *MEASURES.fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, text_col):
                got = measure(batch.column(text_col))
                cols = [batch.column(c) for c in keep] + [pa.array(got[f.name]) for f in MEASURES.fields]
                yield pa.RecordBatch.from_arrays(cols, names=[f.name for f in schema.fields])

    return df.select(*keep, F.col(text_col)).mapInArrow(run, schema)


def base_rule(min_words: int = 20, most_repeat: int = 30) -> F.Column:
    return (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > most_repeat * F.col("n_words"))


def more_rules() -> dict[str, F.Column]:
    """Rules beside the base rule; they count towards a host's verdict only."""
    words_ = F.greatest(F.col("n_words"), F.lit(1))
    return {
        "odd_words": (F.col("word_chars") < 2 * words_) | (F.col("word_chars") > 14 * words_),
        "symbols": 10 * F.col("n_symbols") > words_,
        "dup_lines": F.col("n_dup_lines") >= 10,
    }


def host_verdicts(measured: DataFrame, host_col: str, most_rate: float, least_bound: float, times: float, most_strength: float) -> DataFrame:
    """A row for each host: documents, failures, shrunk failure rate and verdict.

    The prior of the hosts' failure rates is a beta distribution fitted by moments over the hosts, each
    with a weight of one. With m and v the mean and variance of the rates, less the mean binomial variance
    of a rate, its strength is m(1-m)/v - 1, held between 1 and `most_strength` documents: hosts that are
    alike give no upper limit of their own. The posterior of a host is a beta distribution with mean
    (failures + strength*m) / (documents + strength). A host is rejected when the posterior mean less two
    posterior deviations is above `times` the prior mean, a bound held between `least_bound` and `most_rate`.
    """
    by_host = measured.groupBy(F.col(host_col).alias("host")).agg(
        F.count(F.lit(1)).alias("n"), F.sum(F.col("failed").cast("long")).alias("bad")
    )
    rate = F.col("bad") / F.col("n")
    prior = by_host.agg(F.avg(rate).alias("m"), F.var_pop(rate).alias("v"), F.avg(rate * (1 - rate) / F.col("n")).alias("noise"))
    spare = F.greatest(F.col("v") - F.col("noise"), F.lit(1e-9))
    strength = F.least(F.greatest(F.col("m") * (1 - F.col("m")) / spare - 1, F.lit(1.0)), F.lit(float(most_strength)))
    prior = prior.select("m", strength.alias("strength"))
    shrunk = (F.col("bad") + F.col("strength") * F.col("m")) / (F.col("n") + F.col("strength"))
    rate = F.col("host_rate")
    sure = rate - 2 * F.sqrt(rate * (1 - rate) / (F.col("n") + F.col("strength") + 1))
    bound = F.least(F.greatest(times * F.col("m"), F.lit(least_bound)), F.lit(most_rate))
    return (
        by_host.join(F.broadcast(prior))  # one row
        .withColumn("host_rate", shrunk)
        .select("host", "n", "bad", "host_rate", (sure <= bound).alias("host_ok"))
    )


def host_quality(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    host_col: str = "source",
    most_rate: float = 0.5,
    least_bound: float = 0.25,
    times: float = 3.0,
    most_strength: float = 1000.0,
    small_hosts: int = 100_000,
) -> DataFrame:
    """Measures, base rule and verdict of each document.

    Every row of `docs` gives one row, repeated rows too. A null text has no words and fails; a null
    host is a host of its own; an empty table gives no rows; other columns are not read. A document
    is kept when it passes the base rule and its host is not rejected by `host_verdicts` over the base
    rule and `more_rules`. Host rows are counted: at most `small_hosts` of them are broadcast, more are
    joined by shuffle. Equal rates tie at the bound and are kept; a text is measured in one task, with work
    arrays of about 30 bytes for each of its bytes.
    """
    ws = Workspace(docs.sparkSession, "host-rules")
    df = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(host_col).alias("host_in"))
    fails = base_rule()
    measured = text_measures(df, "text", ["doc_id", "host_in"]).withColumn("base_failed", fails)
    any_rule = F.col("base_failed")
    for rule in more_rules().values():
        any_rule = any_rule | rule
    measured = ws.save(measured.withColumn("failed", any_rule), "measured")
    hosts = ws.save(host_verdicts(measured, "host_in", most_rate, least_bound, times, most_strength), "hosts")
    side = F.broadcast(hosts) if hosts.count() <= small_hosts else hosts
    return measured.join(side, F.col("host_in").eqNullSafe(F.col("host")), "left").select(
        "doc_id",
        *[f.name for f in MEASURES.fields],
        "base_failed",
        (~F.col("base_failed") & F.coalesce("host_ok", F.lit(True))).alias("kept"),
        "host_rate",
    )
