"""Feature assembly as Catalyst expressions, so pushdown and pruning reach the scan."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, functions as F, types as T

from .hashing import base_code


def as_double(df: DataFrame, name: str, impute: float = 0.0) -> Column:
    """A numeric, boolean, date or timestamp column as a double; null becomes `impute`."""
    kind = df.schema[name].dataType
    col = F.col(name)
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType, T.DateType)):
        col = F.unix_timestamp(col.cast("timestamp"))
    return F.coalesce(col.cast("double"), F.lit(float(impute)))


def dense_vector(df: DataFrame, columns: Sequence[str], impute: float = 0.0) -> Column:
    return F.array(*[as_double(df, c, impute) for c in columns])


def one_hot(columns: Sequence[str]) -> Column:
    """array<struct<f, v>> with one entry for each non-null column."""
    entries = [F.when(F.col(c).isNotNull(), F.struct(F.concat_ws("=", F.lit(c), F.col(c).cast("string")).alias("f"), F.lit(1.0).alias("v"))) for c in columns]
    return F.array_compact(F.array(*entries))


def crossed(first: str, second: str) -> Column:
    """The name of the cross of two key columns."""
    return F.concat_ws("&", F.concat_ws("=", F.lit(first), F.col(first).cast("string")), F.concat_ws("=", F.lit(second), F.col(second).cast("string")))


def tokens(text: Column) -> Column:
    """Lower-case words between blanks."""
    return F.filter(F.split(F.translate(F.lower(F.coalesce(text, F.lit(""))), "\n\t\r", "   "), " "), lambda w: w != "")


def word_set(text: Column) -> Column:
    """array<struct<f, v>> of the distinct words, value 1."""
    return F.transform(F.array_distinct(tokens(text)), lambda w: F.struct(w.alias("f"), F.lit(1.0).alias("v")))


def word_counts(text: Column) -> Column:
    """array<struct<f, v>> of the distinct words with their counts: lengths of the runs of the sorted words."""
    ordered = F.array_sort(tokens(text))
    nothing = F.array().cast("array<int>")
    heads = F.filter(F.sequence(F.lit(1), F.size(ordered)), lambda i: (i == 1) | (F.element_at(ordered, i) != F.element_at(ordered, F.greatest(i - 1, F.lit(1)))))
    heads = F.when(F.size(ordered) > 0, heads).otherwise(nothing)
    after = F.concat(F.slice(heads, 2, F.greatest(F.size(heads) - 1, F.lit(0))), F.array(F.size(ordered) + 1))
    return F.zip_with(heads, F.slice(after, 1, F.size(heads)), lambda a, b: F.struct(F.element_at(ordered, a).alias("f"), (b - a).cast("double").alias("v")))


def word_ngrams(text: Column, n: int) -> Column:
    words = tokens(text)
    last = F.size(words) - n + 1
    grams = F.transform(F.sequence(F.lit(1), last), lambda i: F.array_join(F.slice(words, i, n), " "))
    return F.when(last >= 1, grams).otherwise(F.array().cast("array<string>"))


def letter_shares(text: Column, letters: str = "abcdefghijklmnopqrstuvwxyz") -> Column:
    """Share of each letter among the characters of a text."""
    low = F.lower(F.coalesce(text, F.lit("")))
    size = F.greatest(F.length(low), F.lit(1)).cast("double")
    return F.array(*[(F.length(low) - F.length(F.replace(low, F.lit(c), F.lit("")))) / size for c in letters])


def strip_html(html: Column) -> Column:
    clean = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</\1>", " ")
    return F.regexp_replace(clean, r"<[^>]*>", " ")


def json_features(props: Column, keys: Sequence[str]) -> Column:
    parsed = F.from_json(props, T.MapType(T.StringType(), T.StringType()))
    entries = [F.when(parsed[k].isNotNull(), F.struct(F.concat(F.lit(k + "="), parsed[k]).alias("f"), F.lit(1.0).alias("v"))) for k in keys]
    return F.array_compact(F.array(*entries))


def coded(feats: Column, hash_fn: str = "xxh64") -> list[Column]:
    """codes and vals columns of array<struct<f, v>>: each name hashed once, here; the trainers only mix integers."""
    return [F.transform(feats, lambda x: base_code(x["f"], hash_fn)).alias("codes"), F.transform(feats, lambda x: x["v"]).alias("vals")]


def column_blocks(df: DataFrame, partitions: int) -> DataFrame:
    """(part, f, entries): features of each row partition with the rows that have them, from (rid, feats)."""
    part = F.pmod(F.xxhash64("rid"), F.lit(partitions)).cast("int").alias("part")
    long = df.select(part, "rid", F.explode("feats").alias("x")).select("part", "rid", "x.f", "x.v")
    return long.groupBy("part", "f").agg(F.array_sort(F.collect_list(F.struct("rid", "v"))).alias("entries"))
