"""Reading and writing tables."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, functions as F


def load(spark: SparkSession, sf_dir: str, name: str, cols: Sequence[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def load_any(spark: SparkSession, path: str, kind: str, schema: str | None = None, **options: str) -> DataFrame:
    """csv, json, orc, parquet or text; a schema spares a scan for inference."""
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def save_any(df: DataFrame, path: str, kind: str, mode: str = "overwrite", **options: str) -> None:
    df.write.format(kind).mode(mode).options(**options).save(path)


def read_libsvm(spark: SparkSession, path: str) -> DataFrame:
    """(y, feats) of lines `label name:value name:value`; names stay strings, so the feature space is open."""
    words = F.split(F.trim("value"), r"\s+")
    pairs = F.filter(F.slice(words, F.lit(2), F.size(words)), lambda w: w.contains(":"))
    feats = F.transform(
        pairs, lambda w: F.struct(F.substring_index(w, ":", 1).alias("f"), F.substring_index(w, ":", -1).cast("double").alias("v"))
    )
    return spark.read.text(path).filter(F.trim("value") != "").select(words[0].cast("double").alias("y"), feats.alias("feats"))


def write_libsvm(df: DataFrame, path: str) -> None:
    """Writes (y, feats) as text lines."""
    pair = F.transform("feats", lambda x: F.concat_ws(":", x["f"], x["v"].cast("string")))
    df.select(F.concat_ws(" ", F.col("y").cast("string"), F.array_join(pair, " ")).alias("value")).write.mode("overwrite").text(path)


def save_bucketed(df: DataFrame, table: str, buckets: int, key: str = "rid") -> None:
    """A table in which rows of a key share a bucket, so that joins of such tables by the key need no exchange."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)


def stream_events(spark: SparkSession, folder: str, schema, files: int | None = 1) -> DataFrame:
    """A file stream of events with ts as timestamp; without `files` all that are there make one batch."""
    raw = spark.readStream.schema(schema)
    raw = (raw.option("maxFilesPerTrigger", files) if files else raw).parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))
