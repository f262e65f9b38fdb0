"""A corpus pipeline of five stages: quality rules, near-dedup, decontamination, mixing, token shards.

Each stage takes (spark, docs, sf_dir), works on all rows that the one before kept and returns the columns
of documents; the last one returns what it reads back from the token files.
"""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession, functions as F

from softsplit.llm._store import Workspace
from softsplit.llm.decontaminate import contamination
from softsplit.llm.host_rules import host_quality
from softsplit.llm.mixing import mix
from softsplit.llm.near_dedup import near_components
from softsplit.llm.token_shards import token_files


def _keyed(docs: DataFrame, name: str) -> DataFrame:
    """The rows of a table as read from Parquet with a number of their own, row_key: file, then row of the file.

    Every read finds the same numbers. Rows that come from no file are stored first.
    """
    try:
        paths = docs.select(F.col("_metadata.file_path").alias("file")).distinct().collect()
    except AnalysisException:
        docs = Workspace(docs.sparkSession, name).save(docs, "rows")
        paths = docs.select(F.col("_metadata.file_path").alias("file")).distinct().collect()
    files = docs.sparkSession.createDataFrame([(p, i) for i, p in enumerate(sorted(r["file"] for r in paths))], "file string, nth long")
    placed = docs.select("*", F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("nth_row"))
    key = F.shiftleft("nth", 40) + F.col("nth_row")
    return placed.join(F.broadcast(files), "file").select(*docs.columns, key.alias("row_key"))


def _without(keyed: DataFrame, rejected: DataFrame) -> DataFrame:
    """Rows whose own number is not in doc_id of rejected; what befalls other rows of their id does not count."""
    return keyed.join(rejected.select(F.col("doc_id").alias("row_key")), "row_key", "left_anti").drop("row_key")


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    keyed = _keyed(docs, "quality")
    return _without(keyed, host_quality(keyed, id_col="row_key").filter(~F.col("kept")))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component the row of the smallest id stays, null ids last and equal ids by row number."""
    keyed = _keyed(docs, "near-dedup-rows")
    found = near_components(keyed, id_col="row_key").select(F.col("doc_id").alias("row_key"), "component_id")
    ids = keyed.select("row_key", F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "row_key").alias("place"))
    placed = Workspace(spark, "near-dedup-found").save(found.join(ids, "row_key"), "placed")
    first = placed.groupBy("component_id").agg(F.min("place").alias("first"), F.count(F.lit(1)).alias("n"))
    first = first.filter("n > 1").select("component_id", F.col("first.row_key").alias("stays"))
    return _without(keyed, placed.join(first, "component_id").filter("row_key != stays").select(F.col("row_key").alias("doc_id")))


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    keyed = _keyed(docs, "decontamination")
    return _without(keyed, contamination(keyed, benchmark, id_col="row_key").filter("contaminated"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row stands in the mix as often as it is copied, and not at all without a copy."""
    keyed = _keyed(docs, "mixing-rows")
    copies = mix(keyed, carry=["row_key"]).filter("copies > 0").select("row_key", "copies")
    taken = keyed.join(copies, "row_key")
    return taken.withColumn("nth_copy", F.explode(F.sequence(F.lit(1).cast("long"), "copies"))).select(*docs.columns)


def token_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return token_files(docs)


STAGES = [
    ("quality_rules", quality),
    ("near_dedup", near_dedup),
    ("decontamination", decontaminate),
    ("mixing", mixing),
    ("token_shards", token_shards),
]

#: Pivotal rounding draws by a hash that SQL engines do not share; the pipeline is tested against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ws = Workspace(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = ws.save(stage(spark, docs, sf_dir), name)
    return docs
