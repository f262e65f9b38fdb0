"""The shared store of intermediate tables, as the operators use it."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..store import Workspace, shared_dir

__all__ = ["Workspace", "shared_dir", "shuffle_partitions"]


def shuffle_partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))
