"""Sharding by longest-processing-time scheduling: groups stay together and go, largest first, to the
least-loaded shard through a heap.

The heap runs on two levels, so that no task or driver holds all groups. Groups above a share of the total
(a bounded number) are items of their own. The others fall into cells by hash; each cell deals its groups,
largest first, to as many bins as there are shards through a heap of its own. The driver then deals bins
and large groups to the shards through one heap.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ._store import Workspace, shuffle_partitions


def lpt(sizes: np.ndarray, bins: int) -> np.ndarray:
    """The bin of each item: in order of size, largest first, ties by place, to the least-loaded bin."""
    heap = [(0, b) for b in range(bins)]
    out = np.zeros(len(sizes), np.int64)
    for i in np.argsort(-sizes, kind="stable").tolist():
        load, b = heap[0]
        out[i] = b
        heapq.heapreplace(heap, (load + int(sizes[i]), b))
    return out


def _deal_cells(groups: DataFrame, bins: int) -> DataFrame:
    """(cell, bin, g1, g2, size) of groups (cell, g1, g2, size), partitioned by cell."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        table = pa.Table.from_batches(held).sort_by([("cell", "ascending"), ("g1", "ascending"), ("g2", "ascending")])
        cell, size = table.column("cell").to_numpy(), table.column("size").to_numpy()
        at = np.concatenate([[0], np.flatnonzero(cell[1:] != cell[:-1]) + 1, [len(cell)]])
        bin_ = np.concatenate([lpt(size[a:b], bins) for a, b in zip(at[:-1], at[1:])])
        yield from table.append_column("bin", pa.array(bin_, pa.int32())).to_batches(max_chunksize=50_000)

    return groups.mapInArrow(run, "cell int, g1 long, g2 long, size long, bin int")


def lpt_shards(
    docs: DataFrame,
    n_shards: int,
    id_col: str = "doc_id",
    text_col: str = "text",
    overhead: int = 16,
    large_share: int = 64,
    cell_groups: int = 1_000_000,
) -> DataFrame:
    """doc_id, size, text_crc32, shard and slot of each row; rows of equal text share a shard.

    size is the UTF-8 length plus `overhead`. Null texts form one group, empty texts another; a null id
    and repeated rows are placed like others; an empty table gives no rows; other columns are not read.
    Slots count from 0 in each shard without a gap. A group of more than total / (n_shards * large_share)
    bytes is an item of its own; there are fewer than n_shards * large_share of them. A cell holds about
    `cell_groups` groups at most, as rows of 28 bytes.
    """
    spark = docs.sparkSession
    ws = Workspace(spark, "sharding")
    text = F.col(text_col)
    digest = F.md5(F.coalesce(text, F.lit("")))  # two halves of it and null-ness name a group
    half = lambda at: F.conv(F.substring(digest, at, 15), 16, 10).cast("long")
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        (F.coalesce(F.octet_length(text), F.lit(0)) + overhead).cast("long").alias("size"),
        F.crc32(F.coalesce(text, F.lit(""))).alias("text_crc32"),
        F.when(text.isNull(), F.lit(-1)).otherwise(half(1)).alias("g1"),
        half(16).alias("g2"),
    )
    rows = ws.save(rows.withColumn("row", F.monotonically_increasing_id()), "rows")
    groups = rows.groupBy("g1", "g2").agg(F.sum("size").alias("size"))
    total, n_groups = groups.agg(F.sum("size"), F.count(F.lit(1))).first()
    large_from = (total or 0) / (n_shards * large_share)
    cells = max(shuffle_partitions(spark), -(-n_groups // cell_groups))
    groups = groups.withColumn("cell", F.pmod(F.xxhash64("g1", "g2"), F.lit(cells)).cast("int"))
    small = groups.filter(F.col("size") < large_from).select("cell", "g1", "g2", "size")
    binned = ws.save(_deal_cells(small.repartition(cells, "cell"), n_shards), "binned")
    large = groups.filter(F.col("size") >= large_from).select("g1", "g2", "size").orderBy("g1", "g2").collect()
    bins = binned.groupBy("cell", "bin").agg(F.sum("size").alias("size")).orderBy("cell", "bin").collect()
    shard = lpt(np.array([r["size"] for r in large] + [r["size"] for r in bins], np.int64), n_shards).tolist()

    own = spark.createDataFrame([(r["g1"], r["g2"], s) for r, s in zip(large, shard)], "g1 long, g2 long, shard int")
    of_bin = spark.createDataFrame([(r["cell"], r["bin"], s) for r, s in zip(bins, shard[len(large) :])], "cell int, bin int, shard int")
    placed_small = rows.join(F.broadcast(own), ["g1", "g2"], "left_anti").join(
        binned.join(F.broadcast(of_bin), ["cell", "bin"]).select("g1", "g2", "shard"), ["g1", "g2"]
    )
    placed = rows.join(F.broadcast(own), ["g1", "g2"]).unionByName(placed_small)
    parts = max(shuffle_partitions(spark), 1)
    placed = ws.save(
        placed.select("row", "doc_id", "size", "text_crc32", "shard", F.pmod(F.xxhash64("row"), F.lit(parts)).alias("part")), "placed"
    )
    # slots: a running number in each (part, shard), after the rows of the shard in earlier parts
    counts = placed.groupBy("shard", "part").agg(F.count(F.lit(1)).alias("n"))
    earlier = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("shard", "part", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("base"))
    within = Window.partitionBy("part", "shard").orderBy("doc_id", "row")
    return (
        placed.withColumn("nth", F.row_number().over(within))
        .join(F.broadcast(base), ["shard", "part"])  # at most parts x shards rows
        .select("doc_id", "size", "text_crc32", "shard", (F.col("base") + F.col("nth") - 1).cast("long").alias("slot"))
    )
