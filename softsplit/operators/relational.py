"""Relational operators that the methods, experiments and reports need."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window, functions as F

#: Rows of a side that may be broadcast without looking at its size further.
SMALL = 1_000_000


def attach_dimension(fact: DataFrame, dim: DataFrame, on: str | Column, small: int = SMALL) -> DataFrame:
    """Inner join of a fact with a dimension; it is broadcast when it has at most `small` rows, which is counted."""
    return fact.join(F.broadcast(dim) if dim.limit(small + 1).count() <= small else dim, on)


def join_side_state(x: DataFrame, state: DataFrame, key: str = "rid", hint: str = "merge") -> DataFrame:
    """Features with their side table of scores; no exchange when both are bucketed alike."""
    return x.join(state.hint(hint), key)


def keep_ids(df: DataFrame, ids: DataFrame, key: str) -> DataFrame:
    return df.join(ids, key, "left_semi")


def drop_ids(df: DataFrame, ids: DataFrame, key: str) -> DataFrame:
    return df.join(ids, key, "left_anti")


def replicate(df: DataFrame, k: int, name: str = "copy") -> DataFrame:
    """Each row k times, numbered."""
    return df.withColumn(name, F.explode(F.sequence(F.lit(0), F.lit(k - 1))))


def assign_bins(df: DataFrame, value: str, edges: Sequence[float], name: str = "bin") -> DataFrame:
    """The number of edges at or below each value, as an expression (a range join with few edges)."""
    table = F.array(*[F.lit(float(e)) for e in edges])
    return df.withColumn(name, F.size(F.filter(table, lambda e: e <= F.col(value))))


def join_within(a: DataFrame, b: DataFrame, a_time: str, b_time: str, seconds: int, by: Sequence[str]) -> DataFrame:
    """Pairs of rows of equal `by` with b_time in [a_time, a_time + seconds], by equi-join on time buckets."""
    bucket = lambda c, shift=0: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / seconds).cast("long") + shift
    left = a.withColumn("bucket_", F.explode(F.array(bucket(a_time), bucket(a_time, 1))))
    right = b.withColumn("bucket_", bucket(b_time))
    gap = F.unix_timestamp(F.col(b_time).cast("timestamp")) - F.unix_timestamp(F.col(a_time).cast("timestamp"))
    return left.join(right, [*by, "bucket_"]).filter((gap >= 0) & (gap <= seconds)).drop("bucket_")


def asof_join(left: DataFrame, right: DataFrame, on: str, by: Sequence[str], value: str) -> DataFrame:
    """left with the `value` of the last right row at or before `on`, within `by`: one sort, no pair join."""
    l_ = left.withColumns({"side_": F.lit(1), "v_": F.lit(None).cast(right.schema[value].dataType)})
    extra = [c for c in left.columns if c not in (*by, on)]
    r_ = right.select(*by, on, *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in extra], F.lit(0).alias("side_"), F.col(value).alias("v_"))
    past = Window.partitionBy(*by).orderBy(on, "side_").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = l_.unionByName(r_).withColumn("last_" + value, F.last("v_", ignorenulls=True).over(past))
    return both.filter("side_ = 1").drop("side_", "v_")


def feature_pairs(feats: DataFrame) -> DataFrame:
    from ..baselines.bundling import conflicts

    return conflicts(feats)


def feature_count(feats: DataFrame, exact: bool = True) -> DataFrame:
    return feats.agg((F.count_distinct("f") if exact else F.approx_count_distinct("f")).alias("features"))


def score_report(df: DataFrame, dims: Sequence[str], value: str, mode: str = "cube") -> DataFrame:
    """Count and sum of `value` by all subsets (cube) or prefixes (rollup) of dims, with grouping_id."""
    grouped = df.cube(*dims) if mode == "cube" else df.rollup(*dims)
    return grouped.agg(F.grouping_id().cast("long").alias("gid"), F.count(F.lit(1)).alias("n"), F.sum(value).alias("total"))


def vector_sum(df: DataFrame, vector: str, by: Sequence[str]) -> DataFrame:
    """(by, j, s): element-wise sums, combined before the shuffle."""
    return df.select(*by, F.posexplode(vector).alias("j", "v")).groupBy(*by, "j").agg(F.sum("v").alias("s"))


def top_scored(df: DataFrame, score: str, k: int, tie: str) -> DataFrame:
    return df.orderBy(F.col(score).desc(), tie).limit(k)


def top_per(df: DataFrame, by: str, score: str, k: int, tie: str) -> DataFrame:
    order = Window.partitionBy(by).orderBy(F.col(score).desc(), tie)
    return df.withColumn("place", F.row_number().over(order)).filter(F.col("place") <= k)


def page(df: DataFrame, order: Sequence[str], k: int, offset: int) -> DataFrame:
    return df.orderBy(*order).offset(offset).limit(k)


def set_op(a: DataFrame, b: DataFrame, kind: str) -> DataFrame:
    return {
        "union": a.unionByName, "intersect": a.intersect, "intersect_all": a.intersectAll, "except": a.subtract, "except_all": a.exceptAll,
    }[kind](b)


def drop_copies(df: DataFrame, cols: Sequence[str], order: str) -> DataFrame:
    """The first row of each set of equal columns."""
    first = Window.partitionBy(*cols).orderBy(order)
    return df.withColumn("nth_", F.row_number().over(first)).filter("nth_ = 1").drop("nth_")


def hash_sample(df: DataFrame, key: str, share: float, seed: int = 0) -> DataFrame:
    """Rows whose key hashes below a share; the same rows wherever they lie."""
    code = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), F.col(key).cast("string"))), 1, 8), 16, 10).cast("long")
    return df.filter(code < int(share * 4294967296))


def nnz_running(df: DataFrame, order: str, nnz: str) -> DataFrame:
    """(order, nnz, before): non-zeros before each row, through range partitions."""
    from ..functions.metrics import prefix_sum

    return prefix_sum(df.select(order, nnz), order, nnz, "before")


def nnz_batches(df: DataFrame, order: str, nnz: str, batches: int) -> DataFrame:
    """(order, nnz, batch): batches of about equal non-zeros; the budget is at least the largest row."""
    df = df.select(order, nnz).persist()
    budget = df.agg(F.greatest(F.max(nnz), F.ceil(F.sum(nnz) / batches))).first()[0] or 1
    return nnz_running(df, order, nnz).withColumn("batch", F.floor(F.col("before") / F.lit(int(budget))).cast("long")).drop("before")
