"""Accuracy measures as DataFrame plans."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window, functions as F


def auc(df: DataFrame, score: str = "score", y: str = "y", by: tuple[str, ...] = (), ranged: bool = False) -> DataFrame:
    """(by, auc, positives, negatives); ties at mid-rank, null without both classes.

    Scores are counted first, so what is ranked are distinct scores. Without `by`, or if `ranged`, ranks come from
    prefix_sum, which ranges over partitions; else groups of `by` are ranked in a window each.
    """
    counted = df.filter(F.col(y).isNotNull()).groupBy(*by, F.col(score).alias("s")).agg(
        F.sum(F.col(y).cast("long")).alias("pos"), F.sum((1 - F.col(y)).cast("long")).alias("neg")
    )
    if by and not ranged:
        below = F.coalesce(F.sum("neg").over(Window.partitionBy(*by).orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        ranked = counted.withColumn("below", below)
    else:
        ranked = prefix_sum(counted.withColumn("at", F.struct(*by, "s")) if by else counted, "at" if by else "s", "neg", "below")
    won = F.sum(F.col("pos") * (2 * F.col("below") + F.col("neg")))  # twice the pairs won
    won -= 2 * F.min("below") * F.sum("pos")  # what lies before a group
    total = ranked.groupBy(*by).agg(won.alias("won"), F.sum("pos").alias("positives"), F.sum("neg").alias("negatives"))
    value = F.when((F.col("positives") > 0) & (F.col("negatives") > 0), F.col("won") / (2.0 * F.col("positives") * F.col("negatives")))
    return total.select(*by, value.alias("auc"), "positives", "negatives")


def prefix_sum(df: DataFrame, order: str, value: str, out: str, partitions: int | None = None) -> DataFrame:
    """The sum of `value` over rows strictly before each row in `order`, without a single-partition window.

    Rows are range-partitioned, summed within each range, and shifted by the totals of earlier ranges
    (one number for each range). Rows of equal order fall into one range.
    """
    return prefix_sums(df, order, {out: value}, partitions)


def prefix_sums(df: DataFrame, order: str, values: dict[str, str], partitions: int | None = None) -> DataFrame:
    """prefix_sum of several columns at once; values: name of the result -> column.

    The ranges stay cached, since the totals and the rows must see the same ones; Spark lets them go with
    the session's last reference or unpersist().
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = df.repartitionByRange(n, order).withColumn("range_no", F.spark_partition_id()).persist()
    totals = ranged.groupBy("range_no").agg(*[F.sum(v).alias(f"total_{o}") for o, v in values.items()])
    earlier = Window.orderBy("range_no").rowsBetween(Window.unboundedPreceding, -1)
    base = totals.select("range_no", *[F.coalesce(F.sum(f"total_{o}").over(earlier), F.lit(0)).alias(f"base_{o}") for o in values])
    within = Window.partitionBy("range_no").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    joined = ranged.join(F.broadcast(base), "range_no")  # one row for each range
    for o, v in values.items():
        joined = joined.withColumn(o, F.col(f"base_{o}") + F.coalesce(F.sum(v).over(within), F.lit(0)))
    return joined.drop("range_no", *[f"base_{o}" for o in values])


def average_precision(df: DataFrame, score: str = "score", y: str = "y", tie: str = "rid", by: tuple[str, ...] = ()) -> DataFrame:
    """(by, ap): mean over positives of the precision at their place, order score descending, then tie.

    Places and hits are numbered over all rows in ranges of (by, score, tie), so a class or a round is not
    one task's; what lies before a group is taken off again (a row for each group).
    """
    rows = df.filter(F.col(y).isNotNull()).select(
        F.struct(*by, (-F.col(score)).alias("down"), F.col(tie).alias("tie")).alias("at"), F.col(y).cast("long").alias("hit"), F.lit(1).cast("long").alias("one")
    )
    ranked = prefix_sums(rows, "at", {"place": "one", "hits": "hit"})
    group = [F.col(f"at.{c}").alias(c) for c in by]
    base = ranked.groupBy(*group).agg(F.min("place").alias("place0"), F.min("hits").alias("hits0"))
    positive = ranked.filter("hit = 1").select(*group, (F.col("place") + 1).alias("place"), (F.col("hits") + 1).alias("hits"))
    joined = positive.join(F.broadcast(base), [*by]) if by else positive.crossJoin(F.broadcast(base))  # one row without groups
    return joined.groupBy(*by).agg(F.avg((F.col("hits") - F.col("hits0")) / (F.col("place") - F.col("place0"))).alias("ap"))


def mean_ap(df: DataFrame, scores: str = "scores", y: str = "y", tie: str = "rid", by: tuple[str, ...] = ()) -> DataFrame:
    """(by, map): unweighted mean of the one-vs-rest AP of the classes present."""
    long = df.select(*by, tie, y, F.posexplode(scores).alias("cls", "s")).withColumn("is", (F.col("cls") == F.col(y)).cast("int"))
    return average_precision(long, "s", "is", tie, (*by, "cls")).groupBy(*by).agg(F.avg("ap").alias("map"))


def accuracy(df: DataFrame, scores: str = "scores", y: str = "y") -> DataFrame:
    best = F.array_position(scores, F.array_max(scores)) - 1
    return df.agg(F.avg((best == F.col(y)).cast("double")).alias("accuracy"))


def log_loss(df: DataFrame, score: str = "score", y: str = "y") -> DataFrame:
    s, t = F.col(score), F.col(y)
    return df.agg(F.avg(F.greatest(s, F.lit(0.0)) - s * t + F.log1p(F.exp(-F.abs(s)))).alias("log_loss"))


def rmse(df: DataFrame, score: str = "score", y: str = "y", by: tuple[str, ...] = ()) -> DataFrame:
    return df.groupBy(*by).agg(F.sqrt(F.avg((F.col(score) - F.col(y)) ** 2)).alias("rmse"))


def confusion(df: DataFrame, predicted: str, y: str, classes: list) -> DataFrame:
    """Rows of true classes with a column of counts for each predicted class."""
    return df.groupBy(F.col(y).alias("actual")).pivot(predicted, classes).count().na.fill(0)


def curve(staged: DataFrame, metric: str, **kw) -> DataFrame:
    """The metric after each round of model.staged()."""
    if metric == "auc":
        flat = staged.withColumn("s", F.col("score")[0])
        return auc(flat, "s", by=("round",)).select("round", F.col("auc").alias("value"))
    if metric == "map":
        return mean_ap(staged, "score", by=("round",)).select("round", F.col("map").alias("value"))
    raise ValueError(f"unknown metric {metric!r}")


def best_round(curve_: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """The best value and the first round that has it."""
    best = F.max(F.struct("value", (-F.col("round")).alias("minus"))).alias("b")
    return curve_.groupBy(*by).agg(best).select(*by, F.col("b.value").alias("best_value"), (-F.col("b.minus")).alias("best_round"))


def scoreboard(values: DataFrame) -> DataFrame:
    """(dataset, method, value, place) of rows (dataset, method, value); place 1 is best."""
    return values.withColumn("place", F.rank().over(Window.partitionBy("dataset").orderBy(F.col("value").desc())))


def uniformity(codes: DataFrame, unit: Column, bins: int = 100) -> DataFrame:
    """(bin, n) of numbers in [1, 2)."""
    return codes.groupBy(F.floor((unit - 1) * bins).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def chi_square(hist: DataFrame, bins: int = 100) -> DataFrame:
    total = hist.agg(F.sum("n").alias("total"), F.sum(F.col("n") * F.col("n")).alias("squares"))
    return total.select((F.col("squares") * F.lit(float(bins)) / F.col("total") - F.col("total")).alias("chi2"))


def membership_evenness(memberships: DataFrame, p: str = "p") -> DataFrame:
    """Mean entropy over ln K, and each cell's mean and variance beside those of a flat Dirichlet."""
    k = F.size(p)
    entropy = -F.aggregate(p, F.lit(0.0), lambda acc, v: acc + F.when(v > 0, v * F.log(v)).otherwise(0.0)) / F.log(k.cast("double"))
    cells = memberships.select(k.alias("k"), F.posexplode(p).alias("cell", "v"), entropy.alias("e"))
    return cells.groupBy("cell").agg(
        F.avg("v").alias("mean"), F.var_pop("v").alias("variance"), F.avg("e").alias("mean_entropy"), F.max("k").alias("k")
    ).select(
        "cell", "mean", "variance", "mean_entropy", (F.lit(1.0) / F.col("k")).alias("flat_mean"),
        ((F.col("k") - 1) / (F.col("k") * F.col("k") * (F.col("k") + 1))).alias("flat_variance"),
    )


def chi_square_limit(freedom: int) -> float:
    """The 1 % point by the cube approximation."""
    t = 2.0 / (9.0 * freedom)
    return freedom * (1 - t + 2.3263 * math.sqrt(t)) ** 3
