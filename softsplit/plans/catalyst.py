"""The round of a soft splitter as DataFrame plans of built-in functions, in long form (rid, cell, value).

These plans suit few cells and are the checked definition of each step; trainers use the Arrow kernels.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..functions.hashing import bits_to_unit, hash_weight, md5_code, unit_to_sym


def cells_of(k: int) -> Column:
    return F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("cell")


def dense_weights(spark: SparkSession, m: int, k: int, round_: int) -> DataFrame:
    """(i, cell, w) from the md5 of `i|round|cell`, for plans that other engines repeat."""
    grid = spark.range(m).select(F.col("id").cast("int").alias("i"), cells_of(k))
    code = md5_code(F.concat_ws("|", F.col("i").cast("string"), F.lit(str(round_)), F.col("cell").cast("string")))
    return grid.select("i", "cell", unit_to_sym(bits_to_unit(code)).alias("w"))


def forward_dense(df: DataFrame, weights: DataFrame) -> DataFrame:
    """(rid, cell, z) of rows (rid, x); the weight table (inputs x cells) is broadcast."""
    long = df.select("rid", F.posexplode("x").alias("i", "v"))
    return long.join(F.broadcast(weights), "i").groupBy("rid", "cell").agg(F.sum(F.col("v") * F.col("w")).alias("z"))


def forward_hashed(df: DataFrame, k: int, round_: int, hash_fn: str = "mix") -> DataFrame:
    """Row layout: each non-zero is hashed for each cell. df: (rid, feats array<struct<f, v>>)."""
    long = df.select("rid", F.explode("feats").alias("x")).select("rid", F.col("x.f").alias("f"), F.col("x.v").alias("v"), cells_of(k))
    return long.groupBy("rid", "cell").agg(F.sum(F.col("v") * hash_weight(F.col("f"), round_, F.col("cell"), hash_fn)).alias("z"))


def forward_hashed_columns(df: DataFrame, k: int, round_: int, hash_fn: str = "mix") -> DataFrame:
    """Column layout: each distinct feature is hashed once for each cell, then joined to its column."""
    long = df.select("rid", F.explode("feats").alias("x")).select("rid", F.col("x.f").alias("f"), F.col("x.v").alias("v"))
    table = long.select("f").distinct().select("f", cells_of(k)).withColumn("w", hash_weight(F.col("f"), round_, F.col("cell"), hash_fn))
    return long.join(table, "f").groupBy("rid", "cell").agg(F.sum(F.col("v") * F.col("w")).alias("z"))


def cell_stats(z: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, cell, n, s, ss): the additive sums of each cell."""
    return z.groupBy(*by, "cell").agg(F.count(F.lit(1)).alias("n"), F.sum("z").alias("s"), F.sum(F.col("z") * F.col("z")).alias("ss"))


def merge_stats(parts: DataFrame) -> DataFrame:
    return parts.groupBy("cell").agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.sum("ss").alias("ss"))


def normalise(z: DataFrame, stats: DataFrame) -> DataFrame:
    """(rid, cell, z) standardised; stats has one row a cell and is broadcast."""
    mu = F.col("s") / F.col("n")
    sd = F.sqrt((F.col("ss") - F.col("n") * mu * mu) / (F.col("n") - 1))
    frozen = stats.select("cell", mu.alias("mu"), sd.alias("sd"))
    zt = F.when(F.col("sd") > 0, (F.col("z") - F.col("mu")) / F.col("sd")).otherwise(0.0)
    return z.join(F.broadcast(frozen), "cell").select("rid", "cell", zt.alias("z"))


def _by_row(zt: DataFrame) -> DataFrame:
    packed = F.array_sort(F.collect_list(F.struct("cell", "z")))  # as many entries as cells
    return zt.groupBy("rid").agg(F.transform(packed, lambda e: e["z"]).alias("zt"))


def soft_assign(zt: DataFrame) -> DataFrame:
    """(rid, p): memberships, rows sum to one; the row's maximum is taken off before exp."""
    e = F.transform("zt", lambda v: F.exp(v - F.array_max("zt")))
    total = F.aggregate("e", F.lit(0.0), lambda acc, v: acc + v)
    return _by_row(zt).withColumn("e", e).select("rid", F.transform("e", lambda v: v / total).alias("p"))


def hard_assign(zt: DataFrame) -> DataFrame:
    """(rid, cell): the cell of the largest value."""
    return _by_row(zt).select("rid", (F.array_position("zt", F.array_max("zt")) - 1).cast("int").alias("cell"))


def gram_sums(rows: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, j, k, a) for j <= k from rows (p, h)."""
    first = rows.select(*by, "h", "p", F.posexplode("p").alias("j", "pj"))
    both = first.select(*by, "h", "j", "pj", F.posexplode("p").alias("k", "pk")).filter("j <= k")
    return both.groupBy(*by, "j", "k").agg(F.sum(F.col("h") * F.col("pj") * F.col("pk")).alias("a"))


def grad_sums(rows: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, j, b) from rows (p, g)."""
    return rows.select(*by, "g", F.posexplode("p").alias("j", "pj")).groupBy(*by, "j").agg(F.sum(F.col("g") * F.col("pj")).alias("b"))


def apply_round(rows: DataFrame, w: list[float], eta: float) -> DataFrame:
    """score + eta * p.w for rows (score, p)."""
    table = F.array(*[F.lit(float(x)) for x in w])
    return rows.withColumn("score", F.col("score") + eta * F.aggregate(F.zip_with("p", table, lambda a, b: a * b), F.lit(0.0), lambda acc, v: acc + v))
