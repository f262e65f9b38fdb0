"""Mixing sources to target weights: pivotal dependent rounding over a reduction tree, in SQL functions only.

A document of a source is wanted c times, c = target / size of the source. floor(c) copies are taken of
each; the rest of c is a fractional copy. Fractional copies meet in pairs: words move from one to the
other until one copy is whole or none, with the chances that keep each copy's expectation, and the other
meets the next. So a block ends with one fractional copy, blocks are combined the same way level by
level, and a source's taken words differ from its target by less than one document. Before that, a
source's few longest copies meet the pool of all its others, so that this document is a short one.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window, functions as F

from ._store import Workspace


def word_count(text: Column) -> Column:
    """Words [^\\x20\\x09-\\x0D]+ of a text; null has none."""
    text = F.coalesce(text, F.lit(""))
    return F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")).cast("long")


def source_targets(sizes: DataFrame, weights: Sequence[float], share: float, most: float) -> DataFrame:
    """(sid, source, source_size, target) of each source; sizes: (source, source_size).

    Sources in code point order, null last, take the weights in turn. `share` times all sizes is dealt by
    weight; a source stops at `most` times its size and the excess is dealt again. In order of limit per
    weight the stopped sources come first, so running sums give who stops and the level of the others.
    """
    deal = F.array(*[F.lit(float(w)) for w in weights])
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    ranked = (
        sizes.withColumn("sid", F.row_number().over(by_name))
        .withColumn("w", F.element_at(deal, (F.pmod(F.col("sid") - 1, F.lit(len(weights))) + 1).cast("int")))
        .withColumn("stop", F.lit(float(most)) * F.col("source_size"))
    )
    fill = Window.orderBy(F.col("stop") / F.col("w"), "sid")
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    rest = fill.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    everyone = Window.partitionBy(F.lit(0))
    level = (F.lit(float(share)) * F.sum("source_size").over(everyone) - F.coalesce(F.sum("stop").over(before), F.lit(0.0))) / F.sum("w").over(rest)
    leveled = ranked.withColumn("level", level).withColumn("stops", F.col("w") * F.col("level") >= F.col("stop"))
    water = F.first(F.when(~F.col("stops"), F.col("level")), ignorenulls=True).over(
        fill.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    )
    return leveled.withColumn("water", water).select(
        "sid", "source", "source_size", F.when(F.col("stops"), F.col("stop")).otherwise(F.col("w") * F.col("water")).alias("target")
    )


#: One meeting of the waiting copy r and the next copy x. a and b are the words that r or x can gain; the
#: outcome says who is settled (r whole, x none, x whole, r none) and the other's new fraction.
_MEET = """
aggregate(units,
  named_struct('uid', CAST(NULL AS bigint), 'h', 0L, 'n', 0D, 'p', 0D,
    'out', CAST(array() AS array<struct<uid:bigint,take:int>>)),
  (r, x) -> CASE WHEN r.uid IS NULL THEN named_struct('uid', x.uid, 'h', x.h, 'n', x.n, 'p', x.p, 'out', r.out)
  ELSE element_at(transform(
    transform(
      transform(
        array(named_struct('a', least(r.n * (1 - r.p), x.n * x.p), 'b', least(x.n * (1 - x.p), r.n * r.p))),
        t -> named_struct('a', t.a, 'b', t.b, 'to_r',
          (shiftrightunsigned(xxhash64(r.h, x.h, {seed}L), 11) / 9007199254740992D) * (t.a + t.b) < t.b)),
      t -> CASE
        WHEN t.to_r AND r.n * (1 - r.p) <= x.n * x.p THEN named_struct('x_waits', true, 'take', 1, 'p', x.p - t.a / x.n)
        WHEN t.to_r THEN named_struct('x_waits', false, 'take', 0, 'p', r.p + t.a / r.n)
        WHEN x.n * (1 - x.p) <= r.n * r.p THEN named_struct('x_waits', false, 'take', 1, 'p', r.p - t.b / r.n)
        ELSE named_struct('x_waits', true, 'take', 0, 'p', x.p + t.b / x.n) END),
    t -> named_struct(
      'uid', IF(t.x_waits, x.uid, r.uid), 'h', IF(t.x_waits, x.h, r.h), 'n', IF(t.x_waits, x.n, r.n),
      'p', greatest(0D, least(1D, t.p)),
      'out', concat(r.out, array(named_struct('uid', IF(t.x_waits, r.uid, x.uid), 'take', t.take))))), 1) END)
"""


#: The meetings of a source's longest copies, one after the other, with the pool of all its others, whose
#: copies share one fraction q: words move between the long copy and the whole pool.
_POOL = """
aggregate(long,
  named_struct('q', q, 'out', CAST(array() AS array<struct<uid:bigint,h:bigint,n:double,p:double>>)),
  (s, x) -> element_at(transform(
    transform(
      array(named_struct('a', least(x.n * (1 - x.p), w * s.q), 'b', least(w * (1 - s.q), x.n * x.p))),
      t -> named_struct('a', t.a, 'b', t.b, 'up',
        (shiftrightunsigned(xxhash64(x.h, {seed}L), 11) / 9007199254740992D) * (t.a + t.b) < t.b)),
    t -> named_struct(
      'q', greatest(0D, least(1D, IF(t.up, s.q - t.a / w, s.q + t.b / w))),
      'out', concat(s.out, array(named_struct('uid', x.uid, 'h', x.h, 'n', x.n,
        'p', IF(t.up, IF(t.a = x.n * (1 - x.p), 1D, x.p + t.a / x.n), IF(t.b = x.n * x.p, 0D, x.p - t.b / x.n))))))), 1))
"""


def _each(side: DataFrame, few: bool) -> DataFrame:
    """A table of a row for each source, broadcast where the sources were counted to be few."""
    return F.broadcast(side) if few else side


def meet_long(units: DataFrame, ws: Workspace, seed: int, share: int = 64, few: bool = False) -> DataFrame:
    """The units with new fractions after each source's long copies, if any, have met the pool of its others.

    The units of a source share one fraction. Long copies have more than 1/share of its words, so there are
    fewer than `share` of them; each becomes whole or none as far as the pool's words allow. What is left
    to the ordinary meetings are short copies, and so is the last one, which alone can miss the target.
    """
    total = units.groupBy("sid").agg(F.sum("n").alias("all"), F.max("p").alias("q"))
    marked = ws.save(units.join(_each(total, few), "sid").withColumn("is_long", F.col("n") * share > F.col("all")), "marked")
    order = F.array_sort(F.collect_list(F.struct((-F.col("n")).alias("o"), "h", "uid", "n", "p")))
    long = marked.filter("is_long").groupBy("sid", "all", "q").agg(order.alias("long"), F.sum("n").alias("taken_up"))
    pool = long.withColumn("w", F.col("all") - F.col("taken_up")).filter("w > 0").select("sid", F.expr(_POOL.format(seed=seed)).alias("s"))
    pool = ws.save(pool, "pool")
    met = pool.select("sid", F.explode("s.out").alias("x")).select("sid", "x.uid", "x.h", "x.n", "x.p")
    rest = marked.join(_each(pool.select("sid", F.col("s.q").alias("new_q")), few), "sid", "left").filter("new_q is null or not is_long")
    return met.unionByName(rest.select("sid", "uid", "h", "n", F.coalesce("new_q", "p").alias("p")))


def pivotal(units: DataFrame, ws: Workspace, seed: int = 11, block: int = 128, few: bool = False) -> DataFrame:
    """(uid, take): whole copies 0 or 1 of units (sid, uid, h, n, p), by meetings in a tree of blocks.

    h is a hash that deals units to blocks and seeds the meetings, n > 0 the unit's words, p its fraction.
    The longest meet first, so that the copy left at the end tends to be a short one.
    """
    settled, level = [], 0
    while True:
        counts = units.groupBy("sid").agg(F.ceil(F.count(F.lit(1)) / block).alias("blocks"))
        counts = ws.save(counts, f"counts{level}")
        widest = counts.agg(F.max("blocks")).first()[0] or 0
        dealt = units.join(_each(counts, few), "sid").withColumn("block", F.pmod(F.xxhash64("h", F.lit(level)), F.col("blocks")))
        met = dealt.groupBy("sid", "block").agg(F.array_sort(F.collect_list(F.struct((-F.col("n")).alias("o"), "h", "uid", "n", "p"))).alias("units"))
        met = ws.save(met.select("sid", F.expr(_MEET.format(seed=seed + level)).alias("r")), f"met{level}")
        settled.append(met.select(F.explode("r.out").alias("o")).select("o.uid", "o.take"))
        units = met.select("sid", "r.uid", "r.h", "r.n", "r.p")
        level += 1
        if widest <= 1:
            break
    chance = F.shiftrightunsigned(F.xxhash64("h", F.lit(seed)), 11) / F.lit(9007199254740992.0)
    out = units.select("uid", (chance < F.col("p")).cast("int").alias("take"))
    for x in settled:
        out = out.unionByName(x)
    return out


def mix(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    weights: Sequence[float] = (5, 2, 1),
    share: float = 1.5,
    most: float = 2.0,
    seed: int = 11,
    small_sources: int = 100_000,
    carry: Sequence[str] = (),
) -> DataFrame:
    """doc_id, size, source_size, target, copies and taken (and the columns `carry`) of each row.

    size counts the words of the text. Copies are whole, at most ceil(most); taken = copies * size. A null
    text and an empty one have size 0 and are taken 0 words; a null source is a source of its own; rows
    that repeat an id are rows like others; an empty table gives no rows; columns not named are not read.
    The choice depends on ids, sizes and `seed` only, so reruns agree. Up to `small_sources` source rows
    are broadcast, more are joined by shuffle.
    """
    ws = Workspace(docs.sparkSession, "mixing")
    rows = docs.select(
        F.col(id_col).alias("doc_id"), word_count(F.col(text_col)).alias("size"), F.col(source_col).alias("source"), *carry
    )
    rows = ws.save(rows.withColumn("uid", F.monotonically_increasing_id()), "rows")
    sources = ws.save(
        source_targets(rows.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, most), "sources"
    )
    side = sources.withColumnRenamed("source", "named")
    few = sources.count() <= small_sources
    side = _each(side, few)
    wanted = rows.join(side, F.col("source").eqNullSafe(F.col("named"))).drop("named")
    c = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    wanted = wanted.withColumn("whole", F.floor(c)).withColumn("p", c - F.floor(c))
    h = F.xxhash64("doc_id", "size", F.lit(seed)).alias("h")
    units = wanted.filter("size > 0 and p > 0").select("sid", "uid", h, F.col("size").cast("double").alias("n"), "p")
    take = pivotal(meet_long(units, ws, seed, few=few), ws, seed, few=few)
    copies = (F.col("whole") + F.coalesce("take", F.lit(0))).cast("long")
    return (
        wanted.join(take, "uid", "left")
        .withColumn("copies", copies)
        .select("doc_id", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"), *carry)
    )
