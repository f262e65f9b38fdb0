"""Benchmark decontamination: a prefix-filtered set join over item-sized word windows, in SQL functions only.

For exact containment the prefix of a window is one token, its rarest by corpus count. A document
position can only begin a match where that token stands, so the words of the documents meet the windows
by that token alone; the window must then lie inside the document (length and position bounds) and be
equal to the words there.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from ._store import Workspace

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: What parts words, which are ASCII digits and lower-case letters, and every character beyond ASCII.
BETWEEN_WORDS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def folded_words(text: Column) -> Column:
    """The words of a text with A-Z lower-cased; a null text has none. lower() is the same on ASCII, and faster."""
    text = F.coalesce(text, F.lit(""))
    low = F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))
    return F.array_remove(F.split(low, BETWEEN_WORDS), "")


def item_windows(items: DataFrame, width: int) -> DataFrame:
    """(item, wid, win): each `width` successive words of an item; an item of fewer words is one window."""
    n = F.size("ws")
    starts = F.sequence(F.lit(1), F.greatest(n - width + 1, F.lit(1)))
    return (
        items.select(F.col("item_id").cast("string").alias("item"), folded_words(F.col("text")).alias("ws"))
        .filter(n > 0)
        .select("item", "ws", F.explode(starts).alias("at"))
        .select("item", F.slice("ws", F.col("at"), F.least(F.lit(width), n)).alias("win"))
        .select("item", F.md5(F.concat_ws(" ", "win")).alias("wid"), "win")
    )


def prefix_tokens(windows: DataFrame, counts: DataFrame) -> DataFrame:
    """(wid, win, token, at): the rarest word of each distinct window, ties by word, and its place."""
    spread = windows.select("wid", "win").dropDuplicates(["wid"]).select("wid", "win", F.posexplode("win").alias("at", "word"))
    ranked = spread.join(counts, "word", "left").select("wid", "win", "at", "word", F.coalesce("n", F.lit(0)).alias("n"))
    first = ranked.groupBy("wid").agg(F.min(F.struct("n", "word", "at")).alias("best"), F.first("win").alias("win"))
    return first.select("wid", "win", F.col("best.word").alias("token"), F.col("best.at").alias("at"))


def window_hits(
    docs: DataFrame,
    items: DataFrame,
    ws: Workspace,
    width: int = 10,
    block: int = 100_000,
) -> tuple[DataFrame, DataFrame]:
    """Saved hits (row, doc_id, n_words, start, len, wid) and the windows (item, wid, win).

    Every document row has one row with its n_words and no wid. Windows are broadcast in blocks of
    `block` rows at most; each further block reads the documents once more.
    """
    windows = ws.save(item_windows(items, width), "windows")
    vocabulary = windows.select(F.explode("win").alias("word")).distinct()
    n_windows = windows.select("wid").distinct().count()
    texts = docs.select("doc_id", "text")
    said = texts.select(F.explode(folded_words(F.col("text"))).alias("word"))
    side = F.broadcast(vocabulary) if n_windows <= block else vocabulary
    counts = ws.save(said.join(side, "word", "left_semi").groupBy("word").agg(F.count(F.lit(1)).alias("n")), "counts")
    prefix = ws.save(prefix_tokens(windows, counts), "prefix")

    spread = (
        texts.select(F.monotonically_increasing_id().alias("row"), "doc_id", folded_words(F.col("text")).alias("ws"))
        .select("row", "doc_id", "ws", F.posexplode(F.concat(F.array(F.lit("")), F.col("ws"))).alias("pos", "token"))
    )
    start = F.col("pos") - 1 - F.col("at")  # pos 0 is the empty token that carries n_words
    inside = (start >= 0) & (start + F.size("win") <= F.size("ws"))
    equal = F.slice("ws", F.greatest(start + 1, F.lit(1)), F.size("win")) == F.col("win")
    blocks = max(1, -(-n_windows // block))
    found = None
    for k in range(blocks):
        part = prefix.filter(F.pmod(F.xxhash64("wid"), F.lit(blocks)) == k) if blocks > 1 else prefix
        if k == 0:
            part = part.unionByName(
                docs.sparkSession.sql("SELECT CAST(NULL AS string) wid, CAST(NULL AS array<string>) win, '' token, 0 at")
            )
        hits = (
            spread.join(F.broadcast(part), "token")
            .filter(F.col("wid").isNull() | (inside & equal))
            .select(
                "row",
                "doc_id",
                F.when(F.col("wid").isNull(), F.size("ws").cast("long")).alias("n_words"),
                F.when(F.col("wid").isNotNull(), start).alias("start"),
                F.size("win").alias("len"),
                "wid",
            )
        )
        found = hits if found is None else found.unionByName(hits)
    return ws.save(found, "hits"), windows


def contamination(
    docs: DataFrame,
    items: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
    width: int = 10,
    block: int = 100_000,
) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256 and contaminated of each row of `docs`.

    A word is hit when an occurrence of any window of any item covers it. Null texts have no words; a
    null or wordless item has no window; a null item id with words counts its windows in n_hit and is
    no member of the item list; items of one id are one item. Rows that repeat an id each have their
    own result. Without documents there are no rows; without items nothing is hit. Other columns are
    not read.
    """
    ws = Workspace(docs.sparkSession, "decontaminate")
    hits, windows = window_hits(
        docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")),
        items.select(F.col(item_col).alias("item_id"), F.col(item_text_col).alias("text")),
        ws,
        width,
        block,
    )
    order = Window.partitionBy("row").orderBy("start", "len").rowsBetween(Window.unboundedPreceding, -1)
    stop = F.col("start") + F.col("len")
    new = F.greatest(F.lit(0), stop - F.greatest("start", F.coalesce(F.max(stop).over(order), F.lit(0))))
    covered = hits.withColumn("new", new).groupBy("row").agg(
        F.max("doc_id").alias("doc_id"), F.max("n_words").alias("n_words"), F.coalesce(F.sum("new"), F.lit(0)).cast("long").alias("n_hit")
    )
    named = windows.select("wid", "item").filter("item is not null").distinct()
    with_items = (
        hits.filter("wid is not null").select("row", "wid").distinct().join(named, "wid").groupBy("row")
        .agg(F.array_sort(F.collect_set("item")).alias("items"))
    )
    joined = covered.join(with_items, "row", "left")
    return joined.select(
        "doc_id",
        "n_words",
        "n_hit",
        F.coalesce(F.size("items"), F.lit(0)).cast("long").alias("n_items"),
        F.sha2(F.coalesce(F.array_join("items", ","), F.lit("")), 256).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
    )
