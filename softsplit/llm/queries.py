"""The registered queries of the pipeline operators: thin contracts over whole tables, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .langid import language_id

    return language_id(table(spark, sf_dir, "documents"))


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .sharding import lpt_shards

    placed = lpt_shards(table(spark, sf_dir, "documents"), 40)
    return placed.withColumns({"law": F.lit("bytes"), "grown_shard": F.lit(None).cast("int")}).withColumn("shard", F.col("shard").cast("int"))


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontaminate import contamination

    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .chat import format_chats

    return format_chats(table(spark, sf_dir, "conversations"))


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_dedup import remove_repeats

    return remove_repeats(table(spark, sf_dir, "documents"))


def op6_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_shards import token_files

    return token_files(table(spark, sf_dir, "documents"))


def op7_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .near_dedup import near_components

    return near_components(table(spark, sf_dir, "documents"))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mix

    return mix(table(spark, sf_dir, "documents")).drop("copies")


def op9_host_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .host_rules import host_quality

    got = host_quality(table(spark, sf_dir, "documents"))
    return got.withColumn("host_rate", F.round("host_rate", 6))


def op10_maxent(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .maxent import score_texts

    return score_texts(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_language_id, op2_sharding, op3_decontaminate, op4_chat_format, op5_suffix_dedup, op6_token_shards, op7_near_dedup, op8_mixing, op9_host_rules, op10_maxent)}

ORACLES: dict[str, str] = {}

_WORDS9 = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_WORDS7 = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+')"

ORACLES["op7_near_dedup"] = f"""
WITH RECURSIVE w AS (SELECT doc_id, {_WORDS7} AS ws FROM documents),
s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) = 0 THEN []
    WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
    ELSE list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' ')) END) AS sh FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
common AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS shared
  FROM s a JOIN s b ON a.sh = b.sh AND a.doc_id <> b.doc_id GROUP BY 1, 2),
link AS (
  SELECT x, y FROM common JOIN n na ON na.doc_id = x JOIN n nb ON nb.doc_id = y
  WHERE 100 * shared >= 75 * (na.n + nb.n - shared)),
reach(doc_id, to_id) AS (
  SELECT x, y FROM link UNION SELECT r.doc_id, l.y FROM reach r JOIN link l ON l.x = r.to_id)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles,
  least(d.doc_id, coalesce(m.c, d.doc_id)) AS component_id,
  d.doc_id <= coalesce(m.c, d.doc_id) AS kept
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id
LEFT JOIN (SELECT doc_id, min(to_id) AS c FROM reach GROUP BY doc_id) m ON m.doc_id = d.doc_id
"""

ORACLES["op9_host_rules"] = f"""
WITH w AS (SELECT doc_id, source, coalesce(text, '') AS t, {_WORDS9} AS ws FROM documents),
g AS (
  SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, array_to_string(ws[i:i + 7], ' ')) AS c
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 6)) AS i FROM w WHERE len(ws) >= 8)),
r AS (
  SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS j FROM g WHERE c > 1) GROUP BY doc_id),
l AS (
  SELECT doc_id, count(*) - count(DISTINCT ln) AS n
  FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS ln FROM w)
  WHERE regexp_matches(ln, '[^\\x20\\x09-\\x0D]') GROUP BY doc_id),
m AS (
  SELECT w.doc_id, w.source, len(ws)::BIGINT AS n_words,
    coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::BIGINT AS word_chars,
    length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
    coalesce(l.n, 0)::BIGINT AS n_dup_lines, coalesce(r.n, 0)::BIGINT AS n_repeat_words
  FROM w LEFT JOIN l ON l.doc_id = w.doc_id LEFT JOIN r ON r.doc_id = w.doc_id),
f AS (
  SELECT *, (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AS base_failed, greatest(n_words, 1) AS p FROM m),
h AS (
  SELECT source, count(*) AS n, sum((base_failed OR word_chars < 2 * p OR word_chars > 14 * p
    OR 10 * n_symbols > p OR n_dup_lines >= 10)::INT) AS bad FROM f GROUP BY source),
q AS (SELECT avg(bad / n) AS m, var_pop(bad / n) AS v, avg(bad / n * (1 - bad / n) / n) AS noise FROM h),
k AS (SELECT m, least(greatest(m * (1 - m) / greatest(v - noise, 1e-9) - 1, 1.0), 1000.0) AS s FROM q),
v AS (SELECT source, (bad + s * m) / (n + s) AS rate, n + s + 1 AS weight, least(greatest(3.0 * m, 0.25), 0.5) AS bound FROM h, k)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  (NOT base_failed AND rate - 2 * sqrt(rate * (1 - rate) / weight) <= bound) AS kept, round(rate, 6) AS host_rate
FROM f JOIN v ON f.source IS NOT DISTINCT FROM v.source
"""

_WORDS3 = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

ORACLES["op3_decontaminate"] = f"""
WITH it AS (SELECT item_id::VARCHAR AS item, {_WORDS3} AS ws FROM benchmark),
win AS (
  SELECT DISTINCT item, least(10, len(ws)) AS n, array_to_string(ws[i:i + 9], ' ') AS win
  FROM (SELECT item, ws, unnest(range(1, greatest(len(ws) - 9, 1) + 1)) AS i FROM it WHERE len(ws) > 0)),
d AS (SELECT doc_id, {_WORDS3} AS ws FROM documents),
pos AS (SELECT doc_id, ws, unnest(range(1, len(ws) + 1)) AS i FROM d),
hit AS (
  SELECT doc_id, i, win.n, item
  FROM (SELECT DISTINCT n FROM win) sizes JOIN pos ON i + sizes.n - 1 <= len(ws)
  JOIN win ON win.n = sizes.n AND win.win = array_to_string(ws[i:i + sizes.n - 1], ' ')),
covered AS (
  SELECT doc_id, count(DISTINCT j) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS j FROM hit) GROUP BY doc_id),
items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items
  FROM (SELECT DISTINCT doc_id, item FROM hit) GROUP BY doc_id)
SELECT d.doc_id, len(d.ws)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN covered ON covered.doc_id = d.doc_id LEFT JOIN items ON items.doc_id = d.doc_id
"""
