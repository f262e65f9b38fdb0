"""Registered queries of the engine with the SQL that checks them.

Sums of fractions are given in fixed point (units of 2**-20), since engines add in different orders.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from .baselines import bundling, trees
from .functions import cost, features, losses, metrics
from .functions.hashing import ADDENDS, HALF, LOW_BITS, MASK, MULTIPLIERS, bits_to_unit, hash_weight, md5_code, simhash
from .operators import relational as rel
from .operators.solve import solve_scores
from .plans import catalyst as cat
from .sources import load

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLES[fn.__name__] = sql
        return fn

    return add


def fixed(value: Column) -> Column:
    return F.floor(value * 1048576 + 0.5).cast("bigint")


def fixed_sql(value: str) -> str:
    return f"floor(({value}) * 1048576 + 0.5)::BIGINT"


# --- tables in training form -----------------------------------------------------------------------------------


def embedding_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(rid, x, half): half is 1 where the first eight coordinates sum above 0."""
    x = F.col("embedding").cast("array<double>")
    half = (F.aggregate(F.slice(x, 1, 8), F.lit(0.0), lambda a, v: a + v) > 0).cast("int")
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("rid"), x.alias("x"), half.alias("half"), "label")


def word_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents", ["doc_id", "text"]).select(F.col("doc_id").alias("rid"), features.word_set(F.col("text")).alias("feats"))


_WORDS = "list_distinct(list_filter(string_split(translate(lower(coalesce(text,'')), chr(10)||chr(13)||chr(9), '   '), ' '), lambda w: w <> ''))"
_CODE = "('0x' || substr(md5({0}), 1, 8))::BIGINT"
_SYM = "((1.0::DOUBLE + ({0} & 8388607) / 8388608.0::DOUBLE) * 2.0::DOUBLE - 3.0::DOUBLE)"
_EMB = """x AS (SELECT vec_id AS rid, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings),
y AS (SELECT vec_id AS rid, (list_sum(list_transform(embedding[1:8], lambda e: e::DOUBLE)) > 0)::INT AS half, label FROM embeddings)"""


def _z_sql(round_: int, k: int) -> str:
    sym = _SYM.format(_CODE.format(f"i || '|{round_}|' || cell"))
    return f"SELECT rid, cell, sum(v * {sym}) AS z FROM x, range({k}) c(cell) GROUP BY rid, cell"


def _mix_sql(round_: int) -> str:
    """The weight of (feature code c, round, cell) by the integer steps of functions.hashing."""
    m, (a0, a1), mask = MULTIPLIERS, ADDENDS[:2], MASK
    steps = [
        ("x1", f"((c & {HALF}) * {m[0]} + {(round_ + 1) * a0}) & {mask}"),
        ("x2", f"(xor(xor(x1, x1 >> 15), c >> 31) * {m[2]}) & {mask}"),
        ("x3", f"(xor(x2, x2 >> 13) * {m[1]}) & {mask}"),
        ("x4", f"xor(xor(x3, x3 >> 16), ((cell + 1) * {a1}) & {mask})"),
        ("x5", f"(x4 * {m[1]}) & {mask}"),
        ("x6", f"(xor(x5, x5 >> 15) * {m[2]}) & {mask}"),
    ]
    inner = "SELECT rid, c, cell::BIGINT AS cell FROM f, range({k}) t(cell)"
    for name, value in steps:
        inner = f"SELECT *, ({value})::BIGINT AS {name} FROM ({inner})"
    return f"SELECT rid, cell, sum((xor(x6, x6 >> 16) & {LOW_BITS}) / {(LOW_BITS + 1) // 2}.0::DOUBLE - 1.0) AS z FROM ({inner}) GROUP BY rid, cell"


def _word_z_sql(round_: int, k: int) -> str:
    return _mix_sql(round_).replace("{k}", str(k))


def _p_sql(round_: int, k: int, z=None) -> str:
    """CTEs z, stats, zt, p of a round, named by it."""
    r = round_
    return f"""z{r} AS ({(z or _z_sql)(r, k)}),
s{r} AS (SELECT cell, count(*) AS n, sum(z) AS s, sum(z * z) AS ss FROM z{r} GROUP BY cell),
zt{r} AS (SELECT rid, z{r}.cell, (z - s / n) / sqrt((ss - n * (s / n) * (s / n)) / (n - 1)) AS zt FROM z{r} JOIN s{r} ON z{r}.cell = s{r}.cell),
e{r} AS (SELECT rid, cell, exp(zt - max(zt) OVER (PARTITION BY rid)) AS e, zt FROM zt{r}),
p{r} AS (SELECT rid, cell, e / sum(e) OVER (PARTITION BY rid) AS p, zt FROM e{r})"""


def _emb_z(spark: SparkSession, sf_dir: str, round_: int = 0, k: int = 4) -> DataFrame:
    rows = embedding_rows(spark, sf_dir)
    return cat.forward_dense(rows.select("rid", "x"), cat.dense_weights(spark, 64, k, round_))


def _emb_p(spark: SparkSession, sf_dir: str, round_: int = 0, k: int = 4) -> DataFrame:
    z = _emb_z(spark, sf_dir, round_, k)
    return cat.soft_assign(cat.normalise(z, cat.cell_stats(z)))


# --- hashing and forward passes ----------------------------------------------------------------------------------


@query(f"SELECT floor(({_CODE.format('i::VARCHAR')} & 8388607) / 8388608.0 * 100)::INT AS bin, count(*) AS n FROM (SELECT DISTINCT o_orderkey AS i FROM orders WHERE o_orderkey IS NOT NULL) GROUP BY 1")
def hash_uniformity_hist(spark, sf_dir):
    return metrics.uniformity(_order_keys(spark, sf_dir), bits_to_unit(md5_code(F.col("id").cast("string"))))


def _order_keys(spark, sf_dir):
    return load(spark, sf_dir, "orders", ["o_orderkey"]).select(F.col("o_orderkey").alias("id")).filter("id IS NOT NULL").distinct()


@query()
def hash_uniformity_chi2(spark, sf_dir):
    """Three hashes of the distinct order keys, each beside the 1 % point."""
    out = None
    for name, code in (
        ("md5", md5_code(F.col("id").cast("string"))),
        ("xxh64", F.xxhash64(F.concat_ws("|", F.col("id").cast("string"), F.lit("0")), F.lit(0))),
        ("mix", None),
    ):
        unit = (hash_weight(F.col("id"), 0, F.lit(0)) + 3) / 2 if code is None else bits_to_unit(code)
        one = metrics.chi_square(metrics.uniformity(_order_keys(spark, sf_dir), unit)).select(F.lit(name).alias("hash_fn"), "chi2", F.lit(metrics.chi_square_limit(99)).alias("limit"))
        out = one if out is None else out.unionByName(one)
    return out


@query(f"""WITH f AS (SELECT DISTINCT unnest({_WORDS}) AS f FROM documents)
SELECT f, cell::INT AS cell, {fixed_sql(_SYM.format(_CODE.format("f || '|0|' || cell")))} AS w FROM f, range(2) c(cell)""")
def hashed_weights(spark, sf_dir):
    words = word_rows(spark, sf_dir).select(F.explode("feats").alias("x")).select(F.col("x.f").alias("f")).distinct()
    return words.select("f", cat.cells_of(2)).select("f", "cell", fixed(hash_weight(F.col("f"), 0, F.col("cell"), "md5")).alias("w"))


_HASHED = f"""WITH f AS (SELECT doc_id AS rid, unnest({_WORDS}) AS f FROM documents)
SELECT rid, cell::INT AS cell, {fixed_sql("sum(" + _SYM.format(_CODE.format("f || '|0|' || cell")) + ")")} AS z
FROM f, range(4) c(cell) GROUP BY rid, cell"""


@query(_HASHED)
def hashed_forward_row(spark, sf_dir):
    return cat.forward_hashed(word_rows(spark, sf_dir), 4, 0, "md5").select("rid", "cell", fixed(F.col("z")).alias("z"))


@query(_HASHED)
def hashed_forward_column(spark, sf_dir):
    return cat.forward_hashed_columns(word_rows(spark, sf_dir), 4, 0, "md5").select("rid", "cell", fixed(F.col("z")).alias("z"))


@query(f"WITH {_EMB} SELECT rid, cell::INT AS cell, {fixed_sql('z')} AS z FROM ({_z_sql(0, 4)})")
def dense_forward(spark, sf_dir):
    return _emb_z(spark, sf_dir).select("rid", "cell", fixed(F.col("z")).alias("z"))


_SIM = " + ".join(f"CASE WHEN sum(CASE WHEN c & {1 << j} <> 0 THEN 1 ELSE -1 END) >= 0 THEN {1 << j} ELSE 0 END" for j in range(8))


@query(f"""WITH f AS (SELECT doc_id AS rid, {_CODE.format("f")} AS c FROM (SELECT doc_id, unnest({_WORDS}) AS f FROM documents))
SELECT rid, ({_SIM})::BIGINT AS signature FROM f GROUP BY rid""")
def simhash_signature(spark, sf_dir):
    return word_rows(spark, sf_dir).filter(F.size("feats") > 0).select("rid", simhash(F.col("feats"), 8).alias("signature"))


# --- statistics, assignment --------------------------------------------------------------------------------------

_STATS_OUT = f"cell::INT AS cell, n, {fixed_sql('s')} AS s, {fixed_sql('ss')} AS ss"


def _stats_out(stats: DataFrame, *by: str) -> DataFrame:
    return stats.select(*by, "cell", "n", fixed(F.col("s")).alias("s"), fixed(F.col("ss")).alias("ss"))


@query(f"WITH {_EMB}, {_p_sql(0, 4)} SELECT {_STATS_OUT} FROM s0")
def cell_stats(spark, sf_dir):
    return _stats_out(cat.cell_stats(_emb_z(spark, sf_dir)))


@query(f"WITH {_EMB}, {_p_sql(0, 4)} SELECT {_STATS_OUT} FROM s0")
def cell_stats_by_partition_merge(spark, sf_dir):
    parts = cat.cell_stats(_emb_z(spark, sf_dir).withColumn("part", F.col("rid") % 7), ("part",))
    return _stats_out(cat.merge_stats(parts))


@query(f"WITH {_EMB}, {_p_sql(0, 4)}, {_p_sql(1, 4)} SELECT 0 AS round, {_STATS_OUT} FROM s0 UNION ALL SELECT 1 AS round, {_STATS_OUT} FROM s1")
def cell_stats_block(spark, sf_dir):
    both = [cat.cell_stats(_emb_z(spark, sf_dir, r)).withColumn("round", F.lit(r)) for r in (0, 1)]
    return _stats_out(both[0].unionByName(both[1]), "round")


@query(f"WITH {_EMB}, {_p_sql(0, 4)} SELECT cell::INT AS cell, {fixed_sql('avg(zt)')} AS mean, {fixed_sql('stddev_samp(zt)')} AS sd FROM zt0 GROUP BY cell")
def normalised_moments(spark, sf_dir):
    z = _emb_z(spark, sf_dir)
    zt = cat.normalise(z, cat.cell_stats(z))
    return zt.groupBy("cell").agg(fixed(F.avg("z")).alias("mean"), fixed(F.stddev_samp("z")).alias("sd"))


@query(f"WITH {_EMB}, {_p_sql(0, 4)} SELECT rid, cell::INT AS cell, {fixed_sql('p')} AS p FROM p0")
def soft_assign(spark, sf_dir):
    return _emb_p(spark, sf_dir).select("rid", F.posexplode("p").alias("cell", "v")).select("rid", "cell", fixed(F.col("v")).alias("p"))


@query(f"WITH {_EMB}, {_p_sql(0, 4)} SELECT rid, arg_max(cell, zt)::INT AS cell FROM p0 GROUP BY rid")
def hard_assign(spark, sf_dir):
    z = _emb_z(spark, sf_dir)
    return cat.hard_assign(cat.normalise(z, cat.cell_stats(z)))


@query(f"""WITH {_EMB}, {_p_sql(0, 4)}, h AS (SELECT rid, -sum(p * ln(p)) / ln(4.0) AS e FROM p0 GROUP BY rid)
SELECT cell::INT AS cell, {fixed_sql('avg(p)')} AS mean, {fixed_sql('var_pop(p)')} AS variance, {fixed_sql('avg(e)')} AS mean_entropy
FROM p0 JOIN h ON p0.rid = h.rid GROUP BY cell""")
def membership_evenness(spark, sf_dir):
    got = metrics.membership_evenness(_emb_p(spark, sf_dir))
    return got.select("cell", *[fixed(F.col(c)).alias(c) for c in ("mean", "variance", "mean_entropy")])


# --- losses --------------------------------------------------------------------------------------------------------

_S = "((doc_id % 7) - 3) / 2.0::DOUBLE"


@query(f"""WITH t AS (SELECT doc_id, toxic, 1.0 / (1.0 + exp(-({_S}))) AS q FROM labels)
SELECT doc_id, {fixed_sql('q - toxic')} AS g, {fixed_sql('greatest(q * (1 - q), 1e-6)')} AS h FROM t""")
def grad_hess_logistic(spark, sf_dir):
    g, h = losses.logistic_expr((F.col("doc_id") % 7 - 3) / F.lit(2.0), F.col("toxic"))
    return load(spark, sf_dir, "labels").select("doc_id", fixed(g).alias("g"), fixed(h).alias("h"))


@query("SELECT l_returnflag, floor(sum(floor((l_quantity - l_extendedprice * (1 - l_discount)) * 1024 + 0.5)))::BIGINT AS g, count(*) AS h FROM lineitem GROUP BY 1")
def grad_hess_squared(spark, sf_dir):
    g, h = losses.squared_expr(F.col("l_quantity"), F.col("l_extendedprice") * (1 - F.col("l_discount")))
    rows = load(spark, sf_dir, "lineitem", ["l_returnflag", "l_quantity", "l_extendedprice", "l_discount"])
    return rows.groupBy("l_returnflag").agg(F.sum(F.floor(g * 1024 + 0.5)).cast("bigint").alias("g"), F.sum(h).cast("bigint").alias("h"))


@query(f"""WITH t AS (SELECT doc_id, list_position(['de','en','es','fr'], lang) - 1 AS y, [exp((doc_id % 5) / 4.0), exp((doc_id % 3) / 2.0), 1.0, exp(-0.5)] AS e FROM documents),
u AS (SELECT doc_id, y, unnest(range(4)) AS cls, unnest(e) / list_sum(e) AS q FROM t)
SELECT doc_id, cls::INT AS cls, {fixed_sql('q - (cls = y)::INT')} AS g, {fixed_sql('greatest(q * (1 - q), 1e-6)')} AS h FROM u""")
def grad_hess_softmax(spark, sf_dir):
    docs = load(spark, sf_dir, "documents", ["doc_id", "lang"])
    y = F.array_position(F.array(*map(F.lit, ("de", "en", "es", "fr"))), F.col("lang")) - 1
    scores = F.array((F.col("doc_id") % 5) / 4.0, (F.col("doc_id") % 3) / 2.0, F.lit(0.0), F.lit(-0.5))
    g, h = losses.softmax_expr(F.col("s"), F.col("y"))
    long = docs.select("doc_id", y.alias("y"), scores.alias("s")).select("doc_id", F.posexplode(F.arrays_zip(g.alias("g"), h.alias("h"))).alias("cls", "gh"))
    return long.select("doc_id", "cls", fixed(F.col("gh.g")).alias("g"), fixed(F.col("gh.h")).alias("h"))


@query(f"""WITH t AS (SELECT c_custkey, count(o_orderkey) AS y FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1)
SELECT c_custkey, {fixed_sql('exp((c_custkey % 3) / 2.0) - y')} AS g, {fixed_sql('exp((c_custkey % 3) / 2.0)')} AS h FROM t""")
def grad_hess_poisson(spark, sf_dir):
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    counted = load(spark, sf_dir, "customer", ["c_custkey"]).join(orders, F.col("o_custkey") == F.col("c_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("y"))
    g, h = losses.poisson_expr((F.col("c_custkey") % 3) / F.lit(2.0), F.col("y"))
    return counted.select("c_custkey", fixed(g).alias("g"), fixed(h).alias("h"))


# --- normal equations and rounds -------------------------------------------------------------------------------------


def _emb_rows(spark, sf_dir, k=4, round_=0):
    y = embedding_rows(spark, sf_dir).select("rid", "half", "label")
    return _emb_p(spark, sf_dir, round_, k).join(y, "rid").withColumns({"g": F.lit(0.5) - F.col("half"), "h": F.lit(0.25)})


_GRAM = "SELECT a.cell AS j, b.cell AS k, sum({h} * a.p * b.p) AS a FROM {p} a JOIN {p} b ON a.rid = b.rid AND a.cell <= b.cell GROUP BY 1, 2"


@query(f"WITH {_EMB}, {_p_sql(0, 4)} SELECT j::INT AS j, k::INT AS k, {fixed_sql('a')} AS a FROM ({_GRAM.format(h=0.25, p='p0')})")
def gram_sums_binary(spark, sf_dir):
    return cat.gram_sums(_emb_rows(spark, sf_dir)).select("j", "k", fixed(F.col("a")).alias("a"))


@query(f"WITH {_EMB}, {_p_sql(0, 4)} SELECT cell::INT AS j, {fixed_sql('sum(p * (0.5 - half))')} AS b FROM p0 JOIN y ON y.rid = p0.rid GROUP BY cell")
def grad_sums(spark, sf_dir):
    return cat.grad_sums(_emb_rows(spark, sf_dir)).select("j", fixed(F.col("b")).alias("b"))


@query(f"""WITH {_EMB}, {_p_sql(0, 4)}
SELECT cls::INT AS cls, a.cell::INT AS j, b.cell::INT AS k, {fixed_sql('sum((0.05 + 0.01 * (cls + y.label)) * a.p * b.p)')} AS a
FROM p0 a JOIN p0 b ON a.rid = b.rid AND a.cell <= b.cell JOIN y ON y.rid = a.rid, range(10) c(cls) GROUP BY cls, a.cell, b.cell""")
def gram_sums_multiclass(spark, sf_dir):
    """One splitter for all ten classes; the upper triangle of each class's Gram matrix, with a curvature of its own."""
    rows = _class_rows(spark, sf_dir)
    return cat.gram_sums(rows, ("cls",)).select("cls", "j", "k", fixed(F.col("a")).alias("a"))


def _class_rows(spark, sf_dir):
    rows = _emb_rows(spark, sf_dir).select("p", "label", F.explode(F.sequence(F.lit(0), F.lit(9))).alias("cls"))
    return rows.withColumns({"g": F.lit(0.1) - (F.col("label") == F.col("cls")).cast("int"), "h": 0.05 + 0.01 * (F.col("cls") + F.col("label"))})


@query(f"""WITH {_EMB}, {_p_sql(0, 4)}
SELECT cls::INT AS cls, cell::INT AS j, {fixed_sql('sum(p * (0.1 - (label = cls)::INT))')} AS b
FROM p0 JOIN y ON y.rid = p0.rid, range(10) c(cls) GROUP BY cls, cell""")
def grad_sums_multiclass(spark, sf_dir):
    return cat.grad_sums(_class_rows(spark, sf_dir), ("cls",)).select("cls", "j", fixed(F.col("b")).alias("b"))


def _solved(spark, sf_dir, k, lam=1.0):
    import numpy as np

    rows = _emb_rows(spark, sf_dir, k)
    a, b = np.zeros((k, k)), np.zeros(k)
    for r in cat.gram_sums(rows).collect():
        a[r["j"], r["k"]] = a[r["k"], r["j"]] = r["a"]
    for r in cat.grad_sums(rows).collect():
        b[r["j"]] = r["b"]
    return solve_scores(a, b, lam)[0]


def _elimination_sql(k: int, lam: float, p: str, g: str, h: str, name: str) -> str:
    """CTEs that solve the k x k system by unrolled elimination: one row with columns w0..w(k-1)."""
    a = {(i, j): f"a{min(i, j)}{max(i, j)}" for i in range(k) for j in range(k)}
    cols = [f"sum(CASE WHEN a.cell={i} AND b.cell={j} THEN {h}*a.p*b.p ELSE 0 END){f' + {lam}' if i == j else ''} AS a{i}{j}" for i in range(k) for j in range(i, k)]
    cols += [f"-sum(CASE WHEN a.cell={i} AND b.cell={i} THEN {g}*a.p ELSE 0 END) AS r{i}" for i in range(k)]
    out = f"{name}_0 AS (SELECT {', '.join(cols)} FROM {p} a JOIN {p} b ON a.rid = b.rid JOIN y ON y.rid = a.rid)"
    cells = {(i, j): a[(i, j)] for i in range(k) for j in range(k)}
    rhs = {i: f"r{i}" for i in range(k)}
    for c in range(k - 1):
        now = []
        for i in range(c + 1, k):
            for j in range(c + 1, k):
                now.append(f"{cells[(i, j)]} - {cells[(i, c)]} * {cells[(c, j)]} / {cells[(c, c)]} AS m{c}_{i}{j}")
            now.append(f"{rhs[i]} - {cells[(i, c)]} * {rhs[c]} / {cells[(c, c)]} AS r{c}_{i}")
        out += f", {name}_{c + 1} AS (SELECT *, {', '.join(now)} FROM {name}_{c})"
        for i in range(c + 1, k):
            for j in range(c + 1, k):
                cells[(i, j)] = f"m{c}_{i}{j}"
            rhs[i] = f"r{c}_{i}"
        # rows above keep the cells they had
        for j in range(c, k):
            cells[("row", c, j)] = cells[(c, j)]
    rows = {(i, j): cells.get(("row", i, j), cells[(i, j)]) for i in range(k) for j in range(k)}
    step = k - 1
    for i in reversed(range(k)):
        known = "".join(f" - {rows[(i, j)]} * w{j}" for j in range(i + 1, k))
        out += f", {name}_{step + 1} AS (SELECT *, ({rhs[i]}{known}) / {rows[(i, i)]} AS w{i} FROM {name}_{step})"
        step += 1
    return out + f", {name} AS (SELECT {', '.join(f'w{i}' for i in range(k))} FROM {name}_{step})"


def _w_rows(spark, w):
    return spark.createDataFrame([(j, float(x)) for j, x in enumerate(w)], "j int, w double").select("j", F.floor(F.col("w") * 10000 + 0.5).cast("bigint").alias("w"))


def _w_sql(k):
    return f"WITH {_EMB}, {_p_sql(0, k)}, {_elimination_sql(k, 1.0, 'p0', '(0.5 - half)', '0.25', 'w')} " + " UNION ALL ".join(
        f"SELECT {j} AS j, floor(w{j} * 10000 + 0.5)::BIGINT AS w FROM w" for j in range(k)
    )


@query(_w_sql(2))
def solve_scores_k2(spark, sf_dir):
    return _w_rows(spark, _solved(spark, sf_dir, 2))


@query(_w_sql(4))
def solve_scores_k4(spark, sf_dir):
    return _w_rows(spark, _solved(spark, sf_dir, 4))


_LOGISTIC = ("(0.5 - half)", "0.25", "1.0 / (1.0 + exp(-score)) - half", "greatest(1.0 / (1.0 + exp(-score)) * (1 - 1.0 / (1.0 + exp(-score))), 1e-6)")
_SQUARED = ("(0.0 - half)", "1.0", "score - half", "1.0")


def _round1_sql(head: str, loss: tuple = _LOGISTIC, z=None) -> str:
    return f"""WITH {head}, {_p_sql(0, 2, z)}, {_elimination_sql(2, 1.0, 'p0', loss[0], loss[1], 'wa')},
score1 AS (SELECT rid, 0.3 * sum(p * CASE cell WHEN 0 THEN w0 ELSE w1 END) AS score FROM p0, wa GROUP BY rid)"""


def _round2_sql(head: str, loss: tuple = _LOGISTIC, z=None) -> str:
    """Two rounds on rows y (rid, half) with two cells, ridge 1 and shrinkage 0.3, up to score2 (rid, score)."""
    return f"""{_round1_sql(head, loss, z)},
y2 AS (SELECT y.rid, {loss[2]} AS g, {loss[3]} AS h FROM y JOIN score1 ON y.rid = score1.rid),
{_p_sql(1, 2, z)}, {_elimination_sql(2, 1.0, 'p1', 'y2.g', 'y2.h', 'wb').replace('JOIN y ON y.rid', 'JOIN y2 ON y2.rid')},
score2 AS (SELECT p1.rid, any_value(score1.score) + 0.3 * sum(p * CASE cell WHEN 0 THEN w0 ELSE w1 END) AS score FROM p1 JOIN score1 ON score1.rid = p1.rid, wb GROUP BY p1.rid)"""


_ROUND1, _ROUND2 = _round1_sql(_EMB), _round2_sql(_EMB)
_SCORES = "SELECT rid, floor(score * 1000000 + 0.5)::BIGINT AS score FROM score2"
_WORD_HEAD = f"""f AS (SELECT rid, ('0x' || substr(md5(f), 1, 15))::BIGINT AS c FROM (SELECT d.doc_id AS rid, unnest({_WORDS}) AS f FROM documents d JOIN labels l ON l.doc_id = d.doc_id)),
y AS (SELECT doc_id AS rid, quality AS half FROM labels)"""

# two rounds of ten classes with one splitter: u and v are the memberships of its two cells
_CLASS_W = """SELECT cls, (b1 * a01 - b0 * a11) / (a00 * a11 - a01 * a01) AS w0, (b0 * a01 - b1 * a00) / (a00 * a11 - a01 * a01) AS w1 FROM (
  SELECT cls, sum(h * u * u) + 1 AS a00, sum(h * u * v) AS a01, sum(h * v * v) + 1 AS a11, sum(g * u) AS b0, sum(g * v) AS b1 FROM {q} GROUP BY cls)"""
_UV = "SELECT rid, max(CASE cell WHEN 0 THEN p END) AS u, max(CASE cell WHEN 1 THEN p END) AS v FROM {p} GROUP BY rid"
_CLASSES2 = f"""WITH {_EMB}, {_p_sql(0, 2)}, {_p_sql(1, 2)}, uva AS ({_UV.format(p='p0')}), uvb AS ({_UV.format(p='p1')}),
qa AS (SELECT uva.*, cls, 0.1 - (label = cls)::INT AS g, 0.09 AS h FROM uva JOIN y ON y.rid = uva.rid, range(10) c(cls)),
wca AS ({_CLASS_W.format(q='qa')}),
sa AS (SELECT rid, qa.cls, 0.3 * (u * w0 + v * w1) AS s FROM qa JOIN wca ON wca.cls = qa.cls),
ea AS (SELECT rid, cls, s, exp(s) / sum(exp(s)) OVER (PARTITION BY rid) AS q FROM sa),
qb AS (SELECT uvb.*, cls, s, q - (label = cls)::INT AS g, greatest(q * (1 - q), 1e-6) AS h FROM uvb JOIN y ON y.rid = uvb.rid JOIN ea ON ea.rid = uvb.rid),
wcb AS ({_CLASS_W.format(q='qb')})
SELECT rid, qb.cls::INT AS cls, floor((s + 0.3 * (u * w0 + v * w1)) * 1000000 + 0.5)::BIGINT AS score FROM qb JOIN wcb ON wcb.cls = qb.cls"""


def _one_round(rows: DataFrame, k: int, lam: float = 1.0, eta: float = 0.3) -> DataFrame:
    """rows (rid, p, score, half) with the round's scores added."""
    import numpy as np

    g, h = losses.logistic_expr(F.col("score"), F.col("half"))
    rows = rows.withColumns({"g": g, "h": h})
    a, b = np.zeros((k, k)), np.zeros(k)
    for r in cat.gram_sums(rows).collect():
        a[r["j"], r["k"]] = a[r["k"], r["j"]] = r["a"]
    for r in cat.grad_sums(rows).collect():
        b[r["j"]] = r["b"]
    return cat.apply_round(rows, solve_scores(a, b, lam)[0].tolist(), eta)


@query(f"{_ROUND1} SELECT rid, floor(score * 1000000 + 0.5)::BIGINT AS score FROM score1")
def boost_one_round(spark, sf_dir):
    rows = _emb_p(spark, sf_dir, 0, 2).join(embedding_rows(spark, sf_dir).select("rid", "half"), "rid").withColumn("score", F.lit(0.0))
    return _one_round(rows, 2).select("rid", F.floor(F.col("score") * 1000000 + 0.5).cast("bigint").alias("score"))


@query(f"{_ROUND2} SELECT rid, floor(score * 1000000 + 0.5)::BIGINT AS score FROM score2")
def boost_two_rounds(spark, sf_dir):
    rows = _emb_p(spark, sf_dir, 0, 2).join(embedding_rows(spark, sf_dir).select("rid", "half"), "rid").withColumn("score", F.lit(0.0))
    after = _one_round(rows, 2).select("rid", "half", "score")
    second = _emb_p(spark, sf_dir, 1, 2).join(after, "rid")
    return _one_round(second, 2).select("rid", F.floor(F.col("score") * 1000000 + 0.5).cast("bigint").alias("score"))


@query(f"""WITH t AS (SELECT c_nationkey AS client, o_totalprice / 100000.0 AS x FROM orders JOIN customer ON c_custkey = o_custkey)
SELECT client, count(*) AS n, sum(floor(x * 1024 + 0.5))::BIGINT AS s, sum(floor(x * x * 1024 + 0.5))::BIGINT AS ss FROM t GROUP BY client""")
def federated_client_sums(spark, sf_dir):
    """What each client sends in the first step: its count and sums."""
    orders = load(spark, sf_dir, "orders", ["o_custkey", "o_totalprice"])
    customers = load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]).withColumnRenamed("c_custkey", "o_custkey")
    x = F.col("o_totalprice") / 100000.0
    unit = lambda v: F.sum(F.floor(v * 1024 + 0.5)).cast("bigint")
    return rel.attach_dimension(orders, customers, "o_custkey").groupBy(F.col("c_nationkey").alias("client")).agg(
        F.count(F.lit(1)).alias("n"), unit(x).alias("s"), unit(x * x).alias("ss")
    )


# --- batches ---------------------------------------------------------------------------------------------------------

_NNZ = f"SELECT doc_id AS rid, len({_WORDS})::BIGINT AS nnz FROM documents"


def _nnz(spark, sf_dir):
    return word_rows(spark, sf_dir).select("rid", F.size("feats").cast("bigint").alias("nnz"))


@query(f"SELECT quantile_disc(nnz, 0.25) AS q25, quantile_disc(nnz, 0.5) AS q50, max(nnz) AS most, sum(nnz)::BIGINT AS total FROM ({_NNZ})")
def nnz_quantiles(spark, sf_dir):
    q = lambda p: F.expr(f"percentile_disc({p}) WITHIN GROUP (ORDER BY nnz)").cast("bigint")
    return _nnz(spark, sf_dir).agg(q(0.25).alias("q25"), q(0.5).alias("q50"), F.max("nnz").alias("most"), F.sum("nnz").alias("total"))


@query(f"""WITH n AS ({_NNZ}), b AS (SELECT greatest(max(nnz), ceil(sum(nnz) / 16.0)) AS budget FROM n)
SELECT rid, nnz, floor(coalesce(sum(nnz) OVER (ORDER BY rid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) / budget)::BIGINT AS batch FROM n, b""")
def nnz_batches(spark, sf_dir):
    return rel.nnz_batches(_nnz(spark, sf_dir), "rid", "nnz", 16)


# --- trees -----------------------------------------------------------------------------------------------------------

_LI = "SELECT l_quantity AS x0, l_discount AS x1, l_tax AS x2, (l_discount >= 0.05 AND l_quantity > 25)::INT AS y FROM lineitem"
_SPLITS = """c AS (SELECT f, v, sum(g) AS g, sum(h) AS h FROM long GROUP BY f, v),
w AS (SELECT f, v, lead(v) OVER (PARTITION BY f ORDER BY v) AS nx, sum(g) OVER (PARTITION BY f ORDER BY v) AS gl, sum(h) OVER (PARTITION BY f ORDER BY v) AS hl,
  sum(g) OVER (PARTITION BY f) AS g, sum(h) OVER (PARTITION BY f) AS h FROM c),
s AS (SELECT f, (v + nx) / 2 AS threshold, 0.5 * (gl*gl/(hl+1) + (g-gl)*(g-gl)/(h-hl+1) - g*g/(h+1)) AS gain, gl, hl, g, h FROM w WHERE nx IS NOT NULL),
best AS (SELECT * FROM s ORDER BY gain DESC, f, threshold LIMIT 1)"""
_LONG = f"li AS ({_LI}), long AS (SELECT unnest([0, 1, 2]) AS f, unnest([x0, x1, x2]) AS v, 0.5 - y AS g, 0.25 AS h FROM li)"


def _li_rows(spark, sf_dir):
    li = load(spark, sf_dir, "lineitem", ["l_quantity", "l_discount", "l_tax"])
    y = ((F.col("l_discount") >= 0.05) & (F.col("l_quantity") > 25)).cast("int")
    return li.select(F.array("l_quantity", "l_discount", "l_tax").alias("x"), y.alias("y")).withColumns({"g": 0.5 - F.col("y"), "h": F.lit(0.25), "node": F.lit(0)})


@query(f"WITH {_LONG}, {_SPLITS} SELECT f, round(threshold, 6) AS threshold, round(gain, 3) AS gain FROM best")
def split_exact_best(spark, sf_dir):
    best = trees.best_splits(trees.candidate_sums(_li_rows(spark, sf_dir), "dense"), 1.0)
    return best.select("f", F.round("threshold", 6).alias("threshold"), F.round("gain", 3).alias("gain"))


@query(f"WITH li AS ({_LI}), long AS (SELECT 0 AS f, ceil(x0 / 5.0) * 5.0 AS v, 0.5 - y AS g, 0.25 AS h FROM li), {_SPLITS} SELECT f, round(threshold, 6) AS threshold, round(gain, 3) AS gain FROM best")
def split_hist_best(spark, sf_dir):
    """Bins of width five on the quantity."""
    edges = [[float(v) for v in range(5, 51, 5)]]
    rows = _li_rows(spark, sf_dir).withColumn("x", trees.to_bins("x", edges))
    best = trees.best_splits(trees.candidate_sums(rows, "dense"), 1.0)
    return best.select("f", F.round("threshold", 6).alias("threshold"), F.round("gain", 3).alias("gain"))


@query(f"""WITH {_LONG}, {_SPLITS} SELECT 'left' AS side, round(-gl / (hl + 1), 6) AS value FROM best UNION ALL SELECT 'right', round(-(g - gl) / (h - hl + 1), 6) FROM best""")
def leaf_values(spark, sf_dir):
    best = trees.best_splits(trees.candidate_sums(_li_rows(spark, sf_dir), "dense"), 1.0)
    value = lambda g, h: F.round(-g / (h + 1), 6)
    sides = F.explode(F.array(
        F.struct(F.lit("left").alias("side"), value(F.col("gl"), F.col("hl")).alias("value")),
        F.struct(F.lit("right").alias("side"), value(F.col("g") - F.col("gl"), F.col("h") - F.col("hl")).alias("value")),
    ))
    return best.select(sides.alias("s")).select("s.side", "s.value")


@query(f"""WITH {_LONG}, {_SPLITS}
SELECT (CASE f WHEN 0 THEN x0 WHEN 1 THEN x1 ELSE x2 END) > threshold AS is_right, count(*) AS n,
  round(any_value(CASE WHEN (CASE f WHEN 0 THEN x0 WHEN 1 THEN x1 ELSE x2 END) <= threshold THEN -gl / (hl + 1) ELSE -(g - gl) / (h - hl + 1) END), 6) AS score
FROM li, best GROUP BY 1""")
def gbdt_depth1(spark, sf_dir):
    rows = _li_rows(spark, sf_dir).select(F.monotonically_increasing_id().alias("rid"), "x", "y")
    model = trees.fit_gbdt_depth(rows, depth=1, rounds=1, eta=1.0, lam=1.0)
    (feature, threshold), = model.trees[0][0].splits.values()
    scored = model.transform(rows)
    is_right = F.element_at("x", int(feature) + 1) > threshold
    return scored.groupBy(is_right.alias("is_right")).agg(F.count(F.lit(1)).alias("n"), F.round(F.first(F.col("score")[0]), 6).alias("score"))


_ONEHOT = "SELECT row_number() OVER () AS rid, 'l_returnflag=' || l_returnflag AS a, 'l_linestatus=' || l_linestatus AS b FROM lineitem"


@query(f"""WITH t AS ({_ONEHOT}) SELECT least(a, b) AS f1, greatest(a, b) AS f2, count(*) AS n FROM t GROUP BY 1, 2""")
def efb_conflicts(spark, sf_dir):
    return bundling.conflicts(_onehot_long(spark, sf_dir))


def _onehot_long(spark, sf_dir):
    li = load(spark, sf_dir, "lineitem", ["l_returnflag", "l_linestatus"]).withColumn("rid", F.monotonically_increasing_id())
    return li.select("rid", F.explode(features.one_hot(["l_returnflag", "l_linestatus"])).alias("x")).select("rid", "x.f", "x.v")


@query("""SELECT 'l_linestatus=' || s AS f, 0 AS bundle FROM (SELECT DISTINCT l_linestatus AS s FROM lineitem)
UNION ALL SELECT 'l_returnflag=' || s, 1 FROM (SELECT DISTINCT l_returnflag AS s FROM lineitem)""")
def efb_bundles(spark, sf_dir):
    """Exclusive features end in one bundle for each column: two status flags, three return flags."""
    found = bundling.bundle_features(_onehot_long(spark, sf_dir))
    first = min(found[f][0] for f in found if f.startswith("l_linestatus"))
    return spark.createDataFrame([(f, 0 if b == first else 1) for f, (b, _) in found.items()], "f string, bundle int")


# --- accuracy --------------------------------------------------------------------------------------------------------

def _scored(spark, sf_dir):
    score = F.floor((F.col("doc_id") * 7919 % 1000 + F.col("quality") * 300) / 100).cast("double")
    return load(spark, sf_dir, "labels").select(F.col("doc_id").alias("rid"), F.col("quality").alias("y"), score.alias("score"))


_SC = "SELECT doc_id AS rid, quality AS y, floor((doc_id * 7919 % 1000 + quality * 300) / 100)::DOUBLE AS score FROM labels"


@query(f"""WITH t AS ({_SC}), r AS (SELECT y, rank() OVER (ORDER BY score) + (count(*) OVER (PARTITION BY score) - 1) / 2.0 AS r FROM t)
SELECT round((sum(r) FILTER (y = 1) - count(*) FILTER (y = 1) * (count(*) FILTER (y = 1) + 1) / 2.0) / (count(*) FILTER (y = 1) * count(*) FILTER (y = 0)), 9) AS auc,
  count(*) FILTER (y = 1) AS positives, count(*) FILTER (y = 0) AS negatives FROM r""")
def auc_binary(spark, sf_dir):
    return metrics.auc(_scored(spark, sf_dir)).withColumn("auc", F.round("auc", 9))


@query(f"""WITH t AS ({_SC}), r AS (SELECT y, row_number() OVER (ORDER BY score DESC, rid) AS k, sum(y) OVER (ORDER BY score DESC, rid ROWS UNBOUNDED PRECEDING) AS hits FROM t)
SELECT round(avg(hits / k), 9) AS ap FROM r WHERE y = 1""")
def average_precision(spark, sf_dir):
    return metrics.average_precision(_scored(spark, sf_dir)).select(F.round("ap", 9).alias("ap"))


_MC = "SELECT doc_id AS rid, list_position(['de','en','es','fr'], lang) - 1 AS y, [(doc_id * 31 % 97)::DOUBLE, (doc_id * 57 % 89)::DOUBLE, (doc_id * 13 % 83)::DOUBLE, (doc_id * 71 % 79)::DOUBLE] AS scores FROM documents"


def _classed(spark, sf_dir):
    d = F.col("doc_id")
    scores = F.array(*[(d * a % b).cast("double") for a, b in ((31, 97), (57, 89), (13, 83), (71, 79))])
    y = (F.array_position(F.array(*map(F.lit, ("de", "en", "es", "fr"))), F.col("lang")) - 1).cast("int")
    return load(spark, sf_dir, "documents", ["doc_id", "lang"]).select(d.alias("rid"), y.alias("y"), scores.alias("scores"))


@query(f"""WITH t AS ({_MC}), l AS (SELECT rid, y, unnest(range(4)) AS cls, unnest(scores) AS s FROM t),
r AS (SELECT cls, (cls = y)::INT AS hit, row_number() OVER (PARTITION BY cls ORDER BY s DESC, rid) AS k, sum((cls = y)::INT) OVER (PARTITION BY cls ORDER BY s DESC, rid ROWS UNBOUNDED PRECEDING) AS hits FROM l)
SELECT round(avg(ap), 9) AS map FROM (SELECT cls, avg(hits / k) AS ap FROM r WHERE hit = 1 GROUP BY cls)""")
def map_multiclass(spark, sf_dir):
    return metrics.mean_ap(_classed(spark, sf_dir)).select(F.round("map", 9).alias("map"))


@query(f"""WITH t AS ({_MC}), q AS (SELECT y, list_position(scores, list_max(scores)) - 1 AS c FROM t)
SELECT y AS actual, count(*) FILTER (c = 0) AS "0", count(*) FILTER (c = 1) AS "1", count(*) FILTER (c = 2) AS "2", count(*) FILTER (c = 3) AS "3" FROM q GROUP BY y""")
def confusion_pivot(spark, sf_dir):
    best = (F.array_position("scores", F.array_max("scores")) - 1).alias("c")
    return metrics.confusion(_classed(spark, sf_dir).select("y", best), "c", "y", [0, 1, 2, 3])


@query(f"""WITH t AS ({_SC}), u AS (SELECT score / 10 - 0.5 AS s, y FROM t)
SELECT round(avg(greatest(s, 0.0) - s * y + ln(1 + exp(-abs(s)))), 9) AS log_loss, round(sqrt(avg((s - y) * (s - y))), 9) AS rmse FROM u""")
def logloss_rmse(spark, sf_dir):
    t = _scored(spark, sf_dir).withColumn("score", F.col("score") / 10 - 0.5)
    both = metrics.log_loss(t).crossJoin(metrics.rmse(t))  # one row each
    return both.select(F.round("log_loss", 9).alias("log_loss"), F.round("rmse", 9).alias("rmse"))


# --- cost ------------------------------------------------------------------------------------------------------------


@query("""SELECT k::INT AS cells, c::INT AS classes, (8 * (2 * k + 1) + 8 * c * (k * (k + 1) // 2 + k))::BIGINT AS bytes FROM (SELECT unnest([64, 1024]) AS k),
(SELECT CASE WHEN n > 2 THEN n ELSE 1 END AS c FROM (SELECT count(DISTINCT l_linestatus) AS n FROM lineitem UNION ALL SELECT count(DISTINCT l_returnflag) FROM lineitem))""")
def comm_volume_ssb(spark, sf_dir):
    """Bytes of a round for two targets of lineitem: a target of two values needs one score, others one a value."""
    targets = ["l_linestatus", "l_returnflag"]
    counted = load(spark, sf_dir, "lineitem", targets).agg(*[F.count_distinct(c).alias(c) for c in targets])
    n = counted.select(F.explode(F.array(*targets)).alias("n")).select(F.when(F.col("n") > 2, F.col("n")).otherwise(1).cast("int").alias("classes"))
    sized = n.select(F.explode(F.array(F.lit(64), F.lit(1024))).alias("cells"), "classes")
    return sized.select("cells", "classes", cost.comm_bytes("ssb", cells=F.col("cells"), classes=F.col("classes")).cast("bigint").alias("bytes"))


@query("""SELECT 'exact' AS method, (16 * (count(DISTINCT l_quantity) + count(DISTINCT l_discount) + count(DISTINCT l_tax) + count(DISTINCT l_extendedprice)))::BIGINT AS bytes FROM lineitem
UNION ALL SELECT 'hist', (16 * 4 * 255)::BIGINT""")
def comm_volume_gbdt(spark, sf_dir):
    """Bytes of one level of one node: exact candidates from the data beside 255 bins."""
    cols = ["l_quantity", "l_discount", "l_tax", "l_extendedprice"]
    row = load(spark, sf_dir, "lineitem", cols).agg(*[F.count_distinct(c).alias(c) for c in cols]).first()
    exact = cost.comm_bytes("exact", levels=[(1, sum(row))])
    hist = cost.comm_bytes("hist", nodes=1, features=len(cols), bins=255)
    return spark.createDataFrame([("exact", int(exact)), ("hist", int(hist))], "method string, bytes long")


@query(f"""WITH f AS (SELECT unnest({_WORDS}) AS f FROM documents)
SELECT 'row' AS layout, (64 * count(*))::BIGINT AS calls FROM f UNION ALL SELECT 'column', (64 * count(DISTINCT f))::BIGINT FROM f""")
def hash_call_counts(spark, sf_dir):
    row = word_rows(spark, sf_dir).select(F.explode("feats.f").alias("f")).agg(F.count("f"), F.count_distinct("f")).first()
    return spark.createDataFrame([(x, cost.hash_calls(x, 64, row[1], row[0])) for x in ("row", "column")], "layout string, calls long")


@query(f"""WITH m AS (SELECT count(DISTINCT f) AS m FROM (SELECT unnest({_WORDS}) AS f FROM documents))
SELECT (100 * 64 * 10)::BIGINT AS ssb_numbers, (100 * 10 * 127)::BIGINT AS tree_numbers, (8 * 64 * m)::BIGINT AS weight_matrix_bytes FROM m""")
def model_size(spark, sf_dir):
    m = word_rows(spark, sf_dir).select(F.explode("feats.f").alias("f")).agg(F.count_distinct("f")).first()[0]
    row = (cost.model_numbers("ssb", 100, 64, 10), cost.model_numbers("trees", 100, 64, 10), cost.weight_matrix_bytes(m, 64))
    return spark.createDataFrame([row], "ssb_numbers long, tree_numbers long, weight_matrix_bytes long")


#: Machines of the scaling measures.
MACHINES = [4, 8, 16, 32, 64]
#: Bytes a second by bandwidth step, fastest first.
BANDWIDTHS = [1e9, 1e8, 1e7, 1e6, 1e5]


_SENT = """sent AS (SELECT 'depth_trees' AS method, (16 * (count(DISTINCT l_quantity) + count(DISTINCT l_discount) + count(DISTINCT l_tax) + count(DISTINCT l_extendedprice)))::BIGINT AS bytes FROM lineitem
UNION ALL SELECT 'leaf_trees', (16 * 4 * 255)::BIGINT UNION ALL SELECT 'soft_split', (8 * (2 * 64 + 1) + 8 * (64 * 65 // 2 + 64))::BIGINT)"""


def _sent(spark, sf_dir):
    """(method, bytes): size 64 beside one level of one node on four columns of lineitem, all values and 255 bins."""
    cols = ["l_quantity", "l_discount", "l_tax", "l_extendedprice"]
    values = load(spark, sf_dir, "lineitem", cols).agg(sum(F.count_distinct(c) for c in cols).alias("values"))
    sent = {
        "depth_trees": cost.comm_bytes("exact", levels=[(1, F.col("values"))]), "leaf_trees": F.lit(cost.comm_bytes("hist", nodes=1, features=len(cols), bins=255)),
        "soft_split": F.lit(cost.comm_bytes("ssb", cells=64)),
    }
    return values.select(F.inline(F.array(*[F.struct(F.lit(m).alias("method"), b.cast("bigint").alias("bytes")) for m, b in sent.items()])))


_STEPS = "(VALUES " + ", ".join(f"({i}, {b}::DOUBLE)" for i, b in enumerate(BANDWIDTHS, 1)) + ") b(step, bandwidth)"


@query(f"""WITH {_SENT}, t AS (SELECT method, step, 1.0::DOUBLE + bytes / bandwidth AS s FROM sent, {_STEPS})
SELECT method, step::INT AS step, round(s / first_value(s) OVER (PARTITION BY method ORDER BY step), 6) AS ratio FROM t""")
def bandwidth_ratios(spark, sf_dir):
    """Modelled seconds at one second of compute, not measured ones."""
    steps = F.inline(F.array(*[F.struct(F.lit(i).alias("step"), F.lit(b).alias("bandwidth")) for i, b in enumerate(BANDWIDTHS, 1)]))
    t = _sent(spark, sf_dir).select("*", steps).withColumn("s", cost.modelled_round_s(F.lit(1.0), F.col("bytes"), F.col("bandwidth")))
    first = F.first("s").over(Window.partitionBy("method").orderBy("step"))
    return t.select("method", "step", F.round(F.col("s") / first, 6).alias("ratio"))


#: Additions and multiplications a row and exchanges a round by method: four columns and size 64; trees of six levels.
WORK = {"depth_trees": (4 * 6, 6), "leaf_trees": (4 * 6, 6), "soft_split": (4 * 64 + 64 * 65 // 2 + 64, 1)}
_BY_MACHINES = f"""WITH {_SENT}, d AS (SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1), m AS (SELECT unnest({MACHINES}) AS step),
f AS (SELECT step, max(n)::BIGINT AS fullest FROM (SELECT step, sum(n) AS n FROM d, m GROUP BY step, l_orderkey % step) GROUP BY step),
w(method, work, exchanges) AS (VALUES {", ".join(f"('{m}', {w}, {x})" for m, (w, x) in WORK.items())}),
t AS (SELECT sent.method, step, (fullest * work + step * exchanges * bytes)::DOUBLE / 1e9 AS s FROM f, sent JOIN w ON sent.method = w.method)"""


def _by_machines(spark, sf_dir):
    """(method, step, s): modelled seconds a round with lineitem dealt by order to so many machines, not measured ones.

    The fullest machine works at 1e9 operations a second; then all send their bytes over one line of 1e9 bytes a second.
    """
    dealt = load(spark, sf_dir, "lineitem", ["l_orderkey"]).groupBy((F.col("l_orderkey") % max(MACHINES)).alias("k")).agg(F.count(F.lit(1)).alias("n"))
    steps = dealt.select("k", "n", F.explode(F.array(*map(F.lit, MACHINES))).alias("step"))
    fullest = steps.groupBy("step", (F.col("k") % F.col("step")).alias("machine")).agg(F.sum("n").alias("n")).groupBy("step").agg(F.max("n").alias("fullest"))
    work = F.create_map(*[v for m, (w, _) in WORK.items() for v in (F.lit(m), F.lit(w))])
    exchanges = F.create_map(*[v for m, (_, x) in WORK.items() for v in (F.lit(m), F.lit(x))])
    t = fullest.crossJoin(F.broadcast(_sent(spark, sf_dir)))  # three methods
    return t.select("method", "step", ((F.col("fullest") * work[F.col("method")] + F.col("step") * exchanges[F.col("method")] * F.col("bytes")).cast("double") / 1e9).alias("s"))


@query(f"{_BY_MACHINES} SELECT method, step::INT AS step, round(s / first_value(s) OVER (PARTITION BY method ORDER BY step), 6) AS ratio, round(4.0 / step, 6)::DOUBLE AS ideal FROM t")
def scaling_ratios(spark, sf_dir):
    first = F.first("s").over(Window.partitionBy("method").orderBy("step"))
    return _by_machines(spark, sf_dir).select("method", "step", F.round(F.col("s") / first, 6).alias("ratio"), F.round(F.lit(4.0) / F.col("step"), 6).alias("ideal"))


@query(f"{_BY_MACHINES} SELECT a.method, a.step::INT AS step, round(a.s / b.s, 6) AS factor FROM t a JOIN t b ON a.step = b.step AND b.method = 'soft_split' WHERE a.method <> 'soft_split'")
def speedup_table(spark, sf_dir):
    t = _by_machines(spark, sf_dir)
    own = t.filter("method = 'soft_split'").select("step", F.col("s").alias("own"))
    return t.filter("method <> 'soft_split'").join(own, "step").select("method", "step", F.round(cost.speedup(F.col("s"), F.col("own")), 6).alias("factor"))


# --- joins -------------------------------------------------------------------------------------------------------------


@query("""SELECT n_name, c_mktsegment, count(*) AS n, sum(floor(l_quantity))::BIGINT AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey
JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2""")
def join_star(spark, sf_dir):
    li = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_quantity"])
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]).withColumnRenamed("o_orderkey", "l_orderkey")
    customers = load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey", "c_mktsegment"]).withColumnRenamed("c_custkey", "o_custkey")
    nations = load(spark, sf_dir, "nation", ["n_nationkey", "n_name"]).withColumnRenamed("n_nationkey", "c_nationkey")
    wide = rel.attach_dimension(rel.attach_dimension(li.join(orders, "l_orderkey"), customers, "o_custkey"), nations, "c_nationkey")
    return wide.groupBy("n_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.sum(F.floor("l_quantity")).cast("bigint").alias("qty"))


@query("SELECT lang, count(*) AS docs, count(toxic) AS labelled, sum(toxic)::BIGINT AS toxic FROM documents LEFT JOIN labels ON documents.doc_id = labels.doc_id GROUP BY lang")
def join_left_labels(spark, sf_dir):
    joined = load(spark, sf_dir, "documents", ["doc_id", "lang"]).join(load(spark, sf_dir, "labels"), "doc_id", "left")
    return joined.groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.count("toxic").alias("labelled"), F.sum("toxic").alias("toxic"))


@query("""SELECT (e.user_id IS NULL) AS no_event, (c.c_custkey IS NULL) AS no_customer, count(*) AS n
FROM (SELECT DISTINCT user_id FROM events) e FULL JOIN customer c ON e.user_id = c.c_custkey GROUP BY 1, 2""")
def join_full_outer(spark, sf_dir):
    users = load(spark, sf_dir, "events", ["user_id"]).distinct()
    both = users.join(load(spark, sf_dir, "customer", ["c_custkey"]), F.col("user_id") == F.col("c_custkey"), "full")
    return both.groupBy(F.col("user_id").isNull().alias("no_event"), F.col("c_custkey").isNull().alias("no_customer")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT source, count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1) GROUP BY source")
def join_semi(spark, sf_dir):
    toxic = load(spark, sf_dir, "labels").filter("toxic = 1")
    return rel.keep_ids(load(spark, sf_dir, "documents", ["doc_id", "source"]), toxic, "doc_id").groupBy("source").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT lang, count(*) AS n FROM documents WHERE NOT EXISTS (SELECT 1 FROM labels WHERE labels.doc_id = documents.doc_id) GROUP BY lang")
def join_anti(spark, sf_dir):
    labels = load(spark, sf_dir, "labels", ["doc_id"])
    return rel.drop_ids(load(spark, sf_dir, "documents", ["doc_id", "lang"]), labels, "doc_id").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@query("""SELECT k::INT AS cells, e AS eta, l AS lam, fold, held FROM (SELECT unnest([16, 64]) AS k), (SELECT unnest([0.1::DOUBLE, 0.3::DOUBLE]) AS e), (SELECT unnest([0.0::DOUBLE, 0.1::DOUBLE, 1.0::DOUBLE]) AS l),
(SELECT (o_orderkey % 3)::INT AS fold, count(*) AS held FROM orders GROUP BY 1)""")
def join_cross_grid(spark, sf_dir):
    """The grid beside the folds of the orders and the rows that each holds out."""
    from .operators.grid import grid_table

    folds = load(spark, sf_dir, "orders", ["o_orderkey"]).groupBy((F.col("o_orderkey") % 3).cast("int").alias("fold")).agg(F.count(F.lit(1)).alias("held"))
    return grid_table(spark, {"cells": [16, 64], "eta": [0.1, 0.3], "lam": [0.0, 0.1, 1.0]}, folds)


@query("SELECT (floor(l_quantity / 10))::INT AS bin, count(*) AS n FROM lineitem GROUP BY 1")
def join_range_bins(spark, sf_dir):
    binned = rel.assign_bins(load(spark, sf_dir, "lineitem", ["l_quantity"]), "l_quantity", [10, 20, 30, 40, 50])
    return binned.groupBy("bin").agg(F.count(F.lit(1)).alias("n"))


@query("""SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id
WHERE a.event_type = 'click' AND b.event_type = 'purchase' AND floor(epoch(b.ts)) - floor(epoch(a.ts)) BETWEEN 0 AND 7200""")
def join_interval(spark, sf_dir):
    ev = load(spark, sf_dir, "events", ["event_id", "user_id", "event_type", "ts"])
    clicks = ev.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("ts").alias("c_ts"))
    buys = ev.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("ts").alias("p_ts"))
    return rel.join_within(clicks, buys, "c_ts", "p_ts", 7200, ["user_id"]).select("click_id", "purchase_id")


@query("""WITH c AS (SELECT * FROM events WHERE event_type = 'purchase'), v AS (SELECT user_id, ts, value FROM events WHERE event_type = 'view')
SELECT c.event_id, v.value AS last_value FROM c ASOF LEFT JOIN v ON c.user_id = v.user_id AND c.ts >= v.ts""")
def join_asof(spark, sf_dir):
    ev = load(spark, sf_dir, "events", ["event_id", "user_id", "event_type", "ts", "value"])
    left = ev.filter("event_type = 'purchase'").select("event_id", "user_id", "ts")
    right = ev.filter("event_type = 'view'").select("user_id", "ts", "value")
    return rel.asof_join(left, right, "ts", ["user_id"], "value").select("event_id", "last_value")


@query(f"SELECT role, count(*) AS words, count(DISTINCT w) AS kinds FROM (SELECT role, unnest({_WORDS}) AS w FROM conversations) GROUP BY role")
def join_lateral_words(spark, sf_dir):
    from .functions.udf import register

    register(spark)
    load(spark, sf_dir, "conversations", ["role", "text"]).createOrReplaceTempView("ssb_turns")
    return spark.sql("SELECT role, count(*) AS words, count(DISTINCT w.word) AS kinds FROM ssb_turns, LATERAL explode_features(text) w GROUP BY role")


# --- aggregates ----------------------------------------------------------------------------------------------------------


@query("SELECT lang, source, grouping_id(lang, source)::BIGINT AS gid, count(*) AS n, sum(n_chars)::BIGINT AS total FROM documents GROUP BY CUBE (lang, source)")
def agg_cube(spark, sf_dir):
    return rel.score_report(load(spark, sf_dir, "documents", ["lang", "source", "n_chars"]), ["lang", "source"], "n_chars", "cube")


@query("SELECT lang, source, grouping_id(lang, source)::BIGINT AS gid, count(*) AS n, sum(n_chars)::BIGINT AS total FROM documents GROUP BY ROLLUP (lang, source)")
def agg_rollup(spark, sf_dir):
    return rel.score_report(load(spark, sf_dir, "documents", ["lang", "source", "n_chars"]), ["lang", "source"], "n_chars", "rollup")


@query("SELECT event_type, coalesce(user_id % 5, -1) AS grp, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (user_id % 5), ())")
def agg_grouping_sets(spark, sf_dir):
    load(spark, sf_dir, "events", ["event_type", "user_id"]).createOrReplaceTempView("ssb_events")
    return spark.sql("SELECT event_type, coalesce(user_id % 5, -1) AS grp, count(*) AS n FROM ssb_events GROUP BY event_type, user_id % 5 GROUPING SETS ((event_type), (user_id % 5), ())")


@query("SELECT p_brand, quantile_disc(p_size, 0.5)::INT AS median, quantile_disc(p_size, 0.9)::INT AS p90, round(stddev_samp(p_size), 6) AS sd, round(corr(p_size, p_retailprice), 6) AS r FROM part GROUP BY 1")
def agg_quantiles(spark, sf_dir):
    q = lambda p: F.expr(f"percentile_disc({p}) WITHIN GROUP (ORDER BY p_size)").cast("int")
    return load(spark, sf_dir, "part", ["p_brand", "p_size", "p_retailprice"]).groupBy("p_brand").agg(
        q(0.5).alias("median"), q(0.9).alias("p90"), F.round(F.stddev_samp("p_size"), 6).alias("sd"), F.round(F.corr("p_size", "p_retailprice"), 6).alias("r")
    )


@query("SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS \"F\", count(*) FILTER (o_orderstatus = 'O') AS \"O\", count(*) FILTER (o_orderstatus = 'P') AS \"P\" FROM orders GROUP BY 1")
def agg_pivot(spark, sf_dir):
    return load(spark, sf_dir, "orders", ["o_orderpriority", "o_orderstatus"]).groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0)


@query("SELECT doc_id, 'quality' AS task, quality AS y FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def agg_unpivot(spark, sf_dir):
    return load(spark, sf_dir, "labels").unpivot("doc_id", ["quality", "toxic"], "task", "y")


@query("SELECT l_returnflag, max(l_extendedprice) AS best, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def agg_argmax_distinct(spark, sf_dir):
    li = load(spark, sf_dir, "lineitem", ["l_returnflag", "l_extendedprice", "l_partkey"])
    best = F.max_by("l_extendedprice", "l_extendedprice").alias("best")
    return li.groupBy("l_returnflag").agg(best, F.count_distinct("l_partkey").alias("parts"))


@query("SELECT label, j::INT AS j, sum(floor(v * 1048576 + 0.5))::BIGINT AS s FROM (SELECT label, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) - 1 AS j FROM embeddings) GROUP BY 1, 2")
def agg_vector_sum(spark, sf_dir):
    scaled = F.transform("x", lambda v: fixed(v))
    return rel.vector_sum(embedding_rows(spark, sf_dir).select("label", scaled.alias("v")), "v", ["label"]).select("label", "j", "s")


@query()
def agg_approximate(spark, sf_dir):
    words = word_rows(spark, sf_dir).select(F.explode("feats.f").alias("f"))
    return rel.feature_count(words, exact=False)


# --- windows, order, sets -----------------------------------------------------------------------------------------------


@query("""SELECT doc_id, row_number() OVER w AS rn, rank() OVER w2 AS rk, dense_rank() OVER w2 AS dr, round(percent_rank() OVER w2, 9) AS pr, round(cume_dist() OVER w2, 9) AS cd, ntile(4) OVER w AS nt
FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id), w2 AS (PARTITION BY lang ORDER BY n_chars)""")
def window_ranks(spark, sf_dir):
    docs = load(spark, sf_dir, "documents", ["doc_id", "lang", "n_chars"])
    w, w2 = Window.partitionBy("lang").orderBy("n_chars", "doc_id"), Window.partitionBy("lang").orderBy("n_chars")
    return docs.select(
        "doc_id", F.row_number().over(w).cast("bigint").alias("rn"), F.rank().over(w2).cast("bigint").alias("rk"), F.dense_rank().over(w2).cast("bigint").alias("dr"),
        F.round(F.percent_rank().over(w2), 9).alias("pr"), F.round(F.cume_dist().over(w2), 9).alias("cd"), F.ntile(4).over(w).cast("bigint").alias("nt"),
    )


@query("""SELECT event_id, coalesce(lag(floor(value * 100)::BIGINT) OVER w, -1) AS before, coalesce(lead(floor(value * 100)::BIGINT, 2) OVER w, -1) AS later, first_value(event_id) OVER w AS f, coalesce(nth_value(event_id, 2) OVER w, -1) AS second
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""")
def window_analytic(spark, sf_dir):
    ev = load(spark, sf_dir, "events", ["event_id", "user_id", "ts", "value"]).withColumn("c", F.floor(F.col("value") * 100).cast("bigint"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    known = lambda c, name: F.coalesce(c.over(w), F.lit(-1).cast("bigint")).alias(name)
    return ev.select("event_id", known(F.lag("c"), "before"), known(F.lead("c", 2), "later"), F.first("event_id").over(w).alias("f"), known(F.nth_value("event_id", 2), "second"))


@query("""SELECT event_id, sum(floor(value * 100)::BIGINT) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS moving,
count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS near FROM events""")
def window_frames(spark, sf_dir):
    ev = load(spark, sf_dir, "events", ["event_id", "user_id", "ts", "value"]).withColumn("c", F.floor(F.col("value") * 100).cast("bigint"))
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, Window.currentRow)
    near = Window.partitionBy("user_id").orderBy("event_id").rangeBetween(-100, Window.currentRow)
    return ev.select("event_id", F.sum("c").over(rows).alias("moving"), F.count(F.lit(1)).over(near).alias("near"))


@query("SELECT o_orderkey, coalesce(sum(floor(o_totalprice)::BIGINT) OVER (ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before FROM orders")
def window_prefix_sum(spark, sf_dir):
    rows = load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]).withColumn("v", F.floor("o_totalprice").cast("bigint"))
    return metrics.prefix_sum(rows, "o_orderkey", "v", "before").select("o_orderkey", "before")


@query("SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 20")
def topk_global(spark, sf_dir):
    return rel.top_scored(load(spark, sf_dir, "part", ["p_partkey", "p_retailprice"]), "p_retailprice", 20, "p_partkey")


@query("SELECT source, doc_id, n_chars FROM (SELECT source, doc_id, n_chars, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS k FROM documents) WHERE k <= 3")
def topk_per_group(spark, sf_dir):
    return rel.top_per(load(spark, sf_dir, "documents", ["source", "doc_id", "n_chars"]), "source", "n_chars", 3, "doc_id").drop("place")


@query("SELECT c_custkey FROM customer ORDER BY c_acctbal, c_custkey LIMIT 10 OFFSET 25")
def sort_page(spark, sf_dir):
    return rel.page(load(spark, sf_dir, "customer", ["c_custkey", "c_acctbal"]), ["c_acctbal", "c_custkey"], 10, 25).select("c_custkey")


@query(f"""WITH a AS (SELECT DISTINCT unnest({_WORDS}) AS w FROM conversations WHERE role = 'user'), b AS (SELECT DISTINCT unnest({_WORDS}) AS w FROM conversations WHERE role = 'assistant')
SELECT 'both' AS kind, count(*) AS n FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'only_first', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)
UNION ALL SELECT 'all', count(*) FROM (SELECT * FROM a UNION ALL SELECT * FROM b)""")
def set_vocabulary_drift(spark, sf_dir):
    turns = load(spark, sf_dir, "conversations", ["role", "text"])
    words = lambda role: turns.filter(F.col("role") == role).select(F.explode(features.tokens(F.col("text"))).alias("w")).distinct()
    a, b = words("user"), words("assistant")
    count = lambda df, kind: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(kind).alias("kind"), "n")
    return count(rel.set_op(a, b, "intersect"), "both").unionByName(count(rel.set_op(a, b, "except"), "only_first")).unionByName(count(rel.set_op(a, b, "union"), "all"))


@query("""WITH a AS (SELECT l_returnflag AS k FROM lineitem WHERE l_quantity < 5), b AS (SELECT l_returnflag AS k FROM lineitem WHERE l_quantity > 49)
SELECT 'except_all' AS kind, k, count(*) AS n FROM (SELECT k FROM a EXCEPT ALL SELECT k FROM b) GROUP BY k UNION ALL
SELECT 'intersect_all', k, count(*) FROM (SELECT k FROM a INTERSECT ALL SELECT k FROM b) GROUP BY k""")
def set_multisets(spark, sf_dir):
    li = load(spark, sf_dir, "lineitem", ["l_returnflag", "l_quantity"])
    a, b = (li.filter(c).select(F.col("l_returnflag").alias("k")) for c in ("l_quantity < 5", "l_quantity > 49"))
    out = [rel.set_op(a, b, kind).groupBy("k").agg(F.count(F.lit(1)).alias("n")).select(F.lit(kind).alias("kind"), "k", "n") for kind in ("except_all", "intersect_all")]
    return out[0].unionByName(out[1])


@query("SELECT min(doc_id) AS doc_id FROM documents GROUP BY text")
def dedup_text(spark, sf_dir):
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"]).select("doc_id", F.sha2("text", 256).alias("t"))
    return rel.drop_copies(docs, ["t"], "doc_id").select("doc_id")


@query(f"SELECT doc_id FROM documents WHERE {_CODE.format(chr(39) + '0|' + chr(39) + ' || doc_id')} < 429496729")
def sample_by_hash(spark, sf_dir):
    return rel.hash_sample(load(spark, sf_dir, "documents", ["doc_id"]), "doc_id", 0.1)


@query(f"SELECT l_orderkey, l_linenumber, copy::INT AS copy FROM lineitem, range(10) c(copy) WHERE {_CODE.format(chr(39) + '0|' + chr(39) + ' || l_orderkey')} < 429496729")
def kdd_sub_replicate(spark, sf_dir):
    """A tenth of the orders, each line ten times."""
    sampled = rel.hash_sample(load(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber"]), "l_orderkey", 0.1)
    return rel.replicate(sampled, 10)


@query("SELECT (doc_id % 5 = 0) AS test, lang, count(*) AS n FROM documents GROUP BY 1, 2")
def split_train_test(spark, sf_dir):
    docs = load(spark, sf_dir, "documents", ["doc_id", "lang"])
    return docs.groupBy((F.col("doc_id") % 5 == 0).alias("test"), "lang").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT count(*) FILTER (lang = 'es') AS unseen, count(*) AS rows FROM documents WHERE doc_id % 5 = 0")
def unseen_class_check(spark, sf_dir):
    """Test rows of a class left out of training, found by an anti-join of classes."""
    docs = load(spark, sf_dir, "documents", ["doc_id", "lang"])
    train = docs.filter("doc_id % 5 <> 0 AND lang <> 'es'").select("lang").distinct()
    test = docs.filter("doc_id % 5 = 0")
    unseen = rel.drop_ids(test, train, "lang").agg(F.count(F.lit(1)).alias("unseen"))
    return unseen.crossJoin(test.agg(F.count(F.lit(1)).alias("rows")))  # one row each


# --- expressions -----------------------------------------------------------------------------------------------------------


@query(f"SELECT doc_id AS rid, len({_WORDS})::INT AS words, len(list_filter(string_split(translate(lower(text), chr(10)||chr(13)||chr(9), '   '), ' '), lambda w: w <> ''))::INT AS tokens FROM documents")
def word_features(spark, sf_dir):
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"])
    return docs.select(F.col("doc_id").alias("rid"), F.size(features.word_set(F.col("text"))).alias("words"), F.size(features.tokens(F.col("text"))).alias("tokens"))


@query("SELECT doc_id, round((length(lower(text)) - length(replace(lower(text), 'e', ''))) / greatest(length(lower(text)), 1)::DOUBLE, 9) AS e FROM documents")
def letter_features(spark, sf_dir):
    return load(spark, sf_dir, "documents", ["doc_id", "text"]).select("doc_id", F.round(features.letter_shares(F.col("text"), "e")[0], 9).alias("e"))


@query("SELECT page_id, length(regexp_replace(regexp_replace(html, '(?is)<script[^>]*>.*?</script>|<style[^>]*>.*?</style>', ' ', 'g'), '<[^>]*>', ' ', 'g')) AS n FROM pages")
def html_text(spark, sf_dir):
    return load(spark, sf_dir, "pages", ["page_id", "html"]).select("page_id", F.length(features.strip_html(F.col("html"))).cast("bigint").alias("n"))


@query("SELECT 'k=' || (props->>'k') AS f, count(*) AS n FROM events GROUP BY 1")
def json_features(spark, sf_dir):
    feats = features.json_features(F.col("props"), ["k"])
    return load(spark, sf_dir, "events", ["props"]).select(F.explode(feats).alias("x")).groupBy("x.f").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT hour(ts)::INT AS h, (dayofweek(ts) + 1)::INT AS d, count(*) AS n, floor(max(epoch(ts)))::BIGINT AS latest FROM events GROUP BY 1, 2")
def timestamp_parts(spark, sf_dir):
    ts = F.col("ts").cast("timestamp")
    return load(spark, sf_dir, "events", ["ts"]).groupBy(F.hour(ts).alias("h"), F.dayofweek(ts).alias("d")).agg(F.count(F.lit(1)).alias("n"), F.max(F.unix_timestamp(ts)).alias("latest"))


@query("""SELECT p_partkey, upper(substr(p_name, 1, 3)) AS head, length(p_name)::INT AS n, levenshtein(p_brand, p_type)::INT AS d, (p_type LIKE '%S%') AS has_s,
CASE WHEN p_size BETWEEN 1 AND 10 THEN 'small' WHEN p_size IN (11, 12) THEN 'mid' ELSE 'large' END AS class FROM part""")
def string_expressions(spark, sf_dir):
    size = F.when(F.col("p_size").between(1, 10), "small").when(F.col("p_size").isin(11, 12), "mid").otherwise("large")
    return load(spark, sf_dir, "part").select(
        "p_partkey", F.upper(F.substring("p_name", 1, 3)).alias("head"), F.length("p_name").alias("n"), F.levenshtein("p_brand", "p_type").alias("d"),
        F.col("p_type").like("%S%").alias("has_s"), size.alias("class"),
    )


@query("""SELECT vec_id, round(list_sum(list_transform(embedding[1:4], lambda v: v::DOUBLE * v::DOUBLE)), 6) AS norm4, len(list_filter(embedding, lambda v: v > 0))::INT AS positives,
round(list_max(embedding)::DOUBLE, 6) AS top FROM embeddings""")
def array_expressions(spark, sf_dir):
    x = F.col("x")
    norm = F.aggregate(F.transform(F.slice(x, 1, 4), lambda v: v * v), F.lit(0.0), lambda a, v: a + v)
    return embedding_rows(spark, sf_dir).select(F.col("rid").alias("vec_id"), F.round(norm, 6).alias("norm4"), F.size(F.filter(x, lambda v: v > 0)).alias("positives"), F.round(F.array_max(x), 6).alias("top"))


@query("SELECT event_type, user_id, sum(n)::BIGINT AS n FROM (SELECT event_type, user_id, 1 AS n FROM events WHERE value > 50) GROUP BY 1, 2")
def map_expressions(spark, sf_dir):
    """Counts by way of a map column: entries filtered, then spread again."""
    ev = load(spark, sf_dir, "events", ["event_type", "user_id", "value"])
    pairs = ev.select("event_type", "user_id", F.create_map(F.lit("value"), F.col("value")).alias("m"))
    kept = pairs.select("event_type", "user_id", F.explode(F.map_filter("m", lambda k, v: v > 50)))
    return kept.groupBy("event_type", "user_id").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT c_custkey, round(sqrt(abs(c_acctbal)), 6) AS r, round(ln(1 + abs(c_acctbal)), 6) AS l, sign(c_acctbal)::INT AS s, greatest(c_nationkey, 10)::INT AS g, (c_custkey & 7)::INT AS b FROM customer")
def math_expressions(spark, sf_dir):
    a = F.abs("c_acctbal")
    return load(spark, sf_dir, "customer").select(
        "c_custkey", F.round(F.sqrt(a), 6).alias("r"), F.round(F.log1p(a), 6).alias("l"), F.signum("c_acctbal").cast("int").alias("s"),
        F.greatest("c_nationkey", F.lit(10)).alias("g"), F.col("c_custkey").bitwiseAND(F.lit(7).cast("long")).cast("int").alias("b"),
    )


# --- training, experiments, streaming (no SQL form; tests hold them against brute force and invariants) ----------------


def _workload(name: str, spark: SparkSession, sf_dir: str, cells: int = 16):
    from .experiments import workload

    return workload(name, spark, sf_dir, cells)


def _curve_of(spark, sf_dir, name, rounds, cells=16, engine="jobs", **kw):
    from .operators.boost import fit

    w = _workload(name, spark, sf_dir, cells)
    model = fit(w.train, w.spec, w.loss, rounds, classes=w.classes, engine=engine, **kw)
    return metrics.curve(model.staged(w.test), w.metric).select("round", F.round("value", 9).alias("value"))


def _trained(spark, sf_dir, loss="logistic", **kw):
    """Scores of all embeddings after two rounds of a trainer with two cells, drawn by md5 so that SQL has them too."""
    from .operators.boost import fit
    from .plans.kernel import Spec

    rows = embedding_rows(spark, sf_dir).select("rid", "x", F.col("half").cast("double").alias("y"))
    model = fit(rows, Spec("dense", 2, 64, hash_fn="md5"), loss, rounds=2, **kw)
    return _scores_of(model.transform(rows.select("rid", "x")))


def _scores_of(scored: DataFrame) -> DataFrame:
    return scored.select("rid", F.floor(F.col("score")[0] * 1000000 + 0.5).cast("bigint").alias("score"))


@query(f"{_ROUND2} {_SCORES}")
def ssb_train_binary(spark, sf_dir):
    return _trained(spark, sf_dir)


@query(f"{_ROUND2} {_SCORES}")
def ssb_train_lookahead(spark, sf_dir):
    """Statistics scanned round by round instead of from second moments."""
    return _trained(spark, sf_dir, lookahead=1)


@query(f"{_ROUND2} {_SCORES}")
def ssb_train_carried_state(spark, sf_dir):
    return _trained(spark, sf_dir, state="carry", partitions=3)


@query(f"{_ROUND2} {_SCORES}")
def ssb_train_driver_state(spark, sf_dir):
    return _trained(spark, sf_dir, state="driver")


@query(f"{_round2_sql(_EMB, _SQUARED)} {_SCORES}")
def ssb_train_squared(spark, sf_dir):
    return _trained(spark, sf_dir, "squared")


@query(_CLASSES2)
def ssb_train_multiclass(spark, sf_dir):
    from .operators.boost import fit
    from .plans.kernel import Spec

    rows = embedding_rows(spark, sf_dir).select("rid", "x", F.col("label").cast("double").alias("y"))
    model = fit(rows, Spec("dense", 2, 64, hash_fn="md5"), "softmax", rounds=2, classes=10)
    long = model.transform(rows.select("rid", "x")).select("rid", F.posexplode("score").alias("cls", "s"))
    return long.select("rid", "cls", F.floor(F.col("s") * 1000000 + 0.5).cast("bigint").alias("score"))


@query(f"{_round2_sql(_WORD_HEAD, _LOGISTIC, _word_z_sql)} {_SCORES}")
def ssb_train_hashed_words(spark, sf_dir):
    """The sparse trainer: words named by md5, weights by the trainers' own integer steps."""
    from .operators.boost import fit
    from .plans.kernel import Spec

    labels = load(spark, sf_dir, "labels", ["doc_id", "quality"]).select(F.col("doc_id").alias("rid"), F.col("quality").cast("double").alias("y"))
    named = word_rows(spark, sf_dir).filter(F.size("feats") > 0)
    rows = named.select("rid", *features.coded(F.col("feats"), "md5")).join(labels, "rid")
    model = fit(rows, Spec("sparse", 2), rounds=2)
    return _scores_of(model.transform(rows.select("rid", "codes", "vals")))


@query()
def ssb_curve_binary(spark, sf_dir):
    return _curve_of(spark, sf_dir, "emb_half", 8)


@query()
def ssb_curve_multiclass(spark, sf_dir):
    return _curve_of(spark, sf_dir, "letters_lang", 5)


@query()
def ssb_train_separate_splitters(spark, sf_dir):
    return _curve_of(spark, sf_dir, "letters_lang", 3, share=False)


@query()
def ssb_train_sparse_words(spark, sf_dir):
    return _curve_of(spark, sf_dir, "words_quality", 5)


@query(f"{_ROUND2} {_SCORES}")
def ssb_train_barrier(spark, sf_dir):
    """Two tasks that exchange their sums."""
    return _trained(spark, sf_dir, engine="barrier", partitions=2)


@query(f"{_ROUND2} {_SCORES}")
def ssb_train_local(spark, sf_dir):
    return _trained(spark, sf_dir, engine="local")


@query(f"{_ROUND2} {_SCORES}")
def ssb_train_federated(spark, sf_dir):
    """Seven clients that send sums only."""
    from .operators.boost import fit_federated
    from .plans.kernel import Spec

    rows = embedding_rows(spark, sf_dir).select("rid", "x", F.col("half").cast("double").alias("y"), (F.col("rid") % 7).alias("client"))
    model, _ = fit_federated(rows, "client", Spec("dense", 2, 64, hash_fn="md5"), rounds=2)
    return _scores_of(model.transform(rows.select("rid", "x")))


@query("""SELECT r::INT AS round, step, client::VARCHAR AS client, CASE step WHEN 'statistics' THEN 8 * (2 * 8 + 1) ELSE 8 * (8 * 9 // 2 + 8 + 2) END::BIGINT AS bytes
FROM range(2) a(r), (VALUES ('statistics'), ('sums')) b(step), (SELECT DISTINCT user_id % 10 AS client FROM events) c""")
def federated_messages(spark, sf_dir):
    """The message log of two rounds with users as clients."""
    from .operators.boost import fit_federated
    from .plans.kernel import Spec

    ev = load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    x = F.array(F.col("value") / 100, F.hour("ts") / 24.0, (F.col("event_id") % 7) / 7.0)
    rows = ev.select(F.col("event_id").alias("rid"), x.alias("x"), (F.col("value") > 50).cast("double").alias("y"), (F.col("user_id") % 10).alias("client"))
    _, messages = fit_federated(rows, "client", Spec("dense", 8, 3), rounds=2)
    return spark.createDataFrame([(m["round"], m["step"], m["client"], m["bytes"]) for m in messages], "round int, step string, client string, bytes long")


@query(f"{_round2_sql(_EMB, _SQUARED)} {_SCORES}")
def ssb_train_squared_block(spark, sf_dir):
    """All squared-loss rounds from one scan of cross-Grams."""
    from .operators.boost import fit_squared_block
    from .plans.kernel import Spec

    rows = embedding_rows(spark, sf_dir).select("rid", "x", F.col("half").cast("double").alias("y"))
    model = fit_squared_block(rows, Spec("dense", 2, 64, hash_fn="md5"), 2)
    return _scores_of(model.transform(rows.select("rid", "x")))


def _regression_curve(spark, sf_dir, name):
    """The RMSE of the test rows after each of five rounds."""
    from .operators.boost import fit

    w = _workload(name, spark, sf_dir, 8)
    staged = fit(w.train, w.spec, w.loss, 5).staged(w.test)
    error = (F.col("score")[0] - F.col("y")) ** 2
    return staged.groupBy("round").agg(F.round(F.sqrt(F.avg(error)), 6).alias("value"))


@query()
def ssb_curve_revenue(spark, sf_dir):
    return _regression_curve(spark, sf_dir, "revenue")


@query()
def ssb_curve_total_price(spark, sf_dir):
    """A control: the price of an order cannot be told from its priority and customer."""
    return _regression_curve(spark, sf_dir, "total_price")


def _workload_curves() -> None:
    """A test curve of five rounds for each workload that no other query trains."""
    for name in ("emb_prod", "emb_sign16", "emb_label", "letters_source", "words_toxic", "words_quality_small_train", "words_lang", "words_role", "onehot_easy", "onehot_hard", "ids"):

        def run(spark, sf_dir, name=name):
            return _curve_of(spark, sf_dir, name, 5)

        run.__name__ = f"ssb_curve_{name}"
        query()(run)


_workload_curves()


@query()
def ssb_predict_topk(spark, sf_dir):
    """The ten test documents with the highest quality score."""
    from .operators.boost import fit

    w = _workload("words_quality", spark, sf_dir)
    model = fit(w.train, w.spec, w.loss, 5, engine="jobs")
    scored = model.transform(w.test.select("rid", "codes", "vals"))
    return rel.top_scored(scored.select("rid", F.round(F.col("score")[0], 6).alias("score")), "score", 10, "rid")


@query()
def gbdt_depth_train(spark, sf_dir):
    w = _workload("letters_lang", spark, sf_dir)
    train = w.train.withColumn("y", (F.col("y") == 1).cast("double"))
    model = trees.fit_gbdt_depth(train, depth=2, rounds=2, candidates="hist", bins=16)
    scored = model.transform(w.test.withColumn("y", (F.col("y") == 1).cast("double"))).withColumn("s", F.col("score")[0])
    return metrics.auc(scored, "s").select(F.round("auc", 6).alias("auc"), "positives", "negatives")


@query()
def gbdt_leaf_train(spark, sf_dir):
    w = _workload("letters_lang", spark, sf_dir)
    is_en = (F.col("y") == 1).cast("double")
    edges = trees.quantile_bins(w.train, 26, 16)
    model = trees.fit_gbdt_leaf(w.train.withColumn("y", is_en).withColumn("x", trees.to_bins("x", edges)), leaves=4, rounds=2)
    scored = model.transform(w.test.withColumn("y", is_en)).withColumn("s", F.col("score")[0])
    return metrics.auc(scored, "s").select(F.round("auc", 6).alias("auc"), "positives", "negatives")


@query()
def random_trees_leaves(spark, sf_dir):
    w = _workload("letters_lang", spark, sf_dir)
    return trees.fit_random_trees(w.train, 2, 1, 26)[0][1].select("leaf", "n", F.round("mean", 6).alias("mean"))


@query("SELECT lang, count(*) / sum(count(*)) OVER () AS share FROM documents GROUP BY lang")
def prior_baseline(spark, sf_dir):
    docs = load(spark, sf_dir, "documents", ["lang"]).withColumnRenamed("lang", "y")
    return trees.fit_prior(docs).withColumnRenamed("y", "lang")


@query()
def bundled_tree_train(spark, sf_dir):
    """Leaf-wise trees on bundles of one-hot columns; one column for each bundle."""
    li = load(spark, sf_dir, "lineitem", ["l_returnflag", "l_linestatus", "l_discount", "l_quantity"]).withColumn("rid", F.monotonically_increasing_id()).persist()
    feats = features.one_hot(["l_returnflag", "l_linestatus", "l_discount"])
    y = (F.col("l_discount") >= 0.05).cast("double")
    names = [r[0] for r in li.select(F.explode(feats).alias("x")).select("x.f").distinct().collect()]
    rows = bundling.bundled_vector(li.select("rid", feats.alias("feats"), y.alias("y")), bundling.one_hot_bundles(names))
    model = trees.fit_gbdt_leaf(rows, leaves=3, rounds=1)
    scored = model.transform(rows).withColumn("s", F.col("score")[0])
    return metrics.auc(scored, "s").select(F.round("auc", 6).alias("auc"), "positives", "negatives")


@query()
def grid_search(spark, sf_dir):
    from .operators.grid import grid_search as search

    w = _workload("emb_half", spark, sf_dir)
    found = search(w.train, w.test, w.spec, {"cells": [8, 16], "eta": [0.1, 0.3], "lam": [0.0, 1.0]}, 5)
    rows = [(r["cells"], r["eta"], r["lam"], r["state"], r["best_value"], r["best_round"]) for r in found]
    return spark.createDataFrame(rows, "cells int, eta double, lam double, state string, best_value double, best_round int").withColumn("best_value", F.round("best_value", 6))


@query()
def scoreboard(spark, sf_dir):
    """Methods by place on the planted half-space; seconds are left out, since they differ between runs."""
    from .experiments import run_accuracy

    rows = run_accuracy([_workload("emb_half", spark, sf_dir)], rounds=10, engine="local", at_once=True)
    values = F.array(*[F.struct(F.lit(r["dataset"]).alias("dataset"), F.lit(r["method"]).alias("method"), F.lit(r["value"]).cast("double").alias("value")) for r in rows])
    return metrics.scoreboard(spark.range(0, 1, 1, 1).select(F.inline(values))).withColumn("value", F.round("value", 6))


@query()
def ablation_weight_laws(spark, sf_dir):
    from .experiments import run_ablation

    grid = [{"init": k} for k in ("uniform", "normal", "mixture", "fan_avg", "fan_in")] + [{"keep": 0.1}, {"norm": "as_printed"}, {"norm": "none"}, {"assign": "hard"}, {"temp": 4.0}, {"layers": (16,)}]
    rows = run_ablation(_workload("letters_lang", spark, sf_dir), grid, rounds=5)
    return spark.createDataFrame([(r["change"], float(r["value"]), r["dead_cells"]) for r in rows], "change string, value double, dead_cells int").withColumn("value", F.round("value", 6))


@query()
def scaling_bytes(spark, sf_dir):
    """Bytes of a round as sent and by the formula, for two sizes and partition counts."""
    from .experiments import run_scaling

    rows = run_scaling(_workload("ids_sub", spark, sf_dir), (2, 4), (16, 64), rounds=2)
    return spark.createDataFrame([(r["cells"], r["partitions"], float(r["bytes"]), float(r["formula_bytes"])) for r in rows], "cells int, partitions int, bytes double, formula_bytes double")


@query()
def duplicates_sensitivity(spark, sf_dir):
    from .experiments import run_duplicates

    rows = [(r["rows"], r["train_rows"], float(r["value"])) for r in run_duplicates(spark, sf_dir)]
    return spark.createDataFrame(rows, "rows string, train_rows long, value double").withColumn("value", F.round("value", 6))


@query(f"{_ROUND2} {_SCORES}")
def ssb_train_side_state(spark, sf_dir):
    return _trained(spark, sf_dir, state="side")


@query()
def bandwidth_model(spark, sf_dir):
    """Modelled ratios from bytes at one second of compute; the ids of lineitem one-hot, one level of one node of the trees."""
    from .experiments import run_bandwidth_model

    keys = ["l_orderkey", "l_partkey", "l_suppkey"]
    ids = load(spark, sf_dir, "lineitem", keys).agg(sum(F.count_distinct(k) for k in keys).alias("ids"))
    sent = {"soft_split": cost.comm_bytes("ssb", cells=64), "hist_trees": cost.comm_bytes("hist", nodes=1, features=F.col("ids"), bins=255)}
    rows = [
        F.struct(F.lit(r["method"]).alias("method"), F.lit(r["bandwidth"]).alias("bandwidth"), *[F.round(F.lit(r[k]), 6).alias(a) for k, a in (("modelled_s", "modelled_s"), ("ratio", "ratio"))])
        for r in run_bandwidth_model(1.0, sent)
    ]
    return ids.select(F.inline(F.array(*rows)))


# DuckDB day windows; the last day stays open in append mode and is filtered out on both sides
_OPEN = "(SELECT date_trunc('day', max(ts) - INTERVAL 1 HOUR) FROM events)"


def _stream(spark, sf_dir):
    """The events as a file stream in one batch: files need not be in the order of time, and a later one's rows would be late."""
    from .sources import stream_events

    schema = load(spark, sf_dir, "events").schema
    return stream_events(spark, f"{sf_dir}/events.parquet*", schema, None)


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    from . import streaming as st

    got = st.run_available(st.tumbling_counts(_stream(spark, sf_dir)), f"tumbling_{id(spark)}_{abs(hash(sf_dir))}", "complete")
    return got.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query("""WITH w AS (SELECT date_trunc('day', ts) - INTERVAL (k) DAY AS day FROM events, range(2) r(k))
SELECT strftime(day, '%Y-%m-%d') AS day, count(*) AS n FROM w GROUP BY 1""")
def stream_sliding(spark, sf_dir):
    from . import streaming as st

    got = st.run_available(st.sliding_mean(_stream(spark, sf_dir)), f"sliding_{id(spark)}_{abs(hash(sf_dir))}", "complete")
    return got.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n")


@query("""WITH o AS (SELECT user_id, ts, (ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 6 HOUR)::INT AS fresh FROM events),
s AS (SELECT user_id, sum(coalesce(fresh, 1)) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM o)
SELECT user_id, count(*) AS n FROM s GROUP BY user_id, s""")
def stream_session(spark, sf_dir):
    from . import streaming as st

    got = st.run_available(st.session_counts(_stream(spark, sf_dir)), f"session_{id(spark)}_{abs(hash(sf_dir))}", "complete")
    return got.select("user_id", "n")


@query("SELECT count(*) AS n, count(DISTINCT event_id) AS kinds FROM events")
def stream_dedup(spark, sf_dir):
    from . import streaming as st

    got = st.run_without_copies(_stream(spark, sf_dir).select("event_id", "ts"), f"dedup_{id(spark)}_{abs(hash(sf_dir))}")
    return got.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("event_id").alias("kinds"))


@query("SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def stream_running_state(spark, sf_dir):
    from . import streaming as st

    got = st.run_available(st.running_by_user(_stream(spark, sf_dir)), f"running_{id(spark)}_{abs(hash(sf_dir))}", "update")
    return got.groupBy("user_id").agg(F.max("n").alias("n"))


@query()
def stream_score(spark, sf_dir):
    """A frozen model over the event stream."""
    from . import streaming as st
    from .operators.boost import fit
    from .plans.kernel import Spec

    x = F.array(F.col("value") / 100, (F.col("event_id") % 7) / 7.0)
    ev = load(spark, sf_dir, "events").select(F.col("event_id").alias("rid"), x.alias("x"), (F.col("value") > 50).cast("double").alias("y"))
    model = fit(ev, Spec("dense", 8, 2), rounds=3, engine="jobs")
    scored = st.run_available(st.score_stream(_stream(spark, sf_dir).select(F.col("event_id").alias("rid"), x.alias("x")), model), f"score_{id(spark)}_{abs(hash(sf_dir))}")
    return scored.select("rid", F.round(F.col("score")[0], 6).alias("score"))
