"""Workloads on the given tables and the experiments over them."""

from __future__ import annotations

import statistics
import time
from collections.abc import Sequence
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession, functions as F

from .baselines import trees
from .functions import cost, features, metrics
from .functions.hashing import md5_code
from .operators import relational as rel
from .operators.boost import fit
from .plans.kernel import Spec
from .sources import load

LANGS = ("de", "en", "es", "fr")


@dataclass
class Workload:
    """Training and test rows in the form of the spec, with the loss and the measure."""

    name: str
    train: DataFrame
    test: DataFrame
    spec: Spec
    loss: str
    metric: str
    classes: int = 1
    control: bool = False


def _split(df: DataFrame, key: str = "rid") -> tuple[DataFrame, DataFrame]:
    return df.filter(F.col(key) % 5 != 0), df.filter(F.col(key) % 5 == 0)


def _class_code(column: str, names: Sequence[str]) -> F.Column:
    """The place of a class among names; null, which no trainer or measure takes, for any other."""
    place = F.array_position(F.array(*map(F.lit, names)), F.col(column))
    return F.when(place > 0, place - 1).cast("double")


def _embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("rid"), F.col("embedding").cast("array<double>").alias("x"), "label")


def _star(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = load(spark, sf_dir, "lineitem").withColumnsRenamed({"l_orderkey": "o_orderkey", "l_partkey": "p_partkey"})
    wide = li.join(load(spark, sf_dir, "orders"), "o_orderkey")
    wide = rel.attach_dimension(wide, load(spark, sf_dir, "part"), "p_partkey")
    wide = rel.attach_dimension(wide, load(spark, sf_dir, "customer").withColumnRenamed("c_custkey", "o_custkey"), "o_custkey")
    return rel.attach_dimension(wide, load(spark, sf_dir, "nation").withColumnRenamed("n_nationkey", "c_nationkey"), "c_nationkey")


def _dedup_documents(spark: SparkSession, sf_dir: str, cols: Sequence[str]) -> DataFrame:
    """Documents without exact copies, so that none stands on both sides of a split."""
    keyed = load(spark, sf_dir, "documents").withColumn("t_", F.sha2("text", 256))
    first = keyed.groupBy("t_").agg(F.min("doc_id").alias("doc_id")).drop("t_")
    return load(spark, sf_dir, "documents", ["doc_id", *cols]).join(first, "doc_id", "left_semi")


def workload(name: str, spark: SparkSession, sf_dir: str, cells: int = 64, seed: int = 0) -> Workload:
    """Workloads by name; planted labels are fixed formulas of the row."""
    dense = Spec("dense", cells, 64, seed=seed)
    sparse = Spec("sparse", cells, seed=seed)
    if name in ("emb_half", "emb_prod"):
        rows = _embeddings(spark, sf_dir)
        half = F.aggregate(F.slice("x", 1, 8), F.lit(0.0), lambda a, v: a + v) > 0
        prod = F.col("x")[0] * F.col("x")[1] + 0.1 * F.col("x")[2] > 0
        return Workload(name, *_split(rows.withColumn("y", (half if name == "emb_half" else prod).cast("double"))), dense, "logistic", "auc")
    if name == "emb_sign16":
        y = sum((F.col("x")[k] > 0).cast("double") * (1 << k) for k in range(4))
        return Workload(name, *_split(_embeddings(spark, sf_dir).withColumn("y", y)), dense, "softmax", "map", 16)
    if name == "emb_label":
        return Workload(name, *_split(_embeddings(spark, sf_dir).withColumn("y", F.col("label").cast("double"))), dense, "softmax", "map", 10, control=True)
    if name in ("letters_lang", "letters_source"):
        docs = _dedup_documents(spark, sf_dir, ["text", "lang", "source"])
        rows = docs.select(F.col("doc_id").alias("rid"), features.letter_shares(F.col("text")).alias("x"), "lang", "source")
        spec = Spec("dense", cells, 26, seed=seed)
        if name == "letters_lang":
            return Workload(name, *_split(rows.withColumn("y", _class_code("lang", LANGS))), spec, "softmax", "map", 4)
        y = F.regexp_extract("source", r"(\d+)", 1).cast("double")
        return Workload(name, *_split(rows.withColumn("y", y)), spec, "softmax", "map", 20, control=True)
    if name in ("words_toxic", "words_quality", "words_quality_small_train"):
        docs = _dedup_documents(spark, sf_dir, ["text"]).join(load(spark, sf_dir, "labels"), "doc_id", "left")
        label = "toxic" if name == "words_toxic" else "quality"
        rows = docs.select(F.col("doc_id").alias("rid"), *features.coded(features.word_set(F.col("text"))), F.col(label).cast("double").alias("y"))
        sides = (rows.filter("rid % 20 = 0"), rows.filter("rid % 20 <> 0")) if name.endswith("small_train") else _split(rows)
        return Workload(name, sides[0], sides[1].filter("y is not null"), replace(sparse, row_norm="l2"), "logistic", "auc")
    if name == "words_lang":
        docs = _dedup_documents(spark, sf_dir, ["text", "lang"])
        rows = docs.select(F.col("doc_id").alias("rid"), *features.coded(features.word_set(F.col("text"))), _class_code("lang", LANGS).alias("y"))
        return Workload(name, *_split(rows), replace(sparse, row_norm="l2"), "softmax", "map", 4)
    if name == "words_role":
        turns = load(spark, sf_dir, "conversations")
        rows = turns.select((F.shiftleft("conv_id", 32) + F.col("turn")).alias("rid"), *features.coded(features.word_set(F.col("text"))), _class_code("role", ("system", "user", "assistant")).alias("y"))
        return Workload(name, *_split(rows), replace(sparse, row_norm="l2"), "softmax", "map", 3)
    if name in ("onehot_easy", "onehot_hard"):
        wide = _star(spark, sf_dir)
        keys = ["l_returnflag", "l_linestatus", "l_discount", "l_tax", "l_quantity", "o_orderpriority", "o_orderstatus", "c_mktsegment", "p_brand", "p_type", "n_name"]
        easy = ((F.col("l_discount") >= 0.05) & (F.col("l_quantity") > 25)).cast("double")
        digits = F.coalesce(F.regexp_extract("p_brand", r"(\d+)", 1).try_cast("int"), F.lit(0)) + F.col("l_quantity").cast("int")
        hard = ((digits + F.coalesce(F.regexp_extract("o_orderpriority", r"(\d)", 1).try_cast("int"), F.lit(0))) % 7 < 3).cast("double")
        rows = wide.select(F.xxhash64(*wide.columns).alias("rid"), F.col("o_orderkey").alias("k"), *features.coded(features.one_hot(keys)), (easy if name == "onehot_easy" else hard).alias("y"))
        return Workload(name, *_split(rows, "k"), sparse, "logistic", "auc")
    if name == "ids":
        li = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity"])
        wide = li.join(load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]), F.col("l_orderkey") == F.col("o_orderkey"))
        names = F.concat(features.one_hot(["l_orderkey", "l_partkey", "l_suppkey", "o_custkey"]), F.array(F.struct(features.crossed("l_suppkey", "o_custkey").alias("f"), F.lit(1.0).alias("v"))))
        y = (md5_code(F.col("l_partkey").cast("string")) % 2).cast("double")
        rows = wide.select(F.xxhash64(*wide.columns).alias("rid"), F.col("l_orderkey").alias("k"), *features.coded(names), y.alias("y"))
        return Workload(name, *_split(rows, "k"), sparse, "logistic", "auc")
    if name == "ids_sub":
        base = workload("ids", spark, sf_dir, cells, seed)
        sub = rel.replicate(rel.hash_sample(base.train, "k", 0.1), 10).withColumn("rid", F.xxhash64("rid", "copy")).drop("copy")
        return replace(base, name=name, train=sub)
    if name in ("revenue", "total_price"):
        if name == "revenue":
            li = load(spark, sf_dir, "lineitem")
            scale = F.array(F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10, F.col("l_extendedprice") / 100_000)
            rows = li.select(F.xxhash64(*li.columns).alias("rid"), F.col("l_orderkey").alias("k"), scale.alias("x"), (F.col("l_extendedprice") * (1 - F.col("l_discount")) / 100_000).alias("y"))
        else:
            orders = load(spark, sf_dir, "orders")
            prio = F.coalesce(F.regexp_extract("o_orderpriority", r"(\d)", 1).try_cast("double"), F.lit(0.0))
            rows = orders.select(F.col("o_orderkey").alias("rid"), F.col("o_orderkey").alias("k"), F.array(prio, F.col("o_custkey") % 10 / 10.0).alias("x"), (F.col("o_totalprice") / 100_000).alias("y"))
        return Workload(name, *_split(rows, "k"), Spec("dense", cells, 4 if name == "revenue" else 2, seed=seed), "squared", "rmse", control=name == "total_price")
    raise ValueError(f"unknown workload {name!r}")


WORKLOADS = (
    "emb_half", "emb_prod", "emb_sign16", "emb_label", "letters_lang", "letters_source", "words_toxic", "words_quality", "words_quality_small_train",
    "words_lang", "words_role", "onehot_easy", "onehot_hard", "ids", "ids_sub", "revenue", "total_price",
)


def without_class(w: Workload, code: float, allow_unseen: bool = False) -> Workload:
    """The workload with a class left out of training; test rows of it raise unless allowed."""
    train = w.train.filter(F.col("y") != code)
    unseen = w.test.join(train.select("y").distinct(), "y", "left_anti")
    if not allow_unseen and not unseen.isEmpty():
        raise ValueError(f"test rows of {w.name} have classes that training never saw")
    return replace(w, train=train)


def test_values(w: Workload, scored: dict[str, DataFrame]) -> dict[str, float]:
    """The value of each name's scored rows (rid, y, score), all measured together."""
    rows = None
    for name, df in scored.items():
        own = df.select(F.lit(name).alias("of"), "rid", "y", "score")
        rows = own if rows is None else rows.unionByName(own)
    if w.metric == "auc":
        got = metrics.auc(rows.withColumn("s", F.col("score")[0]), "s", by=("of",), ranged=True).select("of", "auc")
    elif w.metric == "map":
        got = metrics.mean_ap(rows, "score", by=("of",))
    else:
        got = metrics.rmse(rows.withColumn("s", F.col("score")[0]), "s", by=("of",))
    found = dict(map(tuple, got.collect()))
    return {name: found.get(name) for name in scored}


def test_value(w: Workload, scored: DataFrame) -> float:
    if w.metric == "auc":
        return metrics.auc(scored.withColumn("s", F.col("score")[0]), "s").first()["auc"]
    if w.metric == "map":
        return metrics.mean_ap(scored, "score").first()["map"]
    return metrics.rmse(scored.withColumn("s", F.col("score")[0]), "s").first()["rmse"]


def _mapped(rows: DataFrame) -> DataFrame:
    """Sparse rows with their names and values as the map that the tree systems read."""
    return rows.withColumn("feats", F.map_from_arrays(F.col("codes").cast("array<string>"), F.col("vals")))


def run_accuracy(
    ws: Sequence[Workload], rounds: int = 20, eta: float = 0.3, lam: float = 1.0, engine: str = "jobs", with_trees: bool = True, depth: int = 6, at_once: bool = False
) -> list[dict]:
    """Rows (dataset, method, value, s_round, rounds) of the soft splitter and both tree systems.

    All three train the same rounds with the same eta and lam. Both tree systems search every value as a
    split; trees have at most `depth` levels, or as many leaves as the splitter has cells. at_once: they train side by
    side, so their seconds hold what the others take.
    """
    out = []
    for w in ws:
        train, test = w.train.persist(), w.test.persist()
        same = {"kind": w.spec.kind, "rounds": rounds, "eta": eta, "lam": lam, "loss": w.loss, "classes": w.classes}
        seen, asked = (_mapped(train), _mapped(test)) if w.spec.kind == "sparse" else (train, test)
        made = {"soft_split": lambda: fit(train, w.spec, w.loss, rounds, lam, eta, w.classes, engine=engine)}
        if with_trees:
            made["depth_trees"] = lambda: trees.fit_gbdt_depth(seen, depth=depth, **same)
            made["leaf_trees"] = lambda: trees.fit_gbdt_leaf(seen, leaves=w.spec.cells, **same)
        with ThreadPoolExecutor(len(made) if at_once else 1) as pool:
            fits = {m: pool.submit(inheritable_thread_target(train.sparkSession)(f)) for m, f in made.items()}
            fitted = {m: f.result() for m, f in fits.items()}
        values = test_values(w, {m: f.transform(test if m == "soft_split" else asked) for m, f in fitted.items()})
        for m, f in fitted.items():
            paced = f.history[1:] or f.history if m == "soft_split" else f.history
            pace = statistics.fmean(h["wall_s"] for h in paced)
            out.append({"dataset": w.name, "method": m, "value": values[m], "s_round": pace, "rounds": rounds if m == "soft_split" else len(f.trees)})
        train.unpersist()
        test.unpersist()
    return out


def run_scaling(w: Workload, partitions: Sequence[int], sizes: Sequence[int], rounds: int = 5) -> list[dict]:
    """Seconds and bytes a round by partitions and cells, beside the bytes of the formula for the partitions."""
    out = []
    train = w.train.persist()
    for cells in sizes:
        for parts in partitions:
            timer = cost.RoundTimer()
            model = fit(train, replace(w.spec, cells=cells), w.loss, rounds, classes=w.classes, partitions=parts, lookahead=1, on_round=timer)
            sent = statistics.fmean(h["bytes"] for h in model.history)
            formula = cost.comm_bytes("ssb", cells=cells, classes=w.classes) * parts
            out.append({"cells": cells, "partitions": parts, **timer.summary(), "bytes": sent, "formula_bytes": formula})
    train.unpersist()
    return out


def run_bandwidth_model(compute_s: float, bytes_: dict[str, float], steps: Sequence[float] = (1e9, 1e8, 1e7, 1e6)) -> list[dict]:
    """Modelled seconds a round by method and bandwidth; a model from bytes, not a measurement."""
    rows = []
    for method, sent in bytes_.items():
        first = cost.modelled_round_s(compute_s, sent, steps[0])
        for b in steps:
            s = cost.modelled_round_s(compute_s, sent, b)
            rows.append({"method": method, "bandwidth": b, "modelled_s": s, "ratio": s / first, "modelled": True})
    return rows


def run_ablation(w: Workload, grid: Sequence[dict], rounds: int = 10, engine: str = "local") -> list[dict]:
    """The test value under each change of the spec."""
    out = []
    train, test = w.train.persist(), w.test.persist()
    for change in grid:
        model = fit(train, replace(w.spec, **change), w.loss, rounds, classes=w.classes, engine=engine)
        dead = model.rounds[-1].dead_cells
        out.append({"change": str(sorted(change.items())), "value": test_value(w, model.transform(test)), "dead_cells": dead})
    train.unpersist()
    test.unpersist()
    return out


def run_duplicates(spark: SparkSession, sf_dir: str, rounds: int = 5, cells: int = 16) -> list[dict]:
    """The language task on letters with and without exact copies: copies on both sides of a split leak."""
    out = []
    clean = workload("letters_lang", spark, sf_dir, cells)
    docs = load(spark, sf_dir, "documents", ["doc_id", "text", "lang"])
    rows = docs.select(F.col("doc_id").alias("rid"), features.letter_shares(F.col("text")).alias("x"), _class_code("lang", LANGS).alias("y"))
    for name, w in (("without_copies", clean), ("with_copies", replace(clean, train=_split(rows)[0], test=_split(rows)[1]))):
        model = fit(w.train, w.spec, w.loss, rounds, classes=w.classes, engine="local")
        out.append({"rows": name, "train_rows": w.train.count(), "value": test_value(w, model.transform(w.test))})
    return out


def timed(fn) -> tuple[float, object]:
    began = time.perf_counter()
    result = fn()
    return time.perf_counter() - began, result
