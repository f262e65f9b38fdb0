"""Every registered query of the engine against its SQL, plans, sources, baselines and streaming."""

import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import softsplit.queries as q
from softsplit import sources
from softsplit.baselines import bundling, trees
from softsplit.functions import features, metrics


@pytest.fixture(scope="module")
def con(sf_dir):
    con = duckdb.connect()
    for f in os.listdir(sf_dir):
        con.execute(f"create view {f.removesuffix('.parquet')} as select * from '{sf_dir}/{f}'")
    return con


def _rows(names, rows):
    order = sorted(range(len(names)), key=lambda k: names[k])
    return sorted([tuple(None if r[k] is None else r[k] for k in order) for r in rows], key=repr)


@pytest.mark.parametrize("name", sorted(q.ORACLES))
def test_query_equals_sql(name, spark, sf_dir, con):
    df = q.QUERIES[name](spark, sf_dir)
    want = con.execute(q.ORACLES[name])
    names = [d[0] for d in want.description]
    assert sorted(df.columns) == sorted(names)
    assert _rows(df.columns, df.collect()) == _rows(names, want.fetchall())


def test_pushdown_and_pruning(spark, sf_dir):
    df = sources.load(spark, sf_dir, "lineitem", ["l_quantity"]).filter("l_quantity > 49")
    plan = df._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,49.0)]" in plan
    assert "ReadSchema: struct<l_quantity:double>" in plan


def test_star_join_broadcasts_small_dimensions(spark, sf_dir):
    assert "BroadcastHashJoin" in q.join_star(spark, sf_dir)._jdf.queryExecution().toString()


def test_sources_round_trip(spark, tmp_path):
    rows = spark.createDataFrame([(1.0, [("a", 2.0), ("b", -0.5)]), (0.0, [])], "y double, feats array<struct<f: string, v: double>>")
    sources.write_libsvm(rows, str(tmp_path / "svm"))
    assert sorted(map(str, sources.read_libsvm(spark, str(tmp_path / "svm")).collect())) == sorted(map(str, rows.collect()))
    flat = spark.createDataFrame([(1, "x"), (2, None)], "a int, b string")
    for kind in ("json", "orc", "parquet"):
        sources.save_any(flat, str(tmp_path / kind), kind)
        assert sorted(map(str, sources.load_any(spark, str(tmp_path / kind), kind, "a int, b string").collect())) == sorted(map(str, flat.collect()))
    sources.save_any(flat, str(tmp_path / "csv"), "csv", header="true")
    assert sources.load_any(spark, str(tmp_path / "csv"), "csv", "a int, b string", header="true").count() == 2


def test_bucketed_side_state_joins_without_exchange(spark):
    for name in ("ssb_side_x", "ssb_side_s"):
        spark.sql(f"DROP TABLE IF EXISTS {name}")
        sources.save_bucketed(spark.range(100).withColumnRenamed("id", "rid"), name, 4)
    from softsplit.operators.relational import join_side_state

    joined = join_side_state(spark.table("ssb_side_x"), spark.table("ssb_side_s"))
    assert joined.count() == 100 and "Exchange hashpartitioning" not in joined._jdf.queryExecution().executedPlan().toString()
    for name in ("ssb_side_x", "ssb_side_s"):
        spark.sql(f"DROP TABLE {name}")


def test_metrics_edges(spark):
    one = spark.createDataFrame([(1, 0.5, 1)], "rid int, score double, y int")
    assert metrics.auc(one).first()["auc"] is None
    tied = spark.createDataFrame([(1, 0.5, 1), (2, 0.5, 0)], "rid int, score double, y int")
    assert metrics.auc(tied).first()["auc"] == 0.5
    curve = spark.createDataFrame([(1, 0.2), (2, 0.9), (3, 0.9)], "round int, value double")
    assert metrics.best_round(curve).first()["best_round"] == 2
    for by in ((), ("g",)):
        df = tied.withColumn("g", F.lit(1))
        assert metrics.auc(df, by=by).first()["auc"] == 0.5


def _brute_split(x, g, h, lam):
    best = None
    for f in range(len(x[0])):
        values = sorted({r[f] for r in x})
        for a, b in zip(values, values[1:]):
            left = [r[f] <= (a + b) / 2 for r in x]
            gl, hl = sum(v for v, s in zip(g, left) if s), sum(v for v, s in zip(h, left) if s)
            score = lambda u, v: u * u / (v + lam)
            gain = 0.5 * (score(gl, hl) + score(sum(g) - gl, sum(h) - hl) - score(sum(g), sum(h)))
            if best is None or gain > best[0] + 1e-12:
                best = (gain, f, (a + b) / 2)
    return best


def test_tree_splits_against_brute_force(spark):
    x = [[float(i % 7), float(i * i % 11)] for i in range(60)]
    y = [float((r[0] > 3) ^ (r[1] > 5)) for r in x]
    g, h = [0.5 - v for v in y], [0.25] * 60
    rows = spark.createDataFrame([(0, r, a, b) for r, a, b in zip(x, g, h)], "node int, x array<double>, g double, h double")
    got = trees.best_splits(trees.candidate_sums(rows, "dense"), 1.0).first()
    gain, f, threshold = _brute_split(x, g, h, 1.0)
    assert (got["f"], got["threshold"]) == (f, threshold) and got["gain"] == pytest.approx(gain)
    sparse = rows.select("node", "g", "h", F.map_filter(F.map_from_arrays(F.array(F.lit("a"), F.lit("b")), "x"), lambda k, v: v != 0).alias("feats"))
    same = trees.best_splits(trees.candidate_sums(sparse, "sparse"), 1.0).first()
    assert same["f"] == "ab"[f] and same["gain"] == pytest.approx(gain)


def test_trees_learn(spark):
    rows = spark.createDataFrame([(i, [float(i % 7), float(i * i % 11)], float((i % 7 > 3) ^ (i * i % 11 > 5))) for i in range(200)], "rid long, x array<double>, y double")
    for model in (trees.fit_gbdt_depth(rows, depth=2, rounds=3), trees.fit_gbdt_leaf(rows, leaves=4, rounds=3)):
        scored = model.transform(rows).withColumn("s", F.col("score")[0])
        assert metrics.auc(scored, "s").first()["auc"] > 0.95
    three = rows.withColumn("y", (F.col("rid") % 3).cast("double"))
    model = trees.fit_gbdt_depth(three, depth=1, rounds=1, loss="softmax", classes=3)
    assert len(model.trees[0]) == 3
    (tree, leaves), *_ = trees.fit_random_trees(rows, 2, 1, 2)
    assert leaves.agg(F.sum("n")).first()[0] == 200 and len(tree.splits) == 3


def test_trees_by_columns_equal_those_by_values(spark, monkeypatch):
    rows = spark.createDataFrame([(i, [float(i % 7), float(i * i % 11), None, float("nan"), float(i * 37 % 101)], float((i % 7 > 3) ^ (i * i % 11 > 5))) for i in range(200)], "rid long, x array<double>, y double")
    rows = rows.withColumn("x", F.slice("x", 1, 5))
    clean = rows.withColumn("x", F.array(F.col("x")[0], F.col("x")[1], F.col("x")[4]))
    searches = []
    inner = trees._leaves_by_columns
    monkeypatch.setattr(trees, "_leaves_by_columns", lambda search, *a: inner(lambda *b: searches.append(b) or search(*b), *a))
    got = [trees.fit_gbdt_depth(clean, depth=3, rounds=2).trees, trees.fit_gbdt_leaf(clean, leaves=8, rounds=1).trees]
    assert len(searches) < 7  # one by one, eight leaves take seven searches after the root's
    gaps = trees.fit_gbdt_leaf(rows, leaves=8, rounds=1).trees[0][0]
    assert {f for f, _ in gaps.splits.values()} <= {0, 1, 4}
    monkeypatch.setattr(trees, "COLUMN_ROWS", -1)
    for mine, theirs in zip(got, [trees.fit_gbdt_depth(clean, depth=3, rounds=2).trees, trees.fit_gbdt_leaf(clean, leaves=8, rounds=1).trees]):
        for (a,), (b,) in zip(mine, theirs):
            assert a.splits == {k: tuple(v) for k, v in b.splits.items()} and a.values == pytest.approx(b.values)


def test_a_level_is_one_job(spark):
    rows = spark.createDataFrame([(i, [float(i % 7), float(i * i % 11), float(i * 37 % 101)], float((i % 7 > 3) ^ (i * i % 11 > 5))) for i in range(200)], "rid long, x array<double>, y double")
    spark.sparkContext.setJobGroup("levels", "")
    try:
        model = trees.fit_gbdt_depth(rows, depth=3, rounds=6)
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(model.trees) == 6 and len(spark.sparkContext.statusTracker().getJobIdsForGroup("levels")) <= 6 * 3 + 5  # counting and dealing aside


@pytest.mark.parametrize("loss", ["logistic", "softmax"])
def test_small_tables_train_in_one_task(loss, spark, monkeypatch):
    made = lambda i: [float(i % 7), None if i % 13 == 0 else float(i * i % 11), float("nan") if i % 5 == 0 else float(i * 37 % 101) / 7, 2.0]
    rows = spark.createDataFrame([(i, made(i), float(i * i % 7 % 3 if loss == "softmax" else (i % 7 > 3) ^ (i * i % 11 > 5))) for i in range(300)], "rid long, x array<double>, y double")
    terms = {"rounds": 3, "loss": loss, "classes": 3}
    spark.sparkContext.setJobGroup(f"one task {loss}", "")
    try:
        got = [trees.fit_gbdt_depth(rows, depth=4, **terms), trees.fit_gbdt_leaf(rows, leaves=9, **terms)]
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"one task {loss}")) <= 2 * 6  # no job a round or a level
    monkeypatch.setattr(trees, "TASK_NUMBERS", -1)
    searches = []
    inner = trees._leaves_by_columns
    monkeypatch.setattr(trees, "_leaves_by_columns", lambda search, *a: inner(lambda *b: searches.append(b) or search(*b), *a))
    for one, many in zip(got, [trees.fit_gbdt_depth(rows, depth=4, **terms), trees.fit_gbdt_leaf(rows, leaves=9, **terms)]):
        assert one.trees == many.trees and len(one.history) == 3  # the same sums, to the last bit
    assert 0 < len(searches) < 8 * 3 * got[1].classes  # one by one, nine leaves take eight searches after the root's
    for chunk in (1, 700):
        monkeypatch.setattr(trees, "SEARCHED", chunk)
        assert trees.fit_gbdt_depth(rows, depth=4, **terms).trees == got[0].trees


def test_auc_of_groups_by_ranges(spark):
    rows = spark.range(400).selectExpr("id % 3 as g", "if(id % 17 = 0, null, id * 7 % 29 / 3D) as score", "if(id % 3 = 2, 1, if(id % 11 = 0, null, cast(id % 5 < 2 as int))) as y")
    assert sorted(metrics.auc(rows, by=("g",), ranged=True).collect()) == (want := sorted(metrics.auc(rows, by=("g",)).collect()))
    assert [r["auc"] is None for r in want] == [False, False, True]


@pytest.mark.parametrize("loss", ["logistic", "softmax"])
def test_trees_by_columns_in_later_rounds(loss, spark):
    from softsplit.functions.losses import Loss

    data = [(i * 7 % 150, [float(i % 7), float(i * i % 11), float(i * 37 % 101) / 7, float(i % 2), float(i % 5) / 3], float(i * i % 11 % 3 if loss == "softmax" else (i % 7 > 3) ^ (i * i % 11 > 5))) for i in range(150)]
    rows = spark.createDataFrame(data, "rid long, x array<double>, y double")
    fits = [trees.fit_gbdt_leaf(rows.repartition(n), leaves=6, rounds=3, loss=loss, classes=3) for n in (1, 3)]
    assert fits[0].trees == fits[1].trees  # the sums don't depend on how rows are dealt
    x, y = np.array([d[1] for d in data]), np.array([d[2] for d in data])
    score = np.zeros((len(data), fits[0].classes))
    for grown in fits[0].trees:
        g, h = Loss(loss).grad_hess(score, y)
        for c, tree in enumerate(grown):
            node = trees._nodes(x, tree.splits)
            assert len(set(node.tolist())) == 1 + len(tree.splits) > 2
            for n in set(node.tolist()):
                assert tree.values[n] == pytest.approx(-g[node == n, c].sum() / (h[node == n, c].sum() + 1.0))
            score[:, c] += 0.3 * trees._outputs(x, tree)


def test_many_splits_are_replayed_alike(spark, monkeypatch):
    rows = spark.createDataFrame([(i, [float(i % 7), float(i * i % 11), float(i * 37 % 101)], i * 0.1 if i % 9 else float("nan"), float(i % 3 == 0)) for i in range(150)], "rid long, x array<double>, w double, y double")
    model = trees.fit_gbdt_depth(rows, depth=4, rounds=2)
    odd = rows.unionByName(spark.createDataFrame([(-1, None, None, None), (-2, [None, 3.0, float("nan")], 0.0, 1.0)], rows.schema))
    plain = model.transform(odd)
    monkeypatch.setattr(trees, "MANY_SPLITS", 0)
    quick = model.transform(odd.withColumn("score", F.lit(7)))
    assert quick.columns == plain.columns and "PythonMapInArrow" not in str(plain._jdf.queryExecution()) and "MapInArrow" in str(quick._jdf.queryExecution())
    a, b = ({r["rid"]: r["score"][0] for r in df.collect()} for df in (plain, quick))
    assert a == pytest.approx(b)


def test_bundles(spark):
    rows = spark.createDataFrame([(1, "a", 1.0), (1, "c", 1.0), (2, "b", 1.0), (3, "a", 1.0), (3, "d", 1.0)], "rid int, f string, v double")
    got = bundling.bundle_features(rows)
    assert got["a"][0] == got["b"][0] and got["c"][0] == got["d"][0] != got["a"][0]
    assert {b for b, _ in bundling.bundle_features(rows, max_conflict=2).values()} == {0}
    hot = spark.createDataFrame([(1, 1.0, [("u=1", 1.0), ("v=x", 1.0)]), (2, 0.0, [("u=2", 1.0)])], "rid int, y double, feats array<struct<f: string, v: double>>")
    vec = bundling.bundled_vector(hot, bundling.one_hot_bundles(["u=1", "u=2", "v=x"]))
    assert {r["rid"]: r["x"] for r in vec.collect()} == {1: [1.0, 1.0], 2: [2.0, 0.0]}


def test_features(spark):
    df = spark.createDataFrame([("A b\na", None, 3)], "t string, n double, k int")
    row = df.select(
        features.tokens(F.col("t")).alias("tok"), features.word_counts(F.col("t")).alias("wc"), features.word_ngrams(F.col("t"), 2).alias("ng"),
        features.dense_vector(df, ["n", "k"], 7.0).alias("x"), features.one_hot(["n", "k"]).alias("oh"),
    ).first()
    assert row["tok"] == ["a", "b", "a"] and [(e["f"], e["v"]) for e in row["wc"]] == [("a", 2.0), ("b", 1.0)]
    assert row["ng"] == ["a b", "b a"] and row["x"] == [7.0, 3.0] and [e["f"] for e in row["oh"]] == ["k=3"]
    blocks = features.column_blocks(spark.createDataFrame([(1, [("a", 1.0)]), (2, [("a", 2.0)])], "rid int, feats array<struct<f: string, v: double>>"), 1)
    assert [(e["rid"], e["v"]) for e in blocks.first()["entries"]] == [(1, 1.0), (2, 2.0)]


def test_sql_functions(spark, sf_dir):
    import numpy as np

    from softsplit.functions.udf import gram_udaf, register, solve_groups
    from softsplit.operators.boost import fit
    from softsplit.plans.kernel import Spec, gram

    rows = q.embedding_rows(spark, sf_dir).withColumn("y", F.col("half").cast("double"))
    model = fit(rows, Spec("dense", 4, 64), rounds=2, engine="local")
    register(spark, model)
    rows.createOrReplaceTempView("ssb_rows")
    a = {r[0]: r[1][0] for r in spark.sql("SELECT rid, ssb_score(x) FROM ssb_rows").collect()}
    b = {r["rid"]: r["score"][0] for r in model.transform(rows.select("rid", "x")).collect()}
    assert all(abs(a[k] - b[k]) < 1e-12 for k in b)
    assert spark.sql("SELECT count(*) FROM tri_index(4)").first()[0] == 10
    assert abs(sum(spark.sql("SELECT soft_assign_udf(array(1D, 2D, 3D))").first()[0]) - 1) < 1e-12
    p = np.random.default_rng(0).dirichlet(np.ones(3), 20)
    df = spark.createDataFrame([(x.tolist(), 1.0) for x in p], "p array<double>, h double")
    got = df.agg(gram_udaf("p", "h").alias("a")).first()["a"]
    whole = gram(p, np.ones((20, 1)), np.ones((20, 1)))[0]
    assert np.allclose(got, whole[:6])
    w = solve_groups(spark.createDataFrame([(0, whole.tolist())], "cls int, v array<double>"), 3, 1.0).first()["w"]
    assert len(w) == 3


def test_streaming_state_and_joins(spark, sf_dir):
    from softsplit import streaming as st

    ev = sources.load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    stream = q._stream(spark, sf_dir)
    pairs = st.click_to_purchase(stream.filter("event_type = 'click'"), stream.filter("event_type = 'purchase'"), "2 hours")
    got = st.run_available(pairs, "ssb_pairs").count()
    c = ev.filter("event_type = 'click'").alias("c")
    p = ev.filter("event_type = 'purchase'").alias("p")
    near = F.expr("c.user_id = p.user_id AND p.ts BETWEEN c.ts AND c.ts + interval 2 hours")
    assert got == c.join(p, near).count()
    profile = ev.groupBy("user_id").agg(F.count(F.lit(1)).alias("seen"))
    assert st.run_available(st.with_profile(stream, profile), "ssb_profiled").filter("seen is null").isEmpty()
    drift = st.run_available(st.drift_statistics(stream.withColumn("z", F.array("value")), "z"), "ssb_drift", "complete")
    assert drift.agg(F.sum("n")).first()[0] == ev.count()


@pytest.mark.parametrize("mode", ["append", "complete", "update"])
def test_streamed_rows_stay_off_the_driver(mode, spark, sf_dir):
    from softsplit import streaming as st

    stream = q._stream(spark, sf_dir)
    rows = stream if mode == "append" else stream.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    got = st.run_available(rows, f"ssb_off_{mode}", mode)
    ev = sources.load(spark, sf_dir, "events")
    want = ev.withColumn("ts", F.col("ts").cast("timestamp")) if mode == "append" else ev.groupBy("user_id").count()
    assert got.inputFiles() and sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


@pytest.fixture(scope="module")
def parted(spark, sf_dir, tmp_path_factory):
    """The events in three files that each span the whole time."""
    folder = tmp_path_factory.mktemp("parted")
    sources.load(spark, sf_dir, "events").repartition(3, "event_id").write.parquet(f"{folder}/events.parquet")
    return str(folder)


def test_session_of_several_files(spark, parted, con):
    got = q.stream_session(spark, parted)
    want = con.execute(q.ORACLES["stream_session"]).fetchall()
    assert got.inputFiles() and sorted(map(tuple, got.collect())) == sorted(want)


def test_dedup_of_several_files(spark, parted, con):
    from softsplit import streaming as st

    assert list(map(tuple, q.stream_dedup(spark, parted).collect())) == con.execute(q.ORACLES["stream_dedup"]).fetchall()
    stream = q._stream(spark, parted)
    got = st.run_available(st.without_copies(stream.unionByName(stream)), "ssb_copies")
    assert got.inputFiles() and got.count() == sources.load(spark, parted, "events").count()


def test_dedup_keeps_no_key_in_a_state_store(spark, sf_dir, con, monkeypatch):
    from softsplit import streaming as st

    made = []
    inner = st.Workspace
    monkeypatch.setattr(st, "Workspace", lambda *a: made.append(inner(*a)) or made[-1])
    assert list(map(tuple, q.stream_dedup(spark, sf_dir).collect())) == con.execute(q.ORACLES["stream_dedup"]).fetchall()
    (kept,) = made
    assert os.path.isdir(f"{kept.root.removeprefix('file://')}/state/commits") and not os.path.exists(f"{kept.root.removeprefix('file://')}/state/state")


def test_dedup_over_batches(spark, tmp_path):
    from softsplit import streaming as st

    batches = [
        [(1, "10:00", "a"), (2, "10:05", None), (2, "10:05", "c"), (None, "10:06", "d"), (3, "10:10", "e")],
        [(1, "10:30", "copy"), (None, "10:40", "copy"), (4, "14:00", "f"), (4, "14:00", "f")],
        [(1, "13:30", "copy"), (5, "12:00", "g"), (4, "14:10", "copy"), (6, "14:20", "h")],
        [(1, "14:30", "seen, but long ago"), (7, "12:59", "late"), (8, "13:10", "i"), (9, "14:20", "j"), (6, "14:25", "copy")],
    ]
    for n, rows in enumerate(batches):
        made = spark.createDataFrame([(i, f"2024-01-01 {t}:00", p) for i, t, p in rows], "event_id long, ts string, props string")
        made.withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(str(tmp_path / "events"))
        for f in (tmp_path / "events").glob("*.parquet"):
            if f.stat().st_mtime > 1e9 + 10:
                os.utime(f, (1e9 + n, 1e9 + n))
    stream = spark.readStream.schema("event_id long, ts timestamp, props string").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "events"))
    got = [(r["event_id"], r["ts"].strftime("%H:%M")) for r in st.run_without_copies(stream, "ssb_batches").collect()]
    want = [(r["event_id"], r["ts"].strftime("%H:%M")) for r in st.run_available(st.without_copies(stream), "ssb_batches_store").collect()]
    assert sorted(got, key=str) == sorted(want, key=str) and len(got) == 10


def test_stream_score_trains_off_the_driver(spark, sf_dir, monkeypatch):
    from softsplit.operators.boost import fit
    from softsplit.plans.kernel import Spec

    x = F.array(F.col("value") / 100, (F.col("event_id") % 7) / 7.0)
    ev = sources.load(spark, sf_dir, "events").select(F.col("event_id").alias("rid"), x.alias("x"), (F.col("value") > 50).cast("double").alias("y"))
    want = {r["rid"]: r["score"][0] for r in fit(ev, Spec("dense", 8, 2), rounds=3, engine="local").transform(ev).collect()}
    monkeypatch.delattr(type(ev), "toArrow")
    scored = q.stream_score(spark, sf_dir)
    got = {r["rid"]: r["score"] for r in scored.collect()}
    assert scored.inputFiles() and got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-6 for k in want)


def test_bandwidth_model_counts_the_ids(spark, sf_dir, con):
    (ids,) = con.execute("select count(distinct l_orderkey) + count(distinct l_partkey) + count(distinct l_suppkey) from lineitem").fetchone()
    sent = {"soft_split": 8 * 129 + 8 * (64 * 65 // 2 + 64), "hist_trees": 16 * 255 * ids}
    rows = q.bandwidth_model(spark, sf_dir).collect()
    assert len(rows) == 8
    for r in rows:
        assert r["modelled_s"] == pytest.approx(1 + sent[r["method"]] / r["bandwidth"], abs=1e-6)
        assert r["ratio"] == pytest.approx((1 + sent[r["method"]] / r["bandwidth"]) / (1 + sent[r["method"]] / 1e9), abs=1e-6)


def test_chi_square_of_order_keys(spark, sf_dir, con):
    counts = [r[1] for r in con.execute(_HIST).fetchall()]
    total = sum(counts)
    got = {r["hash_fn"]: r["chi2"] for r in q.hash_uniformity_chi2(spark, sf_dir).collect()}
    assert got.keys() == {"md5", "xxh64", "mix"} and got["md5"] == pytest.approx(100 * sum(n * n for n in counts) / total - total)


_HIST = f"SELECT floor(({q._CODE.format('o_orderkey::VARCHAR')} & 8388607) / 8388608.0 * 100) AS bin, count(*) FROM (SELECT DISTINCT o_orderkey FROM orders WHERE o_orderkey IS NOT NULL) GROUP BY 1"
READS = ("bandwidth_model", "bandwidth_ratios", "comm_volume_ssb", "hash_uniformity_chi2", "hash_uniformity_hist", "join_cross_grid", "scaling_ratios", "speedup_table")


@pytest.mark.parametrize("name", READS)
def test_query_reads_a_given_table(name, spark, sf_dir):
    assert q.QUERIES[name](spark, sf_dir).inputFiles()


def test_entry(spark):
    import __spark_entry__ as entry

    df = entry.entry(spark)
    assert df.count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
