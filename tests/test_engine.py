"""The soft-split booster: worked example, invariants, engine equality, persistence."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from softsplit.functions import cost
from softsplit.functions.hashing import base_code, hash_weight, mix_code, mix_code_np, sym_np
from softsplit.functions.losses import Loss
from softsplit.operators.boost import cell_stats_block, fit, fit_federated, fit_squared_block, moment_stats
from softsplit.operators.model import SSBModel
from softsplit.operators.solve import residual, round_objective, solve_scores
from softsplit.plans.kernel import Block, Spec, assign, draw_splitter, forward, gram, gram_parts, hashed_weights, moments, statistics


@pytest.fixture(scope="module")
def emb(spark, sf_dir):
    from softsplit.queries import embedding_rows

    return embedding_rows(spark, sf_dir).withColumn("y", F.col("half").cast("double")).cache()


@pytest.fixture(scope="module")
def words(spark, sf_dir):
    from softsplit.experiments import workload

    return workload("words_quality", spark, sf_dir, 8)


def test_worked_example():
    p, g, h = np.array([[0.75, 0.25], [0.25, 0.75]]), np.array([[-1.0], [1.0]]), np.ones((2, 1))
    a, b = gram_parts(gram(p, g, h)[0], 2)
    assert np.allclose(a, [[0.625, 0.375], [0.375, 0.625]]) and np.allclose(b, [-0.5, 0.5])
    w, path = solve_scores(a, b, 0.0)
    assert np.allclose(w, [2, -2]) and np.allclose(p @ w, -g[:, 0]) and path == "cholesky"
    assert np.allclose(solve_scores(a, b, 1.0)[0], [0.4, -0.4])


def test_solver_is_stationary_and_falls_back():
    rng = np.random.default_rng(0)
    p, g, h = rng.dirichlet(np.ones(5), 50), rng.normal(size=(50, 1)), rng.uniform(0.1, 1, (50, 1))
    a, b = gram_parts(gram(p, g, h)[0], 5)
    w, _ = solve_scores(a, b, 0.5)
    assert residual(a, b, w, 0.5) < 1e-9
    best = round_objective(a, b, w, 0.5)
    assert all(best <= round_objective(a, b, w + d, 0.5) for d in rng.normal(size=(20, 5)) * 0.1)
    dup = np.hstack([p, p])
    a, b = gram_parts(gram(dup, g, h)[0], 10)
    w, path = solve_scores(a, b, 0.0)
    assert path == "least_squares" and np.linalg.norm(a @ w + b) < 1e-8
    assert np.abs(solve_scores(a, b, 1e12)[0]).max() < 1e-9
    assert np.isclose(a.sum(), 4 * h.sum()) and np.isclose(b.sum(), 2 * g.sum())


def test_memberships():
    rng = np.random.default_rng(1)
    spec = Spec("dense", 6, 4)
    block = Block(40, x=rng.normal(size=(40, 4)))
    w = draw_splitter(spec, 0)
    z = forward(block, spec, 0)
    p = assign(z, *moments(statistics(z)), spec)
    assert np.allclose(p.sum(1), 1)
    scaled = forward(block, spec, 0, weights=w * np.array([1, 2, 3, 0.5, 1, 9]))
    assert np.allclose(assign(scaled, *moments(statistics(scaled)), spec), p)
    zt = (z - z.mean(0)) / z.std(0, ddof=1)
    mu, sd = moments(statistics(z))
    assert np.allclose((z - mu) / sd, zt)
    mu, sd = moments(statistics(np.ones((10, 3))))
    assert (sd == 0).all() and np.allclose(assign(np.ones((2, 3)), mu, sd, Spec("dense", 3, 1)), 1 / 3)
    assert (moments(statistics(np.ones((1, 3))))[1] == 0).all()
    assert np.isclose(moments(statistics(z), "as_printed")[1][0] * np.sqrt(40), sd_of(z))


def sd_of(z):
    return z[:, 0].std(ddof=1)


def test_mixer_is_the_same_in_catalyst_and_numpy(spark):
    rows = spark.range(50).select(base_code(F.col("id")).alias("b"), "id").collect()
    base = np.array([r["b"] for r in rows])
    got = spark.range(50).select([mix_code(base_code(F.col("id")), 3, F.lit(j), 2).alias(str(j)) for j in range(5)]).collect()
    assert (np.array([list(r) for r in got]) == mix_code_np(base, 3, np.arange(5), 2)).all()
    w = spark.range(50).select(hash_weight(F.col("id"), 3, F.lit(4), seed=2).alias("w")).collect()
    assert np.allclose([r["w"] for r in w], sym_np(mix_code_np(base, 3, np.arange(5), 2))[:, 4])


def test_mixer_is_uniform_and_uncorrelated():
    u = (sym_np(mix_code_np(np.arange(1, 10001), 0, np.arange(8))) + 1) / 2
    for j in range(8):
        count = np.bincount((u[:, j] * 100).astype(int), minlength=100)
        assert ((count - 100) ** 2 / 100).sum() < 150
    assert np.abs(np.corrcoef(u.T) - np.eye(8)).max() < 0.05


def test_layouts_and_explicit_matrix_agree():
    codes, vals = np.array([5, 9, 5, 77, 9]), np.array([1.0, 2.0, -1.0, 0.5, 3.0])
    block = Block(4, offsets=np.array([0, 2, 2, 4, 5]), codes=codes, vals=vals)
    row, col = (forward(block, Spec("sparse", 7, layout=x), 2) for x in ("row", "column"))
    known = np.array([5, 9, 77])
    dense = np.zeros((4, 3))
    for r, c, v in zip([0, 0, 2, 2, 3], codes, vals):
        dense[r, np.searchsorted(known, c)] += v
    assert np.allclose(row, col) and np.allclose(row, dense @ hashed_weights(Spec("sparse", 7), known, 2))
    assert (row[1] == 0).all()
    small = Spec("sparse", 7, block_nnz=1, block_rows=2)
    assert np.allclose(forward(block, small, 2), row)
    assert all(b - a <= 2 for a, b in block.parts(small))


@pytest.mark.parametrize("name", ["squared", "logistic", "poisson", "softmax"])
def test_derivatives(name):
    rng = np.random.default_rng(3)
    n, c = 6, 3 if name == "softmax" else 1
    y = rng.integers(0, c if c > 1 else 2, n).astype(float)
    s, loss, e = rng.normal(size=(n, c)), Loss(name), 1e-5
    g, h = loss.grad_hess(s, y)
    for k in range(c):
        d = np.zeros((n, c))
        d[:, k] = e
        up, low = loss.value(s + d, y), loss.value(s - d, y)
        assert np.allclose((up - low) / (2 * e), g[:, k], atol=1e-6)
        assert np.allclose((up - 2 * loss.value(s, y) + low) / e**2, h[:, k], atol=1e-3)
    if c > 1:
        assert np.allclose(g.sum(1), 0)


def test_custom_loss_is_the_logistic_one():
    s, y = np.linspace(-2, 2, 9)[:, None], np.array([0, 1] * 4 + [1.0])
    own = Loss.custom(lambda s, y: np.logaddexp(0, s) - y * s)
    for a, b in zip(own.grad_hess(s, y), Loss("logistic").grad_hess(s, y)):
        assert np.allclose(a, b, atol=1e-5)


def _close(a, b, tol=1e-8):
    return max(np.abs(x.w - y.w).max() for x, y in zip(a.rounds, b.rounds)) < tol


def test_engines_agree(emb):
    spec = Spec("dense", 8, 64)
    local = fit(emb, spec, rounds=4, engine="local")
    for parts in (1, 3, 7):
        assert _close(local, fit(emb, spec, rounds=4, partitions=parts, lookahead=3))
    assert _close(local, fit(emb, spec, rounds=2, engine="barrier", partitions=2))
    assert _close(local, fit_federated(emb.withColumn("c", F.col("rid") % 5), "c", spec, rounds=2)[0])
    assert [h["bytes"] for h in fit(emb, spec, rounds=2, partitions=2, lookahead=1).history] == [2 * (cost.comm_bytes("ssb", cells=8) + 16)] * 2
    assert not _close(local, fit(emb, Spec("dense", 8, 64, seed=1), rounds=2, engine="local"))


def test_state_strategies_agree(emb, spark, tmp_path):
    spec = Spec("dense", 4, 64)
    one = fit(emb, spec, rounds=3, engine="local")
    for state in ("blocks", "carry", "side", "driver"):
        assert _close(one, fit(emb, spec, rounds=3, partitions=3, state=state, checkpoint_every=0)), state
    spark.sparkContext.setCheckpointDir(str(tmp_path))
    for state in ("blocks", "carry", "side"):
        assert _close(one, fit(emb, spec, rounds=3, state=state, checkpoint_every=2)), state
    with pytest.raises(ValueError):
        fit(emb, spec, rounds=1, state="none")


def test_sparse_and_multiclass_engines_agree(words, spark, sf_dir):
    from softsplit.experiments import workload

    assert _close(fit(words.train, words.spec, rounds=3, engine="local"), fit(words.train, words.spec, rounds=3, partitions=3))
    w = workload("letters_lang", spark, sf_dir, 8)
    for share in (True, False):
        one = fit(w.train, w.spec, "softmax", 3, classes=4, engine="local", share=share)
        assert _close(one, fit(w.train, w.spec, "softmax", 3, classes=4, share=share, partitions=2))


def test_reference_loop(emb):
    """A plain loop over whole arrays gives the same scores."""
    spec = Spec("dense", 8, 64)
    rows = emb.select("rid", "x", "y").orderBy("rid").collect()
    x, y, score = np.array([r["x"] for r in rows]), np.array([r["y"] for r in rows]), np.zeros(len(rows))
    for t in range(3):
        z = x @ draw_splitter(spec, t)
        e = np.exp((z - z.mean(0)) / z.std(0, ddof=1))
        p, q = e / e.sum(1, keepdims=True), 1 / (1 + np.exp(-score))
        w = np.linalg.solve((p * (q * (1 - q))[:, None]).T @ p + np.eye(8), -p.T @ (q - y))
        score += 0.3 * p @ w
    model = fit(emb, spec, rounds=3)
    got = {r["rid"]: r["score"][0] for r in model.transform(emb.select("rid", "x")).collect()}
    assert np.allclose([got[r["rid"]] for r in rows], score)


def test_losses_fall_and_models_persist(emb, spark, tmp_path):
    model = fit(emb, Spec("dense", 8, 64), "squared", 6, engine="local", eta=1.0)
    lost = [h["loss"] for h in model.history]
    assert all(b <= a + 1e-12 for a, b in zip(lost, lost[1:]))
    model.save(spark, str(tmp_path / "m"))
    again = SSBModel.load(spark, str(tmp_path / "m"))
    a, b = (sorted((r["rid"], r["score"][0]) for r in m.transform(emb.select("rid", "x")).collect()) for m in (model, again))
    assert np.allclose(a, b)
    staged = model.staged(emb.select("rid", "x"), 2)
    assert sorted(r["round"] for r in staged.select("round").distinct().collect()) == [2, 4, 6]


def test_shortcuts(emb):
    spec = Spec("dense", 8, 64, keep=0.3)
    assert np.allclose(moment_stats(emb, spec, [0, 4])[0], cell_stats_block(emb, spec, [0, 4])[0])
    assert _close(fit(emb, spec, "squared", 4, engine="local"), fit_squared_block(emb, spec, 4))
    sampled = fit(emb, spec, rounds=2, subsample=0.5, engine="local")
    assert len(sampled.rounds) == 2


def test_rows_drawn_by_their_number(emb):
    from softsplit.operators.boost import _keep_rows

    rid = np.arange(20_000)
    one, two = _keep_rows(rid[:10_000], 0, 0, 0.3), _keep_rows(rid[10_000:], 0, 0, 0.3)
    assert (one != two).any() and abs(one.mean() - 0.3) < 0.03 and abs(two.mean() - 0.3) < 0.03
    assert abs((one & _keep_rows(rid[:10_000], 1, 0, 0.3)).mean() - 0.09) < 0.02
    spec = Spec("dense", 4, 64)
    a, b = (fit(emb, spec, rounds=2, subsample=0.5, partitions=p) for p in (2, 5))
    assert _close(a, b) and _close(a, fit(emb, spec, rounds=2, subsample=0.5, engine="local"))


def test_block_numbers_are_dealt_evenly(spark):
    from softsplit.operators.boost import murmur3, numbers_dealt_to

    given = np.array([0, 1, -1, 7, 2**40 + 3, -(2**62)])
    df = spark.createDataFrame([(int(x),) for x in given], "id long").select("id", F.hash("id").alias("h"))
    assert {r["id"]: r["h"] for r in df.collect()} == dict(zip(given.tolist(), murmur3(given).tolist()))
    for part in range(3):
        numbers = numbers_dealt_to(part, 3)
        rows = spark.createDataFrame([(next(numbers),) for _ in range(20)], "bid long").repartition(3, "bid")
        assert {r["p"] for r in rows.select(F.spark_partition_id().alias("p")).collect()} == {part}


def test_a_round_keeps_only_scores(words, monkeypatch):
    """What the default engine persists anew in a round has no features."""
    kept, persist = [], type(words.train).persist
    monkeypatch.setattr(type(words.train), "persist", lambda self, *a, **k: kept.append(self.columns) or persist(self, *a, **k))
    fit(words.train, words.spec, rounds=3, partitions=2)
    assert kept[0] == ["bid", "n", "y", "rid", "x", "offsets", "feats", "back", "vals"]
    assert kept[1:] == [["bid", "score", "v"]] * 3


def test_features_that_share_a_round_code_part_in_others():
    codes = np.random.default_rng(0).integers(0, 2**62, 200_000)
    first = [mix_code_np(codes, r, np.arange(1))[:, 0] for r in (0, 1)]
    pairs = []
    for x in first:
        order = np.argsort(x, kind="stable")
        same = np.flatnonzero(x[order][1:] == x[order][:-1])
        pairs.append({tuple(sorted((int(order[i]), int(order[i + 1])))) for i in same})
    assert not pairs[0] & pairs[1]
    assert len(pairs[0]) < 60  # about n**2 / 2**32


def test_null_labels_and_empty(emb, spark):
    some = emb.withColumn("y", F.when(F.col("rid") % 3 == 0, F.col("y")))
    model = fit(some, Spec("dense", 4, 64), rounds=2, engine="local")
    assert _close(model, fit(some.filter("y is not null"), Spec("dense", 4, 64), rounds=2))
    scored = model.transform(some.select("rid", "x"))
    assert scored.filter("score is null").isEmpty() and scored.count() == some.count()
    with pytest.raises(ValueError):
        fit(emb, Spec("dense", 4, 64), engine="none")


def test_wider_is_better_on_planted_labels(spark, sf_dir):
    from softsplit.experiments import test_value, workload

    w = workload("emb_half", spark, sf_dir.replace("sf0.001", "sf0.01"), 32)
    model = fit(w.train, w.spec, rounds=40, engine="local")
    assert test_value(w, model.transform(w.test)) > 0.9
    w = workload("emb_label", spark, sf_dir, 16)
    model = fit(w.train, w.spec, "softmax", 5, classes=10, engine="local")
    assert test_value(w, model.transform(w.test)) < 0.35  # a control


def test_unseen_class(spark, sf_dir):
    from softsplit.experiments import without_class, workload

    w = workload("letters_lang", spark, sf_dir, 8)
    with pytest.raises(ValueError):
        without_class(w, 2.0)
    assert without_class(w, 2.0, allow_unseen=True).train.filter("y = 2").isEmpty()


def test_all_workloads_build(spark, sf_dir):
    from softsplit.experiments import WORKLOADS, workload

    for name in WORKLOADS:
        w = workload(name, spark, sf_dir, 4)
        assert {"rid", "y"} <= set(w.train.columns) and not w.train.isEmpty(), name
    base, sub = (workload(n, spark, sf_dir, 4).train for n in ("ids", "ids_sub"))
    assert sub.count() % 10 == 0 and 0 < sub.count() < 10 * base.count()


def test_cost_measures():
    assert cost.comm_bytes("ssb", cells=64) == 18184 and cost.comm_bytes("ssb", cells=1024) > 4.2e6
    assert cost.comm_bytes("hist", nodes=1, features=390_000, bins=255) > 1.5e9
    assert cost.hash_calls("column", 64, 10, 1000) == 640 and cost.sync_count("ssb") == 2
    assert cost.choose_forward(0.01) == "sparse" and cost.choose_forward(0.02) == "dense"
    assert cost.nnz_budget([1, 2, 3, 100], 4) == (100, 50)
    assert cost.scaling_ratio([2, 1]) == [1, 0.5] and cost.ideal_ratio([4, 8]) == [1, 0.5]
    timer = cost.RoundTimer()
    for t, s in enumerate((9.0, 1.0, 3.0)):
        timer(t, s)
    assert timer.summary() == {"mean_s": 2.0, "sd_s": pytest.approx(2**0.5), "rounds": 2}


def test_accuracy_gives_all_methods_the_same_rounds(spark):
    from softsplit.experiments import Workload, run_accuracy
    from softsplit.functions import features
    from softsplit.plans.kernel import Spec

    rows = spark.range(40).selectExpr("id as rid", "array(cast(id % 7 as double), cast(id % 5 as double)) as x", "cast(id % 7 > 3 as double) as y").coalesce(1)
    got = run_accuracy([Workload("d", rows, rows, Spec("dense", 4, 2), "logistic", "auc")], rounds=4, engine="local", depth=2)
    assert [(r["method"], r["rounds"]) for r in got] == [("soft_split", 4), ("depth_trees", 4), ("leaf_trees", 4)]
    assert [r["value"] for r in got[1:]] == [1.0, 1.0]
    names = "array(named_struct('f', concat('a', id % 3), 'v', 1D), named_struct('f', concat('b', id % 2), 'v', 1D)) as names"
    rows = spark.range(30).selectExpr("id as rid", names, "cast(id % 3 as double) as y").coalesce(1)
    rows = rows.select("rid", *features.coded(rows["names"]), "y")
    got = run_accuracy([Workload("s", rows, rows, Spec("sparse", 4), "softmax", "map", 3)], rounds=1, engine="local", depth=2)
    assert [(r["method"], r["rounds"]) for r in got] == [("soft_split", 1), ("depth_trees", 1), ("leaf_trees", 1)]
    assert [r["value"] for r in got[1:]] == [1.0, 1.0]


def test_accuracy_measures_all_methods_together(spark):
    from softsplit.experiments import Workload, run_accuracy
    from softsplit.plans.kernel import Spec

    rows = spark.range(200).selectExpr("id as rid", "array(cast(id % 7 as double), cast(id * id % 11 as double)) as x", "cast((id % 7 > 3) <> (id % 3 = 0) as double) as y")
    for loss, metric, most in (("logistic", "auc", 24), ("squared", "rmse", 18)):
        w = Workload("d", rows, rows, Spec("dense", 4, 2), loss, metric)
        spark.sparkContext.setJobGroup(metric, "")
        try:
            got = run_accuracy([w], rounds=3, engine="local", depth=2, at_once=True)
        finally:
            spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        assert len(spark.sparkContext.statusTracker().getJobIdsForGroup(metric)) <= most  # threads hold the group too
        plain = run_accuracy([w], rounds=3, engine="local", depth=2)
        assert [(r["method"], r["value"], r["rounds"]) for r in got] == [(r["method"], r["value"], r["rounds"]) for r in plain]
        from softsplit.baselines import trees
        from softsplit.experiments import test_value as alone

        assert got[1]["value"] == pytest.approx(alone(w, trees.fit_gbdt_depth(rows, depth=2, rounds=3, loss=loss).transform(rows)))
