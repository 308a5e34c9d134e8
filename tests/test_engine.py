import numpy as np
import pytest
from pyspark.sql import functions as F

from vecboost.config import BoostConfig
from vecboost.operators import metrics
from vecboost.operators.binning import array_edges, bin_expr, binned, edges
from vecboost.plans import baselines, presets
from vecboost.functions.losses import PairwiseLogistic
from vecboost.plans.boost import fit, quota_slice, training_loss, write_slices
from vecboost.plans.jvm import JvmRows
from vecboost.plans.kernel import LocalRows
from vecboost.plans.estimator import VectorBoost, register
from vecboost.plans.model import Model, score, score_expr
from vecboost.plans.tuning import random_search

from .reference import boost

N_BINS = 6


@pytest.fixture(scope="module")
def data(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(240, 3))
    y = (x[:, 0] + 0.7 * x[:, 1] > 0).astype(int) + (x[:, 2] > 0.5)
    df = spark.createDataFrame([(i, r.tolist(), int(v)) for i, (r, v) in enumerate(zip(x, y))], "i int, x array<double>, y int").repartition(3)
    cuts = array_edges(df, "x", 3, N_BINS)
    base = binned(df, "x", cuts, ["y", "i"]).persist()
    rows = base.orderBy("i").collect()
    return df, base, cuts, np.array([list(r.bins) for r in rows]), y


@pytest.mark.parametrize("full", [False, True])
@pytest.mark.parametrize("layered", [False, True])
def test_same_as_brute_force(data, full, layered):
    _, base, cuts, bins, y = data
    cfg = BoostConfig(outputs=3, hessian="full" if full else "diagonal", schedule="layer" if layered else "tree", n_trees=2, depth=2)
    model = fit(base, cfg, cuts)
    want, s = boost(bins, y, 3, 2, 2, full=full, layered=layered)
    got = [(t, j, int(x.feature[j]), int(x.bin[j])) for t, x in enumerate(model.trees) for j in x.nodes() if x.feature[j] >= 0]
    assert got == [w[:4] for w in want]
    np.testing.assert_allclose(model.scores(bins.astype(np.uint8)), s, atol=1e-8)
    np.testing.assert_allclose(model.fold().scores(bins.astype(np.uint8)), s, atol=1e-8)


def test_one_output_diag_is_full_and_carried_is_stateless(data):
    df, base, cuts, bins, y = data
    two = base.withColumn("y", (F.col("y") > 0).cast("int"))
    a, b = (fit(two, BoostConfig(outputs=1, loss="logistic", hessian=h, n_trees=2, depth=2), cuts) for h in ("diagonal", "full"))
    np.testing.assert_allclose(a.scores(bins.astype(np.uint8)), b.scores(bins.astype(np.uint8)), atol=1e-9)
    c = fit(two, BoostConfig(outputs=1, loss="logistic", n_trees=2, depth=2, rescore="stateless"), cuts)
    np.testing.assert_allclose(a.scores(bins.astype(np.uint8)), c.scores(bins.astype(np.uint8)), atol=1e-9)


def test_depth_one_layer_is_tree_without_root(data):
    _, base, cuts, bins, _ = data
    a = fit(base, BoostConfig(n_trees=2, depth=1, schedule="layer", root_contributes=False), cuts)
    b = fit(base, BoostConfig(n_trees=2, depth=1), cuts)
    np.testing.assert_allclose(a.scores(bins.astype(np.uint8)), b.scores(bins.astype(np.uint8)), atol=1e-9)


def test_refresh_variants_differ_after_the_first_tree(data):
    _, base, cuts, _, _ = data
    a = fit(base, presets.per_class(3, n_trees=3, depth=2), cuts)
    b = fit(base, presets.per_class(3, n_trees=3, depth=2, refresh="round"), cuts)
    np.testing.assert_allclose(a.trees[0].delta, b.trees[0].delta)
    assert not np.allclose(a.trees[1].delta, b.trees[1].delta)
    assert [t.target for t in a.trees] == [0, 1, 2]


@pytest.mark.parametrize("name", ["samme_like", "gamble_like", "aoso_like", "gd_mc_like"])
def test_presets_lower_their_loss(data, name):
    _, base, cuts, _, _ = data
    m = fit(base, presets.PRESETS[name](3, n_trees=2, depth=2, eta=0.1), cuts)
    assert training_loss(base, m) < training_loss(base, Model(m.config, cuts))


def test_block_and_post_pruning_and_quota(data):
    _, base, cuts, bins, _ = data
    m = fit(base, BoostConfig(hessian="block", blocks=((0, 1),), n_trees=1, depth=2, pruning="post", gamma=1.0), cuts)
    assert all(t.gain[j] > 0 or t.feature[j] < 0 or t.gain[2 * j] + t.gain[2 * j + 1] > 0 for t in m.trees for j in t.nodes())
    q = fit(base, BoostConfig(n_trees=1, depth=2, rows_per_layer=(60, 120)), cuts)
    assert 20 < q.trees[0].n[1] < 130


def test_baselines_and_measures(data, spark):
    df, base, cuts, _, _ = data
    assert baselines.ovr_default(base, cuts, 26, 10) is None
    m = baselines.ovr_default(base, cuts, 3, 3, depth=2)
    lb = baselines.logitboost(base, cuts, 3, 1, depth=2)
    abc = baselines.abc_logitboost(base, cuts, 3, 1, "exhaustive", depth=2)
    for x in (lb, abc):
        np.testing.assert_allclose(sum(t.fold().delta[t.leaves()].sum() for t in x.trees), 0, atol=1e-9)
    ovo = baselines.one_vs_one(base, cuts, 3, 1, depth=2)
    votes = baselines.one_vs_one_predict(base, ovo, 3, ["y"])
    assert votes.where("y = prediction").count() > 120
    e = metrics.evaluate(base, m)
    assert e["n_test"] == 240 and e["accuracy"] > 0.6
    last = metrics.curve(base, m).orderBy(F.desc("n_trees")).first()
    assert abs(last.cross_entropy - e["cross_entropy"]) < 1e-9
    size = metrics.model_size(m)
    assert size["n_params"] == size["n_leaves"] and metrics.model_size(fit(base, presets.diag(3, n_trees=1, depth=2), cuts))["n_params"] % 3 == 0
    true, told, _ = metrics.taylor_gap(base, m, 0)
    assert true < 0 and told < 0
    assert metrics.objective(base, m) > 0
    best, loss, trials = random_search(base.withColumn("fold", F.col("i") % 2), cuts, 3, 3, folds=2, draws=1, grid={"eta": [0.1, 0.3, 1.0]}, depth=1, expansions=0)
    assert "eta" in best and len(trials) == 1
    assert baselines.prior(base).first().share > 0.3


def test_edges_and_missing_values(spark, data):
    df, *_ = data
    flat = df.select(*[F.element_at("x", k + 1).alias(f"x{k}") for k in range(3)], "y")
    for method in ("gk", "kll", "exact", "uniform"):
        got = edges(flat, ["x0", "x1"], 8, method)
        assert all(len(e) == 7 and e == sorted(e) for e in got)
    holes = flat.withColumn("x0", F.when(F.xxhash64("y", "x1") % 3 == 0, None).otherwise(F.col("x0")))
    cuts = edges(holes, ["x0", "x1", "x2"], 8)
    b = binned(holes, ["x0", "x1", "x2"], cuts, ["y"]).persist()
    check = holes.select(bin_expr("x0", cuts[0]).alias("b")).groupBy("b").count().collect()
    bytes_ = np.bincount([r.bins[0] for r in b.collect()], minlength=9)
    assert {r.b: r["count"] for r in check} == {k: n for k, n in enumerate(bytes_) if n}
    m = fit(b, BoostConfig(n_trees=2, depth=2), cuts)
    s = score_expr(m, ["x0", "x1", "x2"])
    a = holes.select(F.round(F.sum(s[0]), 6)).first()[0]
    c = score(b, m, []).select(F.round(F.sum(F.element_at("scores", 1)), 6)).first()[0]
    assert abs(a - c) < 1e-4


def test_save_load_resume_estimator_sql(spark, data, tmp_path):
    df, base, cuts, bins, _ = data
    cfg = BoostConfig(n_trees=2, depth=2)
    m = fit(base, cfg, cuts, classes=["a", "b", "c"])
    m.save(spark, f"file://{tmp_path}/m")
    again = Model.load(spark, f"file://{tmp_path}/m", m.stamp)
    np.testing.assert_allclose(again.scores(bins.astype(np.uint8)), m.scores(bins.astype(np.uint8)))
    more = fit(base, cfg.but(n_trees=3), cuts, model=Model(cfg.but(n_trees=3), cuts, trees=list(again.trees)))
    whole = fit(base, cfg.but(n_trees=3), cuts)
    np.testing.assert_allclose(more.scores(bins.astype(np.uint8)), whole.scores(bins.astype(np.uint8)), atol=1e-8)
    assert m.importance(spark).agg(F.sum("splits")).first()[0] == sum(len(t.nodes()) - len(t.leaves()) for t in m.trees)
    est = VectorBoost(config=BoostConfig(n_trees=2, depth=2, bins=N_BINS)).fit(df)
    out = est.transform(df)
    assert out.where("prediction = y").count() > 150 and len(out.columns) == len(df.columns) + 2
    register(spark, m)
    assert spark.sql("SELECT size(boost_score(array(0.1D, 0.2D, 0.3D))) n").first().n == 3
    assert spark.sql("SELECT count(*) n FROM boost_nodes()").first().n == sum(len(t.leaves()) for t in m.trees)


def test_carried_scores_over_a_rebase_are_the_stateless_ones(data, monkeypatch):
    _, base, cuts, bins, _ = data
    monkeypatch.setattr("vecboost.plans.boost.REBASE", 2)
    cfg = BoostConfig(outputs=3, n_trees=5, depth=1)
    a, b = fit(base, cfg, cuts), fit(base, cfg.but(rescore="stateless"), cuts)
    np.testing.assert_allclose(a.scores(bins.astype(np.uint8)), b.scores(bins.astype(np.uint8)), atol=1e-12)


def test_quota_draws_equal_rows_one_by_one(spark):
    same = spark.range(20_000).selectExpr("id as key", "cast('ab' as binary) as bins", "1 as y")
    for layer in range(3):
        assert 1800 < quota_slice(same, 2000, 20_000, layer, 0, 7).count() < 2200
    assert quota_slice(same, 30_000, 20_000, 0, 0, 7) is same


def same_trees(a, b, tol=1e-9):
    assert len(a.trees) == len(b.trees)
    for s, t in zip(a.trees, b.trees):
        np.testing.assert_array_equal(s.feature, t.feature)
        np.testing.assert_array_equal(s.bin[s.feature >= 0], t.bin[t.feature >= 0])
        np.testing.assert_allclose(s.delta, t.delta, atol=tol)


@pytest.mark.parametrize("how", ["diag", "diag_lbl", "full", "aoso_like", "per_class", "per_class_lbl"])
def test_side_by_side_and_distributed_training_are_the_same(data, how):
    _, base, cuts, bins, y = data
    cfg = presets.PRESETS[how](3, n_trees=3, depth=3)
    same_trees(fit(base, cfg, cuts), fit(LocalRows(bins.astype(np.uint8), y), cfg, cuts))


def test_column_expressions_train_the_same_trees(spark, data):
    df, base, cuts, bins, y = data
    d = df.select("y", *[bin_expr(F.element_at("x", k + 1), cuts[k]).alias(f"b{k}") for k in range(3)])
    for how in ("diag", "diag_lbl", "full_lbl", "samme_like", "aoso_like"):
        cfg = presets.PRESETS[how](3, n_trees=2, depth=2)
        if cfg.loss == "softmax" and cfg.hessian != "pair":
            same_trees(fit(base, cfg, cuts), fit(JvmRows(d, ["b0", "b1", "b2"]), cfg, cuts))
        else:
            with pytest.raises(ValueError):
                fit(JvmRows(d, ["b0", "b1", "b2"]), cfg, cuts)


def test_feature_blocks_and_weights_and_prior(data, monkeypatch):
    _, base, cuts, bins, y = data
    cfg = BoostConfig(n_trees=2, depth=2)
    whole = fit(base, cfg, cuts)
    monkeypatch.setattr("vecboost.plans.boost.HELD", 2000)  # a feature a pass
    same_trees(whole, fit(base, cfg, cuts))
    monkeypatch.undo()
    twice = base.withColumn("weight", F.when(F.col("y") == 1, 3.0).otherwise(1.0))
    copied = base.union(base.where("y = 1")).union(base.where("y = 1"))
    a, b = fit(twice, cfg, cuts), fit(copied, cfg, cuts)
    same_trees(a, b)
    same_trees(a, fit(LocalRows(bins.astype(np.uint8), y, np.where(y == 1, 3.0, 1.0)), cfg, cuts))
    shares = np.bincount(y) / len(y)
    for rows in (base, LocalRows(bins.astype(np.uint8), y)):
        m = fit(rows, cfg.but(base="prior", n_trees=1), cuts)
        np.testing.assert_allclose(m.base, np.log(shares), atol=1e-6)
    assert training_loss(base, Model(cfg, cuts, base=m.base)) < training_loss(base, Model(cfg, cuts))


def test_patience_stops_where_validation_stops_falling(data):
    _, base, cuts, bins, y = data
    rng = np.random.default_rng(0)
    noise = LocalRows(bins.astype(np.uint8), rng.permutation(y))
    m = fit(LocalRows(bins.astype(np.uint8), y), BoostConfig(n_trees=30, depth=3, patience=2, eta=1.0), cuts, validation=noise)
    losses = [noise.loss(Model(m.config, cuts, trees=m.trees[:k])) for k in range(len(m.trees) + 1)]
    assert len(m.trees) < 28 and (len(m.trees) == 0 or min(losses[1:]) == losses[-1])
    d = base.withColumn("part", F.col("i") % 2)
    a = fit(d.where("part = 0"), BoostConfig(n_trees=6, depth=3, patience=1, eta=2.0), cuts, validation=d.where("part = 1"))
    assert 1 <= len(a.trees) <= 6


def test_per_instance_l2_is_multiplied_by_the_rows_of_the_layer(data):
    _, base, cuts, bins, y = data
    a = fit(base, BoostConfig(n_trees=2, depth=2, lam=1 / 240, l2_mode="per_instance"), cuts)
    same_trees(a, fit(base, BoostConfig(n_trees=2, depth=2, lam=1.0), cuts))
    same_trees(a, fit(LocalRows(bins.astype(np.uint8), y), BoostConfig(n_trees=2, depth=2, lam=1 / 240, l2_mode="per_instance"), cuts))


def test_ranking_trains_on_whole_groups(spark):
    rng = np.random.default_rng(9)
    x = rng.normal(size=(600, 2))
    group, grade = np.arange(600) // 12, (x[:, 0] + 0.1 * rng.normal(size=600) > 0).astype(int) + (x[:, 0] > 1)
    df = spark.createDataFrame([(int(g), r.tolist(), int(v)) for g, r, v in zip(group, x, grade)], "group long, x array<double>, y int").repartition(7)
    cuts = array_edges(df, "x", 2, 8)
    base = binned(df, "x", cuts, ["y", "group"]).persist()
    cfg = BoostConfig(outputs=1, loss="pairwise", n_trees=3, depth=2)
    m = fit(base, cfg, cuts)
    bins = np.stack([np.searchsorted(cuts[f], x[:, f]) + 1 for f in range(2)], axis=1).astype(np.uint8)
    same_trees(m, fit(LocalRows(bins, grade, group=group), cfg, cuts))
    assert training_loss(base, m) < 0.75 * training_loss(base, Model(cfg, cuts))
    loss = PairwiseLogistic()
    s, y = rng.normal(size=(9, 1)), np.stack([rng.integers(0, 3, 9), [0] * 4 + [1] * 5], axis=1).astype(float)
    pairs = lambda v: sum(np.logaddexp(0, v[j] - v[i]) for i in range(9) for j in range(9) if y[i, 1] == y[j, 1] and y[i, 0] > y[j, 0])
    assert abs(loss.value(s, y).sum() - pairs(s[:, 0])) < 1e-9
    for k in range(9):
        e = np.zeros(9)
        e[k] = 1e-5
        assert abs((pairs(s[:, 0] + e) - pairs(s[:, 0] - e)) / 2e-5 - loss.grad(s, y)[k, 0]) < 1e-6
    loss.STEP = 2
    np.testing.assert_allclose(loss.grad(s, y), PairwiseLogistic().grad(s, y))


def test_steps_of_a_layered_tree_are_predicted_layer_by_layer(data):
    _, base, cuts, bins, y = data
    rows = LocalRows(bins.astype(np.uint8), y)
    for schedule in ("tree", "layer"):
        m = fit(rows, BoostConfig(n_trees=3, depth=3, schedule=schedule), cuts)
        true, told, error = metrics.taylor_gap(rows, m, 0)
        assert abs(true - 240 * (rows.loss(m) - rows.loss(Model(m.config, cuts)))) < 1e-8 and error >= abs(true - told) - 1e-9
        np.testing.assert_allclose(metrics.taylor_gap(base, m, 0), (true, told, error), rtol=1e-9)
    assert metrics.inference_cost(m)["comparisons"] == 9 and metrics.gap(rows, rows, m) == 0


def test_quotas_read_whole_folders(spark, tmp_path):
    rows = spark.range(20_000).selectExpr("id as key", "cast('ab' as binary) as bins", "cast(1 as int) as y")
    held = write_slices(rows, f"{tmp_path}/s", 32)
    assert held.count() == 20_000
    seen = []
    for layer in range(4):
        d = quota_slice(held, 2000, 20_000, layer, 0, 7, 32)
        plan = d._jdf.queryExecution().executedPlan().toString()
        assert "PartitionFilters: [slice" in plan
        got = {r.key for r in d.select("key").collect()}
        assert 1600 < len(got) < 2400
        seen.append(got)
    assert not seen[0] & seen[1] and not seen[1] & seen[2]


def test_planning_runs_no_job(spark, data):
    df, _, cuts, _, _ = data
    grouped = df.groupBy("i").agg(F.first("x").alias("x"), F.first("y").alias("y"))
    before = len(spark.sparkContext.statusTracker().getJobIdsForGroup(None))
    binned(grouped, "x", cuts, ["y"])
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup(None)) == before
