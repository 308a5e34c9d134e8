"""Small inputs on which queries once differed from their SQL, failed or read no table."""

import datetime
import glob
import os

import duckdb
import numpy as np
import pytest
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from vecboost.config import BoostConfig
from vecboost.operators import metrics
from vecboost.operators.binning import binned, counted
from vecboost.plans import boost, experiments, workloads
from vecboost.plans.boost import fit, training_loss
from vecboost.plans.experiments import Held, null_controls, refresh
from vecboost.plans.side_by_side import local_rows
from vecboost.queries import ORACLES, QUERIES, load_all

load_all()
LINES = "l_orderkey long, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_linenumber int, l_shipdate timestamp"


def plain(v):
    return round(float(v), 6) if isinstance(v, float) else v


def by_sql(name, folder, named=False):
    c = duckdb.connect()
    for p in glob.glob(f"{folder}/*.parquet"):
        c.execute(f"create view {os.path.basename(p)[:-8]} as select * from '{p}{'/*.parquet' if os.path.isdir(p) else ''}'")
    got = c.execute(ORACLES[name])
    names = [d[0] for d in got.description]
    return (names, got.fetchall()) if named else got.fetchall()


def test_prices_on_a_bound_of_a_tenth(spark, tmp_path):
    rows = [(1, 1.0, 32396.35, 0.06, 0.01, 1, datetime.datetime(1995, 1, 1))]
    spark.createDataFrame(rows, LINES).write.parquet(f"{tmp_path}/lineitem.parquet")
    assert [tuple(r) for r in QUERIES["workload_vecreg2"](spark, str(tmp_path)).collect()] == by_sql("workload_vecreg2", tmp_path)


def test_equal_rows_are_counted(spark):
    rng = np.random.default_rng(3)
    x = rng.integers(1, 4, (600, 3))
    y = (x[:, 0] + rng.integers(0, 2, 600)) % 3
    cuts = [[1.5, 2.5, 3.5]] * 3
    rows = spark.createDataFrame([(bytearray(map(int, v)), int(k)) for v, k in zip(x, y)], "bins binary, y int")
    counted = rows.groupBy("bins", "y").agg(F.count("*").alias("copies"))
    local, _ = local_rows(counted, 3)
    assert counted.count() < 100 and len(local) == 600
    for k in ({}, {"schedule": "layer"}, {"schedule": "per_class", "refresh": "round", "n_trees": 3}, {"hessian": "full"}, {"l2_mode": "per_instance", "lam": 0.01}, {"base": "prior"}):
        cfg = BoostConfig(**{"outputs": 3, "n_trees": 2, "depth": 3, **k})
        whole = fit(rows, cfg, cuts)
        want = metrics.evaluate(rows, whole)
        for base in (counted, local):
            m = fit(base, cfg, cuts)
            for s, t in zip(whole.trees, m.trees):
                assert s.feature.tolist() == t.feature.tolist() and s.bin.tolist() == t.bin.tolist() and s.n.tolist() == t.n.tolist()
                np.testing.assert_allclose(s.delta, t.delta, atol=1e-9)
            got = metrics.evaluate(base, m)
            assert got["n_test"] == want["n_test"] == 600
            np.testing.assert_allclose([got[c] for c in sorted(want)], [want[c] for c in sorted(want)], rtol=1e-9)
            np.testing.assert_allclose(training_loss(base, m), training_loss(rows, whole), rtol=1e-9)
            np.testing.assert_allclose(metrics.taylor_gap(base, m, 0), metrics.taylor_gap(rows, whole, 0), rtol=1e-7)
        assert metrics.rows_per_node(counted, whole).agg(F.sum("n")).first()[0] == 600 * len(whole.trees)


def test_experiments_hold_equal_rows_once(spark, sf, tmp_path):
    d = spark.read.parquet(f"{sf}/lineitem.parquet")
    for _ in range(2):
        d = d.union(d)
    d.write.parquet(f"{tmp_path}/lineitem.parquet")
    few, many = (Held(spark, f, "slice3") for f in (sf, str(tmp_path)))
    assert len(many.train.x) == len(few.train.x) and len(many.train) == 4 * len(few.train)
    got, want = ([tuple(r) for r in refresh(spark, f, "slice3", 3).collect()] for f in (str(tmp_path), sf))
    for a, b in zip(got, want):
        assert a[:2] == b[:2] and len(got) == len(want) == 3
    hand = Held(spark, sf, "slice3", keyed=True)
    assert hand.key is not None and len(hand.train.x) == len(few.train)


def test_refresh_bins_and_counts_rows_where_they_are_read(spark, sf, monkeypatch):
    """No row goes through Python before equal ones are one, and none through the driver."""
    rows, cuts, _ = workloads.grouped(spark, sf, "slice3")
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "InArrow" not in plan and "InPandas" not in plan
    monkeypatch.setattr(experiments, "local_rows", lambda *_: pytest.fail("rows asked for on the driver"))
    got = [tuple(map(plain, (r.refresh, r.n_trees, r.accuracy, r.cross_entropy))) for r in QUERIES["exp_refresh"](spark, sf).collect()]
    assert sorted(got, key=str) == sorted((tuple(map(plain, r)) for r in by_sql("exp_refresh", sf)), key=str)


def test_counted_rows_are_the_binned_ones(spark):
    nan, inf = float("nan"), float("inf")
    x = [[1.0, None, 2.0] * 3, [nan, 0.5, -inf] * 3, [inf, 1.0, -0.0] * 3, [1.0, None, 2.0] * 3, [2.5, 3.0, 0.0] * 3]
    d = spark.createDataFrame([(k % 2 == 0, k % 3, v) for k, v in enumerate(x)] * 3, "test boolean, y int, x array<double>")
    few = [[0.0, 1.0, 2.0], [0.5, 1.0], []] * 3
    many = [[k / 100 for k in range(250)], *few[1:]]
    for cuts in (few, many):
        want = binned(d, "x", cuts, ["test", "y"]).groupBy("test", "y", "bins").agg(F.count("*").alias("copies"))
        assert sorted(counted(d, "x", cuts, ["test", "y"]).collect(), key=str) == sorted((r for r in want.collect()), key=str)


@pytest.mark.parametrize("name", ["null_flag", "null_event"])
def test_held_rows_train_the_same_in_tasks_and_distributed(spark, sf, name):
    jobs = [("diag", 2, {}), ("per_class", 3, {"refresh": "round"})]
    with Held(spark, sf, name) as near, Held(spark, sf, name, local=0) as far, Held(spark, sf, name, swapped=True) as turned:
        assert near.local and not far.local
        a, b = (h.each(jobs, experiments.measured) for h in (near, far))
        assert len(turned.train) == len(near.test) and len(turned.test) == len(near.train)
    for r, s in zip(a, b):
        assert r["n_test"] == s["n_test"] > 0 and abs(r["accuracy"] - s["accuracy"]) < 1e-9 and abs(r["cross_entropy"] - s["cross_entropy"]) < 1e-9


def test_null_controls_send_no_rows_through_the_driver(spark, sf, monkeypatch):
    monkeypatch.setattr(experiments, "local_rows", lambda *_: pytest.fail("rows asked for on the driver"))
    assert sorted(tuple(r) for r in QUERIES["null_control"](spark, sf).collect()) == sorted(by_sql("null_control", sf))


def test_null_controls_count_classes_where_the_rows_are(spark, sf, monkeypatch):
    was = [tuple(r) for r in null_controls(spark, sf, ("null_flag",), 2).collect()]
    monkeypatch.setattr(experiments, "local_rows", lambda *_: None)
    got = [tuple(r) for r in null_controls(spark, sf, ("null_flag",), 2).collect()]
    assert got[0][:2] == was[0][:2] and got[0][3:] == was[0][3:] and abs(got[0][2] - was[0][2]) < 1e-9


def test_rounds_do_not_add_to_what_the_driver_keeps(spark, sf, monkeypatch):
    """Plans of the last round are no longer than those of the second, sums meet in no more tasks than there are groups, and garbage goes."""
    seen, best = {}, boost.best_splits

    def watched(sums, *a, **k):
        out = best(sums, *a, **k)
        seen.setdefault(len(model.trees), []).append((len(out._jdf.queryExecution().optimizedPlan().toString()), sums.rdd.getNumPartitions()))
        return out

    monkeypatch.setattr(boost, "best_splits", watched)
    monkeypatch.setattr(boost, "tidied", [0.0])
    spark.conf.set("spark.sql.shuffle.partitions", "40")
    try:
        with Held(spark, sf, "null_flag", local=0) as w:
            cfg = BoostConfig(outputs=3, n_trees=5, depth=3)
            model = boost.Model(cfg, w.cuts)
            fit(w.train, cfg, w.cuts, model=model)
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")
    assert len(seen) == 5 and boost.tidied[0] > 0
    for a, b in zip(seen[1], seen[4]):
        assert b[0] < 1.1 * a[0]
    assert all(n <= 5 for layers in seen.values() for _, n in layers)
    assert boost.slices_of(3, 6, 100) == 3 and boost.slices_of(1000, 6, 100) == 6 and boost.slices_of(1000, 6, boost.HELD) == 1000


@pytest.mark.parametrize("name", ["best_set_rule", "cost_model_grid", "inference_cost_fixed", "model_size_fixed", "postprune_collapse", "round_budget_grid", "stale_stamp_filter"])
def test_reads_lineitem(spark, sf, tmp_path, name):
    with pytest.raises(AnalysisException):
        QUERIES[name](spark, str(tmp_path)).collect()
    spark.read.parquet(f"{sf}/lineitem.parquet").where("l_orderkey % 3 = 0").write.parquet(f"{tmp_path}/lineitem.parquet")
    d = QUERIES[name](spark, str(tmp_path))
    names, want = by_sql(name, tmp_path, named=True)
    assert sorted((tuple(plain(r[c]) for c in names) for r in d.collect()), key=str) == sorted((tuple(map(plain, r)) for r in want), key=str)
