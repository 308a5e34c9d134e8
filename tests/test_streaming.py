import numpy as np
from pyspark.sql import functions as F

from vecboost.config import BoostConfig
from vecboost.plans.workloads import events5
from vecboost.sources.io import LibsvmDense
from vecboost.streaming.minibatch import Trainer, train_stream
from vecboost.streaming.windows import once, prequential


def test_minibatch_training_replays_and_stale_rows(spark, sf, tmp_path):
    events5(spark, sf).repartitionByRange(6, "key").write.parquet(f"{tmp_path}/in")
    d = spark.read.parquet(f"{tmp_path}/in")
    cfg = BoostConfig(outputs=5, n_trees=1, depth=2, bins=8, schedule="layer", rows_per_layer=300)
    stream = spark.readStream.schema(d.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    t = Trainer(spark, f"{tmp_path}/state", cfg, 6)
    train_stream(stream.select("x", "y"), t, f"{tmp_path}/cp").awaitTermination()
    assert t.stamp == 2 and t.done and t.model.trees[0].feature[1] >= 0
    a, b = Trainer(spark, f"{tmp_path}/a", cfg, 6), Trainer(spark, f"{tmp_path}/b", cfg, 6)
    batches = [d.where(F.col("key") % 5 == k).select("x", "y") for k in range(5)]
    for k, x in enumerate(batches):
        a.batch(x, k)
        b.batch(x, k)
        if k in (1,):
            b.batch(x, k)  # a replay
            b.batch(batches[0], 99, stamp=77)  # a stale sender
    assert b.stale > 0
    np.testing.assert_allclose(a.model.trees[0].delta, b.model.trees[0].delta)


def test_event_time_forms(spark, sf, tmp_path):
    d = events5(spark, sf).select("key", "ts", F.element_at("x", 1).alias("v"), "y")
    d.write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema(d.schema).parquet(f"{tmp_path}/in")
    from vecboost.plans.model import Model, Tree

    tree = Tree(5, 1)
    tree.split(1, 0, 1, True, 1.0)
    tree.delta[2, 0] = tree.delta[3, 3] = 1.0
    m = Model(BoostConfig(outputs=5, depth=1), [[15.0]], trees=[tree])
    q = prequential(stream, m, ["v"]).writeStream.format("memory").queryName("pre").outputMode("complete").start()
    q.processAllAvailable()
    q.stop()
    r = spark.sql("SELECT sum(n) n, min(accuracy) a FROM pre").first()
    assert r.n == d.count() and 0 <= r.a <= 1
    q = once(stream, "key").writeStream.format("memory").queryName("once").outputMode("append").start()
    q.processAllAvailable()
    q.stop()
    assert spark.sql("SELECT count(*) n FROM once").first().n == d.count()


def test_libsvm_source(spark, tmp_path):
    lines = [f"{k % 3} 1:{k} 3:{k / 2}" for k in range(100)]
    (tmp_path / "a.svm").write_text("\n".join(lines) + "\n")
    spark.dataSource.register(LibsvmDense)
    d = spark.read.format("libsvm_dense").option("path", str(tmp_path / "a.svm")).option("features", 3).option("span", 97).load()
    r = d.agg(F.count("*"), F.sum(F.element_at("x", 1)), F.sum(F.element_at("x", 3))).first()
    assert tuple(r) == (100, 4950.0, 2475.0)


def batches_of(spark, sf, n):
    d = events5(spark, sf).select("key", "x", "y").persist()
    return [d.where(F.col("key") % n == k).select("x", "y") for k in range(n)]


CFG = BoostConfig(outputs=5, n_trees=2, depth=2, bins=8, schedule="layer", rows_per_layer=300)


def same(a, b):
    assert (a.stamp, a.layer, a.acked, a.edges) == (b.stamp, b.layer, b.acked, b.edges) and len(a.model.trees) == len(b.model.trees)
    for s, t in zip([*a.model.trees, a.wip.tree], [*b.model.trees, b.wip.tree]):
        np.testing.assert_allclose(s.delta, t.delta)
        np.testing.assert_array_equal(s.cut, t.cut)


def test_replays_after_a_flush_and_restarts_mid_tree(spark, sf, tmp_path):
    parts = batches_of(spark, sf, 10)  # of 100 rows each: every three grow a layer
    cuts = [[15.0, 35.0, 60.0], [25.0, 50.0, 75.0], [6.0, 12.0, 18.0], [2.0, 4.0], [3.0, 6.0], [20.0, 40.0]]
    a = Trainer(spark, f"{tmp_path}/a", CFG, 6, cuts)
    for k, x in enumerate(parts):
        a.batch(x, k)
    assert a.stamp == 3 and a.layer == 1 and len(a.model.trees) == 1 and not a.done
    b = Trainer(spark, f"{tmp_path}/b", CFG, 6, cuts)
    for k, x in enumerate(parts):
        b.batch(x, k)
        b.batch(x, k)  # every batch comes twice: before a flush, or (2, 5, 8) after it
        if k in (0, 2, 4, 8):
            b = Trainer(spark, f"{tmp_path}/b", CFG, 6, cuts)  # a new process: the first layer, mid-layer and mid-tree
            b.batch(parts[1], 1)
    same(a, b)


def test_edges_follow_the_stream(spark, sf, tmp_path):
    d = events5(spark, sf).select("key", "x", "y")
    parts = [d.where(F.col("key") % 7 == k).select(F.transform("x", lambda v: v + 10.0 * k).alias("x"), "y") for k in range(7)]  # noqa: B023
    t = Trainer(spark, f"{tmp_path}/t", BoostConfig(outputs=5, n_trees=2, depth=2, bins=4, schedule="layer", rows_per_layer=100), 6)
    seen = []
    for k, x in enumerate(parts[:5]):
        t.batch(x, k)
        seen.append(t.edges[0])
        whole = parts[0]
        for p in parts[1 : k + 1]:
            whole = whole.union(p)
        exact = whole.select(F.percentile(F.element_at("x", 1), F.array(*[F.lit(q) for q in (0.25, 0.5, 0.75)]))).first()[0]
        np.testing.assert_allclose(t.edges[0], exact, rtol=0.1)
    assert all(a[1] < b[1] for a, b in zip(seen, seen[1:])) and t.done
    rows = d.select("x").collect()
    x = np.array([r.x for r in rows])
    m = t.model.regrid()
    bins = np.stack([np.searchsorted(e, x[:, f]) + 1 for f, e in enumerate(m.edges)], axis=1).astype(np.uint8)
    np.testing.assert_allclose(m.scores(bins), t.model.scores(x))
