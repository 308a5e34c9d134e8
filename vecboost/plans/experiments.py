"""The experiments: method against method over the workloads, as tables of results.

Each gives plain rows; grids and sizes are parameters, so the registered queries run cuts of them and bench/run_grid.py all.
Workloads whose binned rows are small enough are trained side by side, an ensemble a task; others by the distributed engine.
"""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import functions as F

from ..config import BoostConfig
from ..functions.significance import best_set, unpaired_t
from ..operators import metrics
from . import baselines, presets, tuning
from .boost import fit, flat, tidy
from .model import Model
from .side_by_side import LOCAL, local_rows, run_all, run_where
from .workloads import WORKLOADS, grouped, prepared

METHODS = ["ovr_default", "ovr_tuned", "per_class", "full", "diag", "diag_lbl"]
#: What a search takes, not a model.
SEARCH = ("folds", "draws", "seed", "grid", "expansions")
#: Folds of the search where some class is too rare for five.
FOLDS = {"hand10": 3}
#: Features up to which equal binned rows are counted instead of kept one by one.
NARROW = 64


def train(method: str, base, cuts, classes: int, n_trees: int, **k) -> Model | None:
    """A model of the method, or None where its first round is too many trees."""
    search, k = {a: b for a, b in k.items() if a in SEARCH or a in ("key", "spark")}, {a: b for a, b in k.items() if a not in SEARCH and a not in ("key", "spark")}
    if method == "ovr_default":
        return baselines.ovr_default(base, cuts, classes, n_trees, **k)
    if method == "ovr_tuned":
        return tuning.ovr_tuned(base, cuts, classes, n_trees, **search, **k)[0] if baselines.round_budget(n_trees, classes)[2] else None
    if method == "logitboost":
        return baselines.logitboost(base, cuts, classes, 1, **{**k, "n_trees": n_trees})
    if method == "abc_logitboost":
        return baselines.abc_logitboost(base, cuts, classes, 1, **{**k, "n_trees": n_trees})
    if method in ("full", "full_lbl"):
        k = {"solver": "cholesky", **k}  # with an L2 the systems are definite: the same solution as by the default's pivoted QR
    return fit(base, presets.PRESETS[method](classes, n_trees=n_trees, **k), cuts)


class Held:
    """A workload's two sides, kept while an experiment runs: in tasks' memory if they are small, else as persisted rows.

    Rows with equal bins and label are one row with their number (copies): training, losses and moments are those of all rows,
    and work grows with the rows that differ. keyed: rows are kept one by one with their keys, for folds and quotas.
    """

    def __init__(self, spark, sf_dir, name: str, bins: int = 32, swapped: bool = False, local: int = LOCAL, keyed: bool = False):
        self.spark, self.key, self.rows, self.sides = spark, None, None, {}
        if not keyed and WORKLOADS[name][2] <= NARROW:
            rows, self.cuts, self.classes = grouped(spark, sf_dir, name, bins)
            self.held = [(rows.withColumn("test", ~F.col("test")) if swapped else rows).persist()]
            self.rows = flat(self.held[0])
            tidy(spark)
            n = [0, 0, *(r["count"] for r in self.rows.groupBy("test").count().collect())][-2:]  # a row a side
            self.local = max(n) * (len(self.cuts) + 16) <= local
            self.empty = not min(n)
            return
        a, b, self.cuts, self.classes = prepared(spark, sf_dir, name, bins)
        a, b = (b.persist(), a.persist()) if swapped else (a.persist(), b.persist())
        sides = [local_rows(d, len(self.cuts), local) for d in (a, b)]
        self.local = all(s is not None for s in sides)
        self.held = [a, b]
        if self.local:
            (a, self.key), (b, _) = sides
            self.__exit__()
        self.sides = {False: a, True: b}

    def side(self, test: bool):
        """One side's rows; those that are counted come to the driver only where they are asked for here."""
        if test not in self.sides:
            d = self.rows.where(F.col("test") == test).drop("test")
            self.sides[test] = local_rows(d, len(self.cuts))[0] if self.local else d
        return self.sides[test]

    @property
    def train(self):
        return self.side(False)

    @property
    def test(self):
        return self.side(True)

    def __enter__(self):
        return self

    def __exit__(self, *_):
        for d in self.held:
            d.unpersist()
        tidy(self.spark)

    def each(self, jobs: list, work) -> list:
        """work(train, test, cuts, classes, job) for each job: side by side, or one after another."""
        cuts, classes = self.cuts, self.classes
        if not self.local:
            return [work(self.train, self.test, cuts, classes, j) for j in jobs]
        if self.rows is not None and not self.empty:
            return run_where(self.rows, len(cuts), jobs, lambda a, b, job: work(a, b, cuts, classes, job))
        told = self.spark.sparkContext.broadcast([(d.x, d.y, d.copies) for d in (self.train, self.test)])

        def run(job):
            from .kernel import LocalRows

            sides = [LocalRows(x, y, copies=n) for x, y, n in told.value]
            return work(*sides, cuts, classes, job)

        try:
            return run_all(self.spark, jobs, run)
        finally:
            told.unpersist()


def first(model: Model, n: int) -> Model:
    return Model(model.config, model.edges, trees=model.trees[:n], base=model.base)


def told(model: Model, test) -> dict:
    size = metrics.model_size(model)
    return {**metrics.evaluate(test, model), "n_leaves": size["n_leaves"], "n_params": size["n_params"], "built": len(model.trees)}


def at_sizes(train_rows, test, cuts, classes, job) -> list[dict | None]:
    """The measures of one method at several sizes: the first trees of the largest ensemble."""
    method, sizes, k = job
    per_round = classes if method.startswith("ovr") else 1
    budgets = [baselines.round_budget(n, per_round) for n in sizes]
    largest = train(method, train_rows, cuts, classes, max(sizes), **k)
    return [told(first(largest, built), test) if largest is not None and fair and built <= len(largest.trees) else None for _, built, fair in budgets]


ROW = "dataset string, method string, n_trees int, rounds int, accuracy double, cross_entropy double, n_test long, accuracy_sd double, cross_entropy_sd double, n_leaves long, n_params long, best_accuracy boolean, best_cross_entropy boolean, best_without_lbl boolean"


def main_comparison(spark, sf_dir, names=("emb10",), methods=METHODS, sizes=(10, 25, 50, 100), bins: int = 32, **k):
    """Rows of ROW: every method at every size, with marks by the t-test rule. A size is the first trees of the largest ensemble;
    the tuned baseline is searched anew at each size."""
    out = []
    search, fixed = {a: b for a, b in k.items() if a in SEARCH}, {a: b for a, b in k.items() if a not in SEARCH}
    for name in names:
        with Held(spark, sf_dir, name, bins, keyed="ovr_tuned" in methods) as w:
            plain = [m for m in methods if m != "ovr_tuned"]
            found = dict(zip(plain, w.each([(m, tuple(sizes), fixed) for m in plain], at_sizes)))
            if "ovr_tuned" in methods:
                own = {"folds": FOLDS.get(name, 5), **search, "spark": spark, "key": w.key}
                tuned = [train("ovr_tuned", w.train, w.cuts, w.classes, n, **own, **fixed) for n in sizes]
                found["ovr_tuned"] = [None if m is None else told(m, w.test) for m in tuned]
            for i, n in enumerate(sizes):
                cell = []
                for m in methods:
                    got = found[m][i] or {"accuracy": None, "cross_entropy": None}
                    cell.append({"method": m, "n_trees": got.get("built", n), "rounds": baselines.round_budget(n, w.classes if m.startswith("ovr") else 1)[0], **got})
                marks = {"best_accuracy": best_set(cell), "best_cross_entropy": best_set(cell, "cross_entropy", False), "best_without_lbl": best_set(cell, without=("diag_lbl",))}
                for f in cell:
                    out.append((name, f["method"], f["n_trees"], f["rounds"], f["accuracy"], f["cross_entropy"], f.get("n_test"), f.get("accuracy_sd"), f.get("cross_entropy_sd"), f.get("n_leaves"), f.get("n_params"), *(f["method"] in s for s in marks.values())))
    return spark.createDataFrame(out, ROW)


def measured(train_rows, test, cuts, classes, job) -> dict:
    method, n_trees, k = job
    m = train(method, train_rows, cuts, classes, n_trees, **k)
    return told(m, test)


def convergence(spark, sf_dir, name: str = "emb10", methods=("per_class", "full", "diag", "diag_lbl"), n_trees: int = 100, **k):
    """(dataset, method, n_trees, accuracy, cross_entropy) after every tree."""
    with Held(spark, sf_dir, name) as w:

        def work(train_rows, test, cuts, classes, method):
            m = train(method, train_rows, cuts, classes, n_trees, **k)
            if hasattr(test, "x"):
                hit, ent = metrics.curve_of(m, test.x, test.y, test.copies)
                return [(i + 1, a / len(test), b / len(test)) for i, (a, b) in enumerate(zip(hit, ent))]
            return [(r.n_trees, r.accuracy, r.cross_entropy) for r in metrics.curve(test, m).orderBy("n_trees").collect()]  # a row a tree

        rows = [(name, m, *r) for m, curve in zip(methods, w.each(list(methods), work)) for r in curve]
    return spark.createDataFrame(rows, "dataset string, method string, n_trees int, accuracy double, cross_entropy double")


def grid_swapped(spark, sf_dir, depths=(2, 3, 4), rates=(0.04, 0.06, 0.08, 0.1), methods=("logitboost", "abc_logitboost", "diag", "diag_lbl"), n_trees: int = 100):
    """Small training side, large test side: accuracy over depth and rate, every method with the same number of trees (whole
    rounds of trees per class, so a few more)."""
    jobs = [(m, n_trees, {"depth": d, "eta": eta}) for d in depths for eta in rates for m in methods]
    with Held(spark, sf_dir, "emb10", swapped=True) as w:
        got = w.each(jobs, measured)
    return spark.createDataFrame([(k["depth"], k["eta"], m, r["built"], r["accuracy"], r["cross_entropy"]) for (m, _, k), r in zip(jobs, got)], "depth int, eta double, method string, n_trees int, accuracy double, cross_entropy double")


def hessian_costs(spark, sf_dir, names=("role3", "cover7", "emb10", "letter26"), n_trees: int = 10, **k):
    """Full against diagonal: scores, seconds, sums a cell."""
    rows = []
    for name in names:
        with Held(spark, sf_dir, name) as w:

            def work(train_rows, test, cuts, classes, method):
                began = time.time()
                m = train(method, train_rows, cuts, classes, n_trees, **k)
                took = time.time() - began
                c = metrics.cost_model(m.config, 1, len(cuts))
                return {**told(m, test), "seconds": took / n_trees, "sums": c["sums_per_cell"], "bytes": c["task_bytes"]}

            for method, r in zip(("diag", "full"), w.each(["diag", "full"], work)):
                rows.append((name, w.classes, method, r["accuracy"], r["cross_entropy"], r["seconds"], r["sums"], r["bytes"]))
    return spark.createDataFrame(rows, "dataset string, classes int, method string, accuracy double, cross_entropy double, seconds_per_tree double, sums_per_cell long, task_bytes long")


def layer_ablation(spark, sf_dir, name: str = "role3", losses=("softmax", "multiexp"), n_trees: int = 10, **k):
    """Tree against layer schedule by loss: accuracy, true change of the training loss, what the steps' second-order models
    predicted, their summed errors, and the gap of test and training loss."""
    jobs = [(loss, schedule) for loss in losses for schedule in ("tree", "layer")]
    with Held(spark, sf_dir, name) as w:

        def work(train_rows, test, cuts, classes, job):
            loss, schedule = job
            cfg = BoostConfig(outputs=classes, loss=loss, label_encoding="centered" if loss == "multiexp" else "onehot", schedule=schedule, n_trees=n_trees, **k)
            m = fit(train_rows, cfg, cuts)
            return (metrics.evaluate(test, m)["accuracy"], *metrics.taylor_gap(train_rows, m, 0), metrics.gap(train_rows, test, m))

        rows = [(*j, *r) for j, r in zip(jobs, w.each(jobs, work))]
    return spark.createDataFrame(rows, "loss string, schedule string, accuracy double, true_change double, predicted_change double, step_error double, overfit_gap double")


def refresh(spark, sf_dir, name: str = "cover7_oblique", n_trees: int | None = None, **k):
    """Trees per class: scores refreshed after each tree, after each layer, or once a round."""
    with Held(spark, sf_dir, name) as w:
        n = n_trees or w.classes
        jobs = [("per_class", n, {"refresh": how, **k}) for how in ("tree", "round", "layer")]
        rows = [(j[2]["refresh"], r["built"], r["accuracy"], r["cross_entropy"]) for j, r in zip(jobs, w.each(jobs, measured))]
    return spark.createDataFrame(rows, "refresh string, n_trees int, accuracy double, cross_entropy double")


def class_counts(spark, sf_dir, names=("role3", "cover7", "emb10", "letter26"), n_vector: int = 2, most: int | None = None, **k):
    """How many trees per class it takes to match the loss of a few vector trees, by the number of classes; null where `most`
    (default: three for each vector tree and class) don't."""
    rows = []
    for name in names:
        with Held(spark, sf_dir, name) as w:

            def work(train_rows, test, cuts, classes, job):
                m = train(job, train_rows, cuts, classes, n_vector if job == "diag" else most or 3 * n_vector * classes, **k)
                if job == "diag":
                    return metrics.evaluate(test, m)["cross_entropy"]
                if hasattr(test, "x"):
                    return [v / len(test) for v in metrics.curve_of(m, test.x, test.y, test.copies)[1]]
                return [r.cross_entropy for r in metrics.curve(test, m).orderBy("n_trees").collect()]  # a row a tree

            target, got = w.each(["diag", "per_class"], work)
            need = next((i + 1 for i, x in enumerate(got) if x <= target), None)
            rows.append((name, w.classes, n_vector, need, None if need is None else need / n_vector))
    return spark.createDataFrame(rows, "dataset string, classes int, vector_trees int, per_class_trees int, ratio double")


def quotas(spark, sf_dir, name: str = "cover7_oblique", n_trees: int = 3, small: int = 2000, **k):
    """Rows a layer: as many for each, twice as many for each deeper one, or all. Quotas are drawn from distributed rows."""
    rows = []
    with Held(spark, sf_dir, name, local=0, keyed=True) as w:
        depth = k.get("depth", 4)
        for label, q in (("constant", small), ("growing", tuple(small * 2**d for d in range(depth))), ("all", None)):
            m = fit(w.train, presets.diag_lbl(w.classes, n_trees=n_trees, rows_per_layer=q, **k), w.cuts)
            read = sum(int(t.n[j]) for t in m.trees for j in t.nodes() if t.feature[j] >= 0)
            e = metrics.evaluate(w.test, m)
            rows.append((label, read, e["accuracy"], e["cross_entropy"]))
    return spark.createDataFrame(rows, "quota string, rows_in_splits long, accuracy double, cross_entropy double")


def significance(spark, sf_dir, name: str = "emb10", methods=("per_class", "full", "diag", "diag_lbl"), n_trees: int = 10, **k):
    """Pairs of methods with t, degrees of freedom and p, for accuracy and loss."""
    rows = []
    with Held(spark, sf_dir, name) as w:
        e = dict(zip(methods, w.each([(m, n_trees, k) for m in methods], measured)))
    for i, a in enumerate(methods):
        for b in methods[i + 1 :]:
            for metric in ("accuracy", "cross_entropy"):
                rows.append((a, b, metric, *unpaired_t(e[a][metric], e[a][f"{metric}_sd"], e[a]["n_test"], e[b][metric], e[b][f"{metric}_sd"], e[b]["n_test"])))
    return spark.createDataFrame(rows, "a string, b string, metric string, t double, df double, p double")


def preset_scores(spark, sf_dir, names=("emb10",), n_trees: int = 10, **k):
    rows = []
    ours = ("logitboost_compact", "samme_like", "gamble_like", "aoso_like", "gd_mc_like")
    for name in names:
        with Held(spark, sf_dir, name) as w:
            rows += [(name, p, r["accuracy"], r["cross_entropy"]) for p, r in zip(ours, w.each([(p, n_trees, k) for p in ours], measured))]
    return spark.createDataFrame(rows, "dataset string, method string, accuracy double, cross_entropy double")


def null_controls(spark, sf_dir, names=("null_label", "null_flag", "null_priority", "null_event", "source20"), n_trees: int = 10, **k):
    """Labels without signal: accuracy against the share of the largest class; near says that they lie within three deviations."""

    def work(train_rows, test, cuts, classes, job):
        r = measured(train_rows, test, cuts, classes, job)
        most = np.bincount(test.y, test.copies).max() if hasattr(test, "x") else max(q.n for q in test.groupBy("y").agg(F.sum(metrics.copies_of(test)).alias("n")).collect())  # a row a class
        return {**r, "most": int(most)}

    rows = []
    for name in names:
        with Held(spark, sf_dir, name) as w:
            r = w.each([("diag", n_trees, k)], work)[0]
            n, most = r["n_test"], r["most"] / r["n_test"]
            rows.append((name, w.classes, r["accuracy"], most, r["accuracy"] <= most + 3 * (most * (1 - most) / n) ** 0.5))
    return spark.createDataFrame(rows, "dataset string, classes int, accuracy double, largest_share double, near boolean")
