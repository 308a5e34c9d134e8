"""Accuracy and cost measures."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..config import BoostConfig
from ..functions.arrays import byte_matrix
from ..functions.solve import hessian_of
from ..plans.boost import targets, training_loss
from ..plans.kernel import LocalRows, loss_for
from ..plans.model import Model, score

CLIP = 1e-15


def per_row(scored: DataFrame, label: str = "y", keep: list[str] | None = None) -> DataFrame:
    """(keep, correct, loss) of classification rows with probability and prediction."""
    p = F.element_at("probability", F.col(label) + 1)
    return scored.select(*(keep or []), (F.col("prediction") == F.col(label)).cast("double").alias("correct"), (-F.log(F.greatest(p, F.lit(CLIP)))).alias("loss"))


def moments(scored: DataFrame, label: str = "y", by: list[str] | None = None) -> DataFrame:
    """accuracy, cross_entropy, their deviations and the number of rows, of all rows or of each group: what the t-tests take."""
    if "copies" in scored.columns:
        n, mean = F.sum("copies"), lambda c: F.sum(F.col(c) * F.col("copies")) / F.sum("copies")
        sd = lambda c: F.sqrt(F.greatest((F.sum(F.col(c) * F.col(c) * F.col("copies")) - n * mean(c) * mean(c)) / F.when(n > 1, n - 1), F.lit(0.0)))
        rows = per_row(scored, label, [*(by or []), "copies"])
        return rows.groupBy(*(by or [])).agg(mean("correct").alias("accuracy"), mean("loss").alias("cross_entropy"), sd("correct").alias("accuracy_sd"), sd("loss").alias("cross_entropy_sd"), n.alias("n_test"))
    rows = per_row(scored, label, by)
    return rows.groupBy(*(by or [])).agg(F.avg("correct").alias("accuracy"), F.avg("loss").alias("cross_entropy"), F.stddev_samp("correct").alias("accuracy_sd"), F.stddev_samp("loss").alias("cross_entropy_sd"), F.count("*").alias("n_test"))


def evaluate(base: DataFrame | LocalRows, model: Model, n_trees: int | None = None) -> dict:
    """The moments of a model's rows: one job, one row."""
    if isinstance(base, LocalRows):
        p = loss_for(model.config).predict(Model(model.config, model.edges, base=model.base, trees=model.trees[:n_trees]).scores(base.x))
        hit = (p.argmax(axis=1) == base.y).astype(float)
        ent = -np.log(np.maximum(p[np.arange(len(p)), base.y], CLIP))
        n, mean = len(base), lambda v: float(np.average(v, weights=base.copies)) if n else float("nan")
        sd = lambda v: (mean((v - mean(v)) ** 2) * n / (n - 1)) ** 0.5 if n > 1 else None
        return {"accuracy": mean(hit), "cross_entropy": mean(ent), "accuracy_sd": sd(hit), "cross_entropy_sd": sd(ent), "n_test": n}
    return moments(score(base, model, ["y", *(["copies"] if "copies" in base.columns else [])], n_trees)).first().asDict()


def accuracy(scored: DataFrame, label: str = "y", by: list[str] | None = None) -> DataFrame:
    return moments(scored, label, by).select(*(by or []), "accuracy")


def cross_entropy(scored: DataFrame, label: str = "y", by: list[str] | None = None) -> DataFrame:
    return moments(scored, label, by).select(*(by or []), "cross_entropy")


def curve_of(model: Model, x: np.ndarray, y: np.ndarray, copies: np.ndarray | None = None) -> tuple[list[float], list[float]]:
    """Hits and summed cross-entropy after every tree."""
    n = np.ones(len(y)) if copies is None else copies
    loss, s, hit, ent = loss_for(model.config), np.tile(model.base, (len(x), 1)), [], []
    for t in model.trees:
        t.descend(x, s)
        p = loss.predict(s)
        hit.append(float(((p.argmax(axis=1) == y) * n).sum()))
        ent.append(float(-(np.log(np.maximum(p[np.arange(len(y)), y], CLIP)) * n).sum()))
    return hit, ent


def copies_of(base: DataFrame):
    """How many equal rows each row stands for."""
    return (F.col("copies") if "copies" in base.columns else F.lit(1)).cast("long").alias("copies")


def curve(base: DataFrame, model: Model, by: str | None = None) -> DataFrame:
    """([by,] n_trees, accuracy, cross_entropy) after every tree: one pass, each task adding trees one by one."""
    k, keys = len(model.trees), [by] if by else []

    def run(batches):
        for b in batches:
            x, y = byte_matrix(b.column("bins")), targets(b, "class")
            n = b.column("copies").to_numpy(zero_copy_only=False)
            groups = b.column("g").to_pylist()
            for g in sorted(set(groups), key=str):
                some = np.array([v == g for v in groups])
                hit, ent = curve_of(model, x[some], y[some], n[some])
                yield pa.RecordBatch.from_pydict({"g": pa.array([g] * k, pa.string()), "n_trees": pa.array(range(1, k + 1), pa.int32()), "hit": hit, "ent": ent, "n": pa.array([int(n[some].sum())] * k, pa.int64())})

    group = (F.col(by).cast("string") if by else F.lit("")).alias("g")
    sums = base.select("bins", "y", copies_of(base), group).mapInArrow(run, "g string, n_trees int, hit double, ent double, n long")
    out = sums.groupBy("g", "n_trees").agg((F.sum("hit") / F.sum("n")).alias("accuracy"), (F.sum("ent") / F.sum("n")).alias("cross_entropy"))
    return out.withColumnRenamed("g", by) if by else out.drop("g")


def trees_to_target(curves: DataFrame, target: float, metric: str = "accuracy", greater: bool = True, by: str = "method") -> DataFrame:
    """(by, n_trees): the fewest trees whose metric reaches the target."""
    ok = F.col(metric) >= target if greater else F.col(metric) <= target
    return curves.groupBy(by).agg(F.min(F.when(ok, F.col("n_trees"))).alias("n_trees"))


def model_size(model: Model) -> dict:
    """Trees, leaves, and stored numbers: leaves x outputs for vector trees, leaves for trees of one class."""
    leaves = [len(t.leaves()) for t in model.trees]
    inner = [len(t.nodes()) for t in model.trees]
    width = [1 if t.target is not None else model.config.outputs for t in model.trees]
    layered = model.config.layered
    return {"n_trees": len(model.trees), "n_leaves": sum(leaves), "n_params": sum(n * w for n, w in zip(leaves, width)), "n_params_unfolded": sum(n * w for n, w in zip(inner if layered else leaves, width))}


def schedule_counts(cfg: BoostConfig) -> dict:
    """Rounds, gradient refreshes and passes over the rows for n_trees full trees."""
    k, d, c = cfg.n_trees, cfg.depth, cfg.outputs
    if cfg.layered:
        r = k if cfg.schedule == "layer" else -(-k // c)
        return {"rounds": r, "refreshes": k * d + k * cfg.root_contributes, "passes": k * d + k * cfg.root_contributes}
    if cfg.schedule == "per_class" and cfg.refresh == "round":
        r = -(-k // c)
        return {"rounds": r, "refreshes": r, "passes": r * d}
    return {"rounds": k if cfg.schedule == "tree" else -(-k // c), "refreshes": k, "passes": k * d}


def cost_model(cfg: BoostConfig, rows: int, features: int) -> dict:
    """Sums a cell, arithmetic a row and a candidate, bytes that one task of the deepest layer gives to the exchange."""
    scalar = cfg.schedule == "per_class"
    c = 1 if scalar else cfg.outputs
    width = 3 if scalar else 1 + c + hessian_of(cfg.hessian, c).width
    solve = c**3 if cfg.hessian in ("full", "block") and not scalar else c
    cells = 2 ** (cfg.depth - 1) * features * cfg.bins
    return {"sums_per_cell": width, "adds_per_row": features * width, "solve_per_candidate": solve, "candidates_per_layer": cells, "task_bytes": cells * width * 8, **schedule_counts(cfg), "row_visits": schedule_counts(cfg)["passes"] * rows}


def inference_cost(model: Model) -> dict:
    """Comparisons a row at most, and bytes of the folded model."""
    size = model_size(model)
    return {"comparisons": sum(t.depth for t in model.trees), "bytes": 8 * size["n_params"] + 12 * (size["n_leaves"] - size["n_trees"])}


def taylor_gap(base: DataFrame | LocalRows, model: Model, first: int) -> tuple[float, float, float]:
    """(true, predicted, error) of the summed loss's change by the trees from `first` on. Predicted is the sum over steps of the
    second-order model at the scores before each: a step is a tree, or, layer by layer, a layer. error: the steps' absolute
    differences of truth and prediction, added up."""
    cfg = model.config
    loss = loss_for(cfg)

    def steps(x, y, n):
        s, out = Model(cfg, model.edges, base=model.base, trees=model.trees[:first]).scores(x), []
        for t in model.trees[first:]:
            path = t.descend(x)
            for layer in range(t.depth + 1) if cfg.layered else [None]:
                if layer is None:
                    d = np.zeros_like(s)
                    t.descend(x, d)
                else:  # the ancestor of a row's leaf in that layer; none if the path ends above
                    level = np.floor(np.log2(path)).astype(int)
                    d = np.where((level >= layer)[:, None], t.delta[path >> np.maximum(level - layer, 0)], 0)
                told = (loss.grad(s, y) * d).sum(axis=1) @ n + 0.5 * np.einsum("i,ia,iab,ib->", n, d, loss.full(s, y), d)
                before, s = loss.value(s, y) @ n, s + d
                out.append((float(loss.value(s, y) @ n - before), float(told)))
        return out

    if isinstance(base, LocalRows):
        sums = steps(base.x, base.targets(), np.ones(len(base.x)) if base.copies is None else base.copies.astype(float))
    else:

        def run(batches):
            for b in batches:
                if b.num_rows:
                    got = steps(byte_matrix(b.column("bins")), targets(b, loss.kind), b.column("copies").to_numpy(zero_copy_only=False).astype(float))
                    yield pa.RecordBatch.from_pydict({"k": pa.array(range(len(got)), pa.int32()), "true": [g[0] for g in got], "told": [g[1] for g in got]})

        sums = [(r.true, r.told) for r in base.select("bins", "y", copies_of(base)).mapInArrow(run, "k int, true double, told double").groupBy("k").agg(F.sum("true").alias("true"), F.sum("told").alias("told")).orderBy("k").collect()]  # a row a step
    return sum(a for a, _ in sums), sum(b for _, b in sums), sum(abs(a - b) for a, b in sums)


def rows_per_node(base: DataFrame, model: Model) -> DataFrame:
    """(tree, node, n): rows that end in each leaf."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                x = byte_matrix(b.column("bins"))
                for k, t in enumerate(model.trees):
                    node, at = np.unique(t.descend(x), return_inverse=True)
                    n = np.bincount(at, b.column("copies").to_numpy(zero_copy_only=False)).astype(np.int64)
                    yield pa.RecordBatch.from_pydict({"tree": pa.array([k] * len(node), pa.int32()), "node": pa.array(node, pa.int32()), "n": pa.array(n, pa.int64())})

    return base.select("bins", copies_of(base)).mapInArrow(run, "tree int, node int, n long").groupBy("tree", "node").agg(F.sum("n").alias("n"))


def objective(base: DataFrame, model: Model) -> float:
    """Mean training loss times rows, plus gamma a leaf and half lam times the squared leaf vectors."""
    cfg, folded = model.config, model.fold()
    leaves = [t.delta[t.leaves()] for t in folded.trees]
    return training_loss(base, model) * base.agg(F.sum(copies_of(base))).first()[0] + cfg.gamma * sum(map(len, leaves)) + 0.5 * cfg.lam * sum(float((w**2).sum()) for w in leaves)


def gap(train: DataFrame, test: DataFrame, model: Model) -> float:
    """Test minus training loss."""
    return training_loss(test, model) - training_loss(train, model)


def confusion(scored: DataFrame, label: str = "y") -> DataFrame:
    return scored.groupBy(label, "prediction").agg(F.count("*").alias("n"))


def moving_accuracy(scored: DataFrame, order: str, label: str = "y", rows: int = 100, by: str | None = None) -> DataFrame:
    w = (W.partitionBy(by) if by else W.partitionBy(F.lit(0))).orderBy(order).rowsBetween(1 - rows, 0)
    return scored.withColumn("moving_accuracy", F.avg((F.col("prediction") == F.col(label)).cast("double")).over(w))
