"""The boosters and floors that the vector trees are compared with."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import BoostConfig
from .boost import fit
from .model import Model, score


def round_budget(trees: int, classes: int) -> tuple[int, int, bool]:
    """(rounds, trees built, whether the cell counts): a round builds a tree a class; twice the trees or more asked for is no
    fair cell."""
    rounds = -(-trees // classes)
    built = rounds * classes
    return rounds, built, built < 2 * trees


def ovr_default(base: DataFrame, edges, outputs: int, n_trees: int, **k) -> Model | None:
    """One-vs-rest rounds at common library defaults (child weight 1, curvature taken twice); None where a round is too many trees."""
    _, built, fair = round_budget(n_trees, outputs)
    if not fair:
        return None
    cfg = BoostConfig(**{"outputs": outputs, "schedule": "per_class", "refresh": "round", "n_trees": built, "hessian_scale": 2.0, "min_child_weight": 1.0, **k})
    return fit(base, cfg, edges)


def tree_per_class(base: DataFrame, edges, outputs: int, n_trees: int, **k) -> Model:
    """A scalar tree at a time, classes in turn, scores refreshed after each."""
    return fit(base, BoostConfig(outputs=outputs, schedule="per_class", refresh="tree", n_trees=n_trees, **k), edges)


def logitboost(base: DataFrame, edges, outputs: int, rounds: int, **k) -> Model:
    cfg = BoostConfig(**{"outputs": outputs, "schedule": "per_class", "refresh": "round", "n_trees": rounds * outputs, "lam": 1e-6, **k})
    return fit(base, cfg, edges, how="logitboost")


def abc_logitboost(base: DataFrame, edges, outputs: int, rounds: int, base_class: str | int = "worst_class", **k) -> Model:
    """Scores sum to zero; each round has a base class and a tree for every other."""
    cfg = BoostConfig(**{"outputs": outputs, "schedule": "per_class", "refresh": "round", "n_trees": rounds * (outputs - 1), "lam": 1e-6, **k})
    return fit(base, cfg, edges, how="abc", base_class=base_class)


def one_vs_one(base: DataFrame, edges, outputs: int, n_trees: int, **k) -> dict[tuple[int, int], Model]:
    """A binary ensemble a pair of classes; vote with one_vs_one_predict."""
    out = {}
    for a in range(outputs):
        for b in range(a + 1, outputs):
            rows = base.where(F.col("y").isin(a, b)).withColumn("y", (F.col("y") == b).cast("int"))
            out[a, b] = fit(rows, BoostConfig(**{"outputs": 1, "loss": "logistic", "n_trees": n_trees, **k}), edges)
    return out


def one_vs_one_predict(df: DataFrame, models: dict[tuple[int, int], Model], outputs: int, keep: list[str]) -> DataFrame:
    votes = [F.lit(0)] * outputs
    d = df
    for (a, b), m in models.items():
        d = score(d, m, [c for c in d.columns]).drop("scores", "probability").withColumnRenamed("prediction", f"_v{a}_{b}")
        votes[a] = votes[a] + (F.col(f"_v{a}_{b}") == 0).cast("int")
        votes[b] = votes[b] + (F.col(f"_v{a}_{b}") == 1).cast("int")
    best = F.array_position(F.array(*votes), F.array_max(F.array(*votes))) - 1
    return d.select(*keep, best.cast("int").alias("prediction"))


def prior(train: DataFrame, label: str = "y") -> DataFrame:
    """(label, share), greatest first: the floor of every workload."""
    n = train.groupBy(label).agg(F.count("*").alias("n"))
    total = n.agg(F.sum("n").alias("t"))
    return n.crossJoin(F.broadcast(total)).select(label, (F.col("n") / F.col("t")).alias("share")).orderBy(F.desc("share"), label)  # the broadcast side is one row


def mllib_forest(train: DataFrame, features: list[str], label: str = "y", trees: int = 20, depth: int = 4):
    """Spark's own random forest, as an outside check of sizes and scores."""
    from pyspark.ml.classification import RandomForestClassifier
    from pyspark.ml.feature import VectorAssembler

    va = VectorAssembler(inputCols=features, outputCol="_v", handleInvalid="keep")
    return va, RandomForestClassifier(featuresCol="_v", labelCol=label, numTrees=trees, maxDepth=depth, seed=7).fit(va.transform(train))


def expected_prior_xent(shares: list[float]) -> float:
    p = np.array(shares)
    return float(-(p * np.log(p)).sum())
