"""The engine's layers as Catalyst expressions alone: for few outputs and features, no row leaves the JVM.

Scores, nodes, derivatives, sums, prefix sums, gains and the choice of splits are columns (operators/native.py); only the
winners reach the driver. Vector trees, the softmax loss, and the Hessian kinds that native.py has in closed form. Missing
values (bin 0) lie below every edge, so they go left.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import native as N
from .kernel import Split, Wip
from .model import Model, Tree


def node_expr(tree: Tree, bins: list[str]) -> Column:
    """The node of a row, by nested conditionals over its bins."""

    def at(j: int) -> Column:
        f = int(tree.feature[j])
        return F.lit(j) if f < 0 else F.when(F.col(bins[f]) <= F.lit(int(tree.bin[j])), at(2 * j)).otherwise(at(2 * j + 1))

    return at(1)


def path_sums(tree: Tree, bins: list[str], c: int) -> list[Column]:
    """What the tree adds to each score of a row: the contributions along its path."""
    t = tree.fold()

    def at(j: int, k: int) -> Column:
        f = int(t.feature[j])
        return F.lit(float(t.delta[j, k])) if f < 0 else F.when(F.col(bins[f]) <= F.lit(int(t.bin[j])), at(2 * j, k)).otherwise(at(2 * j + 1, k))

    return [at(1, k) for k in range(c)]


class JvmRows:
    """Rows with a column for each feature's bin and the label y; given to fit() in place of binned rows.

    Scores of committed trees are columns of a persisted table, made anew from the input every REBASE trees.
    """

    REBASE = 10

    def __init__(self, base: DataFrame, bins: list[str], y: str = "y"):
        self.base, self.bins, self.y = base.select(*bins, F.col(y).alias("y")), bins, y
        self.held: DataFrame | None = None
        self.done = 0

    def count(self) -> int:
        return self.base.count()

    def _scored(self, model: Model) -> DataFrame:
        """Rows with scores s0.. of the committed trees."""
        c, n = model.config.outputs, len(model.trees)
        if self.held is None or self.done != n:
            anew = self.held is None or n % self.REBASE == 0 or self.done > n
            rows = self.base if anew else self.held
            s = [F.lit(float(b)) for b in model.base] if anew else [F.col(f"s{k}") for k in range(c)]
            for t in model.trees[0 if anew else self.done :]:
                s = [a + b for a, b in zip(s, path_sums(t, self.bins, c))]
            now = rows.select(*self.bins, "y", *[x.alias(f"s{k}") for k, x in enumerate(s)]).persist()
            now.count()
            if self.held is not None:
                self.held.unpersist()
            self.held, self.done = now, n
        return self.held

    def forget(self) -> None:
        pass

    def release(self) -> None:
        if self.held is not None:
            self.held.unpersist()
        self.held, self.done = None, 0

    def splits(self, model: Model, wips: list[Wip], layer: int, fresh: bool, features: int | None = None) -> list[Split]:
        cfg, c = model.config, model.config.outputs
        if cfg.loss != "softmax" or len(wips) > 1 or wips[0].direction is not None or cfg.zero_sum == "penalty" or cfg.min_child_weight or cfg.l2_mode != "absolute" or cfg.hessian_scale != 1 or cfg.rows_per_layer is not None:
            raise ValueError("JvmRows: vector trees under the softmax loss, without child weights, quotas and scaled curvature")
        if cfg.hessian not in ("diagonal", "identity") and not (cfg.hessian == "full" and c <= 3):
            raise ValueError("JvmRows: diagonal or identity Hessians, full ones up to three outputs")
        tree, packed = wips[0].tree, cfg.hessian == "full"
        d, s = self._scored(model), [F.col(f"s{k}") for k in range(c)]
        if fresh:
            s = [a + b for a, b in zip(s, path_sums(tree, self.bins, c))]
        g, h = N.softmax_stats(s, F.col("y"), packed)
        stats = [f"g{k}" for k in range(c)] + [f"h{k}" for k in range(len(h))]
        bins = self.bins if features is None else self.bins[:features]
        rows = d.select(node_expr(tree, self.bins).alias("node"), *bins, *N.named(g, h)).where(F.col("node").isin(list(wips[0].open)))
        cells = N.prefix(N.histogram(rows, bins, stats), stats)
        found = N.best(N.candidates(cells, c, len(h), cfg.lam, cfg.hessian, cfg.gamma, weights=True, zero_sum=cfg.zero_sum == "multiplier", whole=True))
        return [Split(0, r.node, r.feature, r.bin, True, -np.inf if r.gain is None else r.gain, r.nl + r.nr, r.nl, r.nr, r.w, r.wl, r.wr) for r in found.collect()]  # a row an open node
