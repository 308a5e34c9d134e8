"""Trees, ensembles, their tables and their predictions."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import BoostConfig
from ..functions.arrays import byte_matrix, to_lists
from ..functions.losses import loss_of

NODE = "tree int, node int, layer int, is_leaf boolean, feature int, bin int, edge double, default_left boolean, delta array<double>, n long, gain double, target_class int, stamp long"


@dataclass
class Tree:
    """A binary tree, nodes numbered as in a heap from 1. delta is what a node adds to the scores of its rows."""

    c: int
    depth: int
    target: int | None = None  # of a tree for one class
    feature: np.ndarray = None
    bin: np.ndarray = None
    left_default: np.ndarray = None
    delta: np.ndarray = None
    n: np.ndarray = None
    gain: np.ndarray = None
    cut: np.ndarray = None  # thresholds by value, of trees whose edges moved while they grew

    def __post_init__(self):
        k = 2 ** (self.depth + 1)
        if self.feature is None:
            self.feature, self.bin, self.left_default = np.full(k, -1, np.int64), np.zeros(k, np.int64), np.ones(k, bool)
            self.delta, self.n, self.gain = np.zeros((k, self.c)), np.zeros(k, np.int64), np.zeros(k)
        if self.cut is None:
            self.cut = np.full(k, np.nan)

    def nodes(self) -> list[int]:
        out = [1]
        for j in out:
            if self.feature[j] >= 0:
                out += [2 * j, 2 * j + 1]
        return out

    def leaves(self) -> list[int]:
        return [j for j in self.nodes() if self.feature[j] < 0]

    def split(self, j: int, feature: int, bin_: int, left_default: bool, gain: float, cut: float | None = None) -> None:
        self.feature[j], self.bin[j], self.left_default[j], self.gain[j] = feature, bin_, left_default, gain
        if cut is not None:
            self.cut[j] = cut

    def descend(self, bins: np.ndarray, scores: np.ndarray | None = None) -> np.ndarray:
        """Node of every row of bins, or of raw values where nodes have thresholds of their own; scores, if given, get
        the deltas along the path."""
        raw = bins.dtype.kind == "f"
        node = np.ones(len(bins), np.int64)
        rows = np.arange(len(bins))
        if scores is not None:
            scores += self.delta[node]
        for _ in range(self.depth):
            f = self.feature[node]
            live = f >= 0
            if not live.any():
                break
            x = bins[rows, np.maximum(f, 0)]
            left = np.where(np.isnan(x) if raw else x == 0, self.left_default[node], x <= (self.cut if raw else self.bin)[node])
            node = np.where(live, 2 * node + ~left, node)
            if scores is not None:
                scores[live] += self.delta[node[live]]
        return node

    def fold(self) -> Tree:
        """The same predictions with every contribution pushed down into the leaves."""
        t = Tree(self.c, self.depth, self.target, self.feature.copy(), self.bin.copy(), self.left_default.copy(), self.delta.copy(), self.n.copy(), self.gain.copy(), self.cut.copy())
        for j in t.nodes():
            if t.feature[j] >= 0:
                t.delta[2 * j] += t.delta[j]
                t.delta[2 * j + 1] += t.delta[j]
                t.delta[j] = 0
        return t

    def collapse(self) -> None:
        """Bottom-up: a split whose own gain and whose subtree's total gain aren't positive becomes a leaf (its
        weight in tree mode is set by the caller); deltas of nodes that go are dropped."""
        total = np.zeros(len(self.feature))
        for j in reversed(self.nodes()):
            if self.feature[j] >= 0:
                total[j] = self.gain[j] + max(0.0, total[2 * j]) + max(0.0, total[2 * j + 1])
                if total[j] <= 0:
                    self.cut_below(j)

    def cut_below(self, j: int) -> None:
        for k in (2 * j, 2 * j + 1):
            if self.feature[k] >= 0:
                self.cut_below(k)
            self.delta[k], self.n[k] = 0, 0
        self.feature[j], self.gain[j] = -1, 0


@dataclass
class Model:
    config: BoostConfig
    edges: list[list[float]]
    classes: list = field(default_factory=list)
    base: np.ndarray = None
    trees: list[Tree] = field(default_factory=list)
    stamp: int = 0

    def __post_init__(self):
        self.base = np.zeros(self.config.outputs) if self.base is None else np.asarray(self.base, np.float64)

    def scores(self, bins: np.ndarray, n_trees: int | None = None) -> np.ndarray:
        s = np.tile(self.base, (len(bins), 1))
        for t in self.trees[:n_trees]:
            t.descend(bins, s)
        return s

    def fold(self) -> Model:
        return Model(self.config, self.edges, self.classes, self.base, [t.fold() for t in self.trees], self.stamp)

    def used_features(self) -> list[int]:
        return sorted({int(f) for t in self.trees for f in t.feature[t.nodes()] if f >= 0})

    def importance(self, spark: SparkSession) -> DataFrame:
        """(feature, splits, gain)."""
        rows = [(int(t.feature[j]), float(t.gain[j])) for t in self.trees for j in t.nodes() if t.feature[j] >= 0]
        return spark.createDataFrame(rows, "feature int, g double").groupBy("feature").agg(F.count("*").alias("splits"), F.sum("g").alias("gain"))

    def rules(self, names: list[str] | None = None) -> list[tuple[int, int, str, list[float]]]:
        """(tree, leaf, condition, leaf vector) of every leaf of the folded model."""
        out = []
        for k, t in enumerate(self.fold().trees):
            todo = [(1, [])]
            while todo:
                j, path = todo.pop()
                f = int(t.feature[j])
                if f < 0:
                    out.append((k, j, " AND ".join(path) or "TRUE", t.delta[j].tolist()))
                    continue
                name, edge = names[f] if names else f"x{f}", self.edge(f, int(t.bin[j]))
                null = " OR {} IS NULL" if t.left_default[j] else " AND {} IS NOT NULL"
                todo.append((2 * j + 1, [*path, f"NOT ({name} <= {edge}{null.format(name)})"]))
                todo.append((2 * j, [*path, f"({name} <= {edge}{null.format(name)})"]))
        return out

    def regrid(self) -> Model:
        """The same model over the thresholds that its nodes hold by value: edges are those, and bins their places."""
        used: list[set] = [set() for _ in self.edges]
        for t in self.trees:
            for j in t.nodes():
                if t.feature[j] >= 0:
                    used[t.feature[j]].add(float(t.cut[j]))
        edges, out = [sorted(u) for u in used], []
        for t in self.trees:
            t = t.fold()
            for j in t.nodes():
                if t.feature[j] >= 0:
                    t.bin[j] = edges[t.feature[j]].index(float(t.cut[j])) + 1
            out.append(t)
        return Model(self.config, edges, self.classes, self.base, out, self.stamp)

    def edge(self, f: int, b: int) -> float | None:
        return self.edges[f][b - 1] if 1 <= b <= len(self.edges[f]) else float("-inf") if b < 1 else float("inf")

    def table(self, spark: SparkSession) -> DataFrame:
        rows = [(k, j, j.bit_length() - 1, bool(t.feature[j] < 0), int(t.feature[j]), int(t.bin[j]), (self.edge(int(t.feature[j]), int(t.bin[j])) if np.isnan(t.cut[j]) else float(t.cut[j])) if t.feature[j] >= 0 else None, bool(t.left_default[j]), t.delta[j].tolist(), int(t.n[j]), float(t.gain[j]), t.target, self.stamp) for k, t in enumerate(self.trees) for j in t.nodes()]
        return spark.createDataFrame(rows, NODE)

    def save(self, spark: SparkSession, path: str) -> None:
        """Nodes and meta data as Parquet; a stamp's rows are written once and a later stamp adds its own."""
        meta = [(self.stamp, self.config.to_json(), [list(map(float, e)) for e in self.edges], [str(c) for c in self.classes], self.base.tolist())]
        # one partition: a model is small by construction (trees x 2^depth x outputs)
        self.table(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/stamp={self.stamp}/nodes")
        spark.createDataFrame(meta, "stamp long, config string, edges array<array<double>>, classes array<string>, base array<double>").coalesce(1).write.mode("overwrite").parquet(f"{path}/stamp={self.stamp}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str, stamp: int) -> Model:
        m = spark.read.parquet(f"{path}/stamp={stamp}/meta").first()
        config = BoostConfig.from_json(m.config)
        out = Model(config, [list(e) for e in m.edges], list(m.classes), np.array(m.base), [], m.stamp)
        for r in spark.read.schema(NODE).parquet(f"{path}/stamp={stamp}/nodes").orderBy("tree", "node").collect():
            while len(out.trees) <= r.tree:
                out.trees.append(Tree(config.outputs, config.depth))
            t = out.trees[r.tree]
            t.target, t.delta[r.node], t.n[r.node], t.gain[r.node] = r.target_class, r.delta, r.n, r.gain
            if not r.is_leaf:
                t.split(r.node, r.feature, r.bin, r.default_left, r.gain, r.edge)
        return out


def score(df: DataFrame, model: Model, keep: list[str], n_trees: int | None = None) -> DataFrame:
    """(keep, scores, prediction) of binned rows: the folded model goes to every task, rows don't move."""
    folded, loss = model.fold(), loss_of(model.config.loss, model.config.outputs, model.config.label_encoding)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            s = folded.scores(byte_matrix(b.column("bins")), n_trees) if b.num_rows else np.zeros((0, folded.config.outputs))
            p = loss.predict(s)
            best = (p[:, 0] >= 0.5).astype(np.int32) if loss.kind == "binary" else p.argmax(axis=1).astype(np.int32)
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in keep), to_lists(s), to_lists(p), pa.array(best)], [*keep, "scores", "probability", "prediction"])

    from pyspark.sql.types import ArrayType, DoubleType, IntegerType, StructField, StructType

    kept = df.select(*keep).schema.fields
    return df.select(*dict.fromkeys(["bins", *keep])).mapInArrow(run, StructType([*kept, StructField("scores", ArrayType(DoubleType())), StructField("probability", ArrayType(DoubleType())), StructField("prediction", IntegerType())]))


def score_expr(model: Model, cols: list[str]) -> list:
    """One column a score, as nested conditionals over raw features: all in the JVM, for a few small trees."""
    folded = model.fold()

    def tree(t: Tree, j: int, k: int):
        if t.feature[j] < 0:
            return F.lit(float(t.delta[j, k]))
        x = F.col(cols[int(t.feature[j])]).cast("double")
        missing = x.isNull() | F.isnan(x)
        left = F.when(missing, F.lit(bool(t.left_default[j]))).otherwise(x <= F.lit(folded.edge(int(t.feature[j]), int(t.bin[j]))))
        return F.when(left, tree(t, 2 * j, k)).otherwise(tree(t, 2 * j + 1, k))

    out = []
    for k in range(model.config.outputs):
        e = F.lit(float(model.base[k]))
        for t in folded.trees:
            if np.any(t.delta[:, k]):
                e = e + tree(t, 1, k)
        out.append(e)
    return out
