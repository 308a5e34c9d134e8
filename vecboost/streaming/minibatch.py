"""Training from micro-batches with stamped sums.

Every batch is scored with the latest model, gives its sketch and its histograms under the current stamp, and is then
acknowledged. When a layer's row quota is reached, the sums of the acknowledged batches are flushed: one layer is grown,
the edges of the next stamp come from the sketches of all batches so far, the state is written, and the stamp moves on.
Contributions with another stamp are stale. Nodes keep their thresholds by value, so edges may move with the stream.

A batch that comes again under its stamp overwrites what it wrote; one that was flushed already changes nothing. A trainer
made anew on the same path goes on from the last flush: stamp, layer, tree being grown, edges and acknowledged batches.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import BoostConfig
from ..operators.binning import binned
from ..plans.boost import SUMS, apply_splits, best_splits, layer_sums
from ..plans.kernel import Split, Wip, bins_of
from ..plans.model import Model, Tree

STATE, ACK = "stamp long, state string", "batch_id long, stamp long, rows long"
#: The stamp of a batch that only sketched, as no edges were known yet.
WARM_UP = -1
#: Of a sketch: exact up to about as many values, ranks to about 0.15 % beyond; some 30 KB a feature.
SIZE = 2048


def read_if_there(spark: SparkSession, schema: str, path: str, base: str | None = None) -> DataFrame | None:
    try:
        r = spark.read.schema(schema)
        return (r.option("basePath", base) if base else r).parquet(path)
    except Exception as e:
        if "PATH_NOT_FOUND" not in str(e):
            raise
        return None


class SketchStore:
    """Mergeable KLL sketches of each feature: one set a batch, and one of all batches up to each stamp."""

    def __init__(self, spark: SparkSession, path: str, width: int, bins: int):
        self.spark, self.path, self.width, self.bins = spark, f"{path}/sketches", width, bins

    def update(self, batch: DataFrame, stamp: int, batch_id: int, x: str = "x") -> None:
        s = batch.select(F.posexplode(x).alias("f", "v")).where(~F.isnan("v")).groupBy("f").agg(F.kll_sketch_agg_double("v", SIZE).alias("sketch"))
        s.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/batches/stamp={stamp}/batch_id={batch_id}")  # a row a feature

    def merge(self, stamps: list[int], acked: list[int], into: int) -> list[list[float]]:
        """Adds the acknowledged batches of the stamps to all before; the edges then, empty for features without values."""
        parts = [read_if_there(self.spark, "f int, sketch binary", f"{self.path}/merged/stamp={into - 1}")]
        for s in stamps:
            d = read_if_there(self.spark, "f int, sketch binary, batch_id long", f"{self.path}/batches/stamp={s}", f"{self.path}/batches/stamp={s}")
            parts.append(None if d is None else d.where(F.col("batch_id").isin(acked)).select("f", "sketch"))
        parts = [p for p in parts if p is not None]
        if not parts:
            return [[] for _ in range(self.width)]
        held = parts[0]
        for p in parts[1:]:
            held = held.union(p)
        held.groupBy("f").agg(F.kll_merge_agg_double("sketch").alias("sketch")).coalesce(1).write.mode("overwrite").parquet(f"{self.path}/merged/stamp={into}")
        probs = [k / self.bins for k in range(1, self.bins)]
        merged = self.spark.read.schema("f int, sketch binary").parquet(f"{self.path}/merged/stamp={into}")
        got = merged.select("f", F.array(*[F.kll_sketch_get_quantile_double("sketch", F.lit(p)) for p in probs]).alias("e")).collect()  # a row a feature
        by = {r.f: sorted({float(v) for v in r.e if v is not None and np.isfinite(v)}) for r in got}
        return [by.get(f, []) for f in range(self.width)]


class StampedStore:
    """Histogram sums by (stamp, batch_id)."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, f"{path}/cells"

    def push(self, sums: DataFrame, stamp: int, batch_id: int) -> None:
        sums.write.mode("overwrite").parquet(f"{self.path}/stamp={stamp}/batch_id={batch_id}")

    def current(self, stamp: int, acked: list[int]) -> DataFrame:
        """Sums of the stamp's acknowledged batches."""
        at = f"{self.path}/stamp={stamp}"
        held = read_if_there(self.spark, SUMS + ", batch_id long", at, at)
        held = self.spark.createDataFrame([], SUMS + ", batch_id long") if held is None else held
        return held.where(F.col("batch_id").isin(acked)).drop("batch_id")


def tree_json(t: Tree) -> dict:
    return {k: np.asarray(getattr(t, k)).tolist() for k in ("feature", "bin", "left_default", "delta", "n", "gain", "cut")}


def tree_of(d: dict, outputs: int, depth: int) -> Tree:
    kinds = {"feature": np.int64, "bin": np.int64, "left_default": bool, "delta": float, "n": np.int64, "gain": float, "cut": float}
    return Tree(outputs, depth, None, **{k: np.array(d[k], v) for k, v in kinds.items()})


@dataclass
class Trainer:
    """foreachBatch(trainer.batch) trains; config.rows_per_layer is the quota of each layer (an int or one a layer).

    start_edges: fixed edges instead of sketched ones. The model's nodes hold thresholds by value; model.regrid() gives one
    over bins, which is also what is saved.
    """

    spark: SparkSession
    path: str
    config: BoostConfig
    width: int
    start_edges: list[list[float]] | None = None
    stamp: int = 0
    layer: int = 0
    stale: int = 0
    model: Model = None
    wip: Wip = None
    edges: list[list[float]] = None
    acked: dict[int, int] = field(default_factory=dict)

    def __post_init__(self):
        self.sketches = SketchStore(self.spark, self.path, self.width, self.config.bins)
        self.cells = StampedStore(self.spark, self.path)
        self.model = self.model or Model(self.config, [[] for _ in range(self.width)])
        self.wip = self.wip or Wip(Tree(self.config.outputs, self.config.depth))
        self.edges = self.edges or self.start_edges or [[] for _ in range(self.width)]
        self._load()

    @property
    def done(self) -> bool:
        return len(self.model.trees) >= self.config.n_trees

    def _load(self) -> None:
        held = read_if_there(self.spark, STATE, f"{self.path}/state/*")
        last = None if held is None else held.orderBy(F.desc("stamp")).first()
        if last is not None:
            d = json.loads(last.state)
            c, depth = self.config.outputs, self.config.depth
            self.stamp, self.layer, self.stale, self.edges = last.stamp, d["layer"], d["stale"], d["edges"]
            self.model.trees = [tree_of(t, c, depth) for t in d["trees"]]
            self.model.stamp = self.stamp
            self.wip = Wip(tree_of(d["wip"], c, depth), open=tuple(d["open"]))
        acks = read_if_there(self.spark, ACK, f"{self.path}/acks/*")
        if acks is not None:
            self.acked = {r.batch_id: r.rows for r in acks.where(F.col("stamp") == self.stamp).collect()}  # a row a batch of this stamp

    def _save(self) -> None:
        d = {"layer": self.layer, "stale": self.stale, "edges": self.edges, "trees": [tree_json(t) for t in self.model.trees], "wip": tree_json(self.wip.tree), "open": list(self.wip.open)}
        self.spark.createDataFrame([(self.stamp, json.dumps(d))], STATE).coalesce(1).write.mode("overwrite").parquet(f"{self.path}/state/stamp-{self.stamp}")

    def _ack(self, batch_id: int, stamp: int, rows: int) -> None:
        self.spark.createDataFrame([(batch_id, stamp, rows)], ACK).coalesce(1).write.mode("overwrite").parquet(f"{self.path}/acks/batch-{batch_id}")

    def batch(self, df: DataFrame, batch_id: int, stamp: int | None = None) -> None:
        """df: x array<double>, y. stamp: the one the sender had; another than the current is stale and only counted."""
        if self.done:
            return
        if stamp is not None and stamp != self.stamp:
            self.stale += df.count()
            return
        had = read_if_there(self.spark, ACK, f"{self.path}/acks/batch-{batch_id}")
        had = None if had is None else had.first()
        if had is not None and had.stamp != self.stamp:
            return  # flushed already, or what the first edges come from
        df = df.persist()
        rows = df.count()
        if rows:
            known = any(self.edges)
            self.sketches.update(df, self.stamp if known else WARM_UP, batch_id)
            if known:
                base = binned(df, "x", self.edges, ["y", "x"])
                grid = Model(self.config, self.edges, base=self.model.base, trees=self.model.trees)
                self.cells.push(layer_sums(base, grid, [self.wip], self.config.layered), self.stamp, batch_id)
                self._ack(batch_id, self.stamp, rows)
                self.acked[batch_id] = rows
                if sum(self.acked.values()) >= (self.config.quota(self.layer) or 1):
                    self.flush()
            else:
                self._ack(batch_id, WARM_UP, rows)
                self.edges = self.sketches.merge([WARM_UP], [batch_id], 0)
                self._save()
        df.unpersist()

    def flush(self) -> None:
        """Grows one layer from the current stamp's sums and moves the stamp, and the edges, on."""
        cfg, acked = self.config, sorted(self.acked)
        grid = Model(cfg, self.edges)
        sums = self.cells.current(self.stamp, acked)
        found = [Split(**r.asDict()) for r in best_splits(sums, cfg, False, bins_of(grid), sum(self.acked.values())).collect()]  # a row an open node
        more = apply_splits(found, cfg, [self.wip], self.layer, cfg.layered, cut=grid.edge)
        self.layer += 1
        if self.layer >= cfg.depth or not more:
            self.model.trees.append(self.wip.tree)
            self.wip, self.layer = Wip(Tree(cfg.outputs, cfg.depth)), 0
        if self.start_edges is None:
            self.edges = self.sketches.merge([self.stamp], acked, self.stamp + 1)
        self.stamp += 1
        self.model.stamp, self.acked = self.stamp, {}
        self._save()
        out = Model(cfg, self.edges, base=self.model.base, trees=self.model.trees, stamp=self.stamp).regrid()
        out.save(self.spark, f"{self.path}/model")


def train_stream(stream: DataFrame, trainer: Trainer, checkpoint: str):
    """A streaming query that trains until its source ends; batches replayed after a failure change nothing."""
    return stream.writeStream.foreachBatch(lambda df, k: trainer.batch(df, k)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
