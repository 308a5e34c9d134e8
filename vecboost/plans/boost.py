"""Distributed boosting: vector trees, layer-by-layer, and trees per class.

A layer is one job. Tasks score their rows with the model so far (or take the carried scores), find the rows' nodes in the
trees being grown, sum gradients and curvature by node, feature and bin, and give one row a (tree, node, feature). One
exchange on that key brings the sums together where the feature's best split is found; only winners reach the driver.
Where gradients stay the same down a tree, only the smaller child of a split is summed: its sibling is the parent less it.
"""

from __future__ import annotations

import gc
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, StructField, StructType

from ..config import BoostConfig
from ..functions.arrays import byte_matrix, list_matrix, to_lists
from .jvm import JvmRows
from .kernel import HELD, LocalRows, Split, Wip, add_cells, add_up, best_of, bins_of, hessian_for, loss_for, pack_cells, places, row_stats
from .model import Model, Tree

SPLIT = "tree int, node int, feature int, bin int, default_left boolean, gain double, n long, nl long, nr long, w array<double>, wl array<double>, wr array<double>"
SUMS = "tree int, node int, feature int, sums binary"
#: Rounds between two scorings of all rows by the whole model; tasks a core that a layer's sums come from.
REBASE, TASKS = 10, 4
#: Seconds between two collections of the driver's garbage, and when the last one was.
TIDY, tidied = 10, [0.0]


def tidy(spark) -> None:
    """Collects the driver's garbage, if that was not done just now. What Spark keeps of a layer's job (its shuffle files and broadcasts
    on the executors, plans and their texts here) goes only when the driver has garbage collected; a driver that only plans jobs
    seldom does until its whole heap is taken."""
    if time.monotonic() - tidied[0] >= TIDY:
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        tidied[0] = time.monotonic()


def flat(df: DataFrame) -> DataFrame:
    """Persisted rows by a plan of one node. Plans, which the driver keeps with their texts, would else hold those of all rounds before;
    the rows' lineage stays whole, so lost ones are made again."""
    spark = df.sparkSession
    return type(df)(spark._jsparkSession.internalCreateDataFrame(df._jdf.queryExecution().toRdd(), df._jdf.schema(), False), spark)


def targets(batch: pa.RecordBatch, kind: str) -> np.ndarray:
    y = batch.column("y")
    if kind == "class":
        return y.to_numpy(zero_copy_only=False).astype(np.int64)
    if kind == "binary":
        return y.to_numpy(zero_copy_only=False).astype(np.float64)
    if kind == "rank":
        return np.stack([y.to_numpy(zero_copy_only=False).astype(np.float64), batch.column("group").to_numpy(zero_copy_only=False).astype(np.float64)], axis=1)
    return list_matrix(y).astype(np.float64)


def whole_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches cut where the group changes, so that a group's rows (which follow each other) come together."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        g = b.column("group").to_numpy(zero_copy_only=False)
        if not len(g):
            continue
        last = int(np.flatnonzero(g != g[-1])[-1]) + 1 if g[0] != g[-1] else 0
        if last:
            held.append(b.slice(0, last))
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held = [b.slice(last)]
        elif held and held[-1].column("group")[-1].as_py() != g[0]:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held = [b]
        else:
            held.append(b)
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def by_group(base: DataFrame, cfg: BoostConfig) -> DataFrame:
    """base, for a ranking loss dealt so that a group's rows follow each other in one slice; groups are lists that a task can hold."""
    return base.repartition("group").sortWithinPartitions("group") if loss_for(cfg).kind == "rank" else base


def layer_sums(base: DataFrame, model: Model, wips: list[Wip], fresh: bool, summed: list[tuple[int, ...]] | None = None, features: tuple[int, int] | None = None) -> DataFrame:
    """Rows of SUMS: of every open node (or the nodes `summed` of each tree), one row a task and (tree, node, feature).

    fresh: gradients at the scores including the trees being grown (layer by layer); else at committed trees'. Features go
    in blocks that keep a task's sums under HELD bytes, one pass over the rows a block. A column x (array) is
    what trees with thresholds of their own are asked about.
    """
    cfg = model.config
    loss, bins = loss_for(cfg), bins_of(model)
    nodes = [t.open for t in wips] if summed is None else summed
    carried, weighted, counted, raw = "scores" in base.columns, "weight" in base.columns, "copies" in base.columns, "x" in base.columns
    n_stats = max(3 if t.direction is not None else 1 + hessian_for(cfg, False).c + hessian_for(cfg, False).width for t in wips)
    m = len(model.edges)
    first, end = features or (0, m)
    block = max(1, HELD // max(1, 8 * bins * n_stats * sum(map(len, nodes))))

    def sums_of(a: int, z: int):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held: dict[int, np.ndarray] = {}
            for b in whole_groups(batches) if loss.kind == "rank" else batches:
                if not b.num_rows:
                    continue
                x, y = byte_matrix(b.column("bins")), targets(b, loss.kind)
                asked = list_matrix(b.column("x")) if raw else x
                s = list_matrix(b.column("scores")).copy() if carried else model.scores(asked)
                spots = [t.tree.descend(asked, s if fresh else None) for t in wips]
                stats = row_stats(cfg, loss, wips, s, y, *(b.column(c).to_numpy(zero_copy_only=False) if there else None for c, there in (("weight", weighted), ("copies", counted))))
                for k, (t, spot, own) in enumerate(zip(wips, spots, stats)):
                    if nodes[k]:
                        if k not in held:
                            held[k] = np.zeros((len(nodes[k]), z - a, bins, own.shape[1]))
                        add_up(held[k], x[:, a:z], places(t, spot, nodes[k]), own)
            for k, out in held.items():
                for j, cells in zip(nodes[k], out):
                    if cells[0, :, 0].any():
                        yield pa.RecordBatch.from_arrays([pa.array([k] * (z - a), pa.int32()), pa.array([j] * (z - a), pa.int32()), pa.array(range(a, z), pa.int32()), pa.array([pack_cells(v) for v in cells], pa.binary())], ["tree", "node", "feature", "sums"])

        return run

    cols = ["bins", "y", *(["scores"] if carried else []), *(["weight"] if weighted else []), *(["copies"] if counted else []), *(["x"] if raw else []), *(["group"] if loss.kind == "rank" else [])]
    rows = base.select(*cols)
    if loss.kind != "rank":
        rows = rows.coalesce(TASKS * base.sparkSession.sparkContext.defaultParallelism)  # sums a task, not a file's slice, go to the exchange
    out = None
    for a in range(first, end, block):
        part = rows.mapInArrow(sums_of(a, min(a + block, end)), SUMS)
        out = part if out is None else out.union(part)
    return out


def slices_of(groups: int, cores: int, size: int) -> int:
    """Into how many slices groups of `size` bytes of sums meet: one a core, more where a task would hold too many of them, but no
    more than there are groups. Every slice beyond costs a Python task without rows, and the driver what it keeps of each task."""
    return max(1, min(groups, max(cores, -(-4 * groups * size // HELD))))


def met(sums: DataFrame, cfg: BoostConfig, scalar: bool, bins: int, parents: DataFrame | None = None, groups: int | None = None) -> DataFrame:
    """Rows of SUMS, one a (tree, node, feature): all tasks' sums together. parents: those of the layer above (only of nodes
    that were split), from which the children that nobody summed are had by subtraction. groups: how many meet, siblings as one,
    where that is known."""
    width = 1 + hessian_for(cfg, scalar).c + hessian_for(cfg, scalar).width

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple[int, int, int, int], np.ndarray] = {}
        for b in batches:
            for key in zip(*(b.column(c).to_pylist() for c in ("level", "tree", "node", "feature", "sums"))):
                *key, raw = key
                key = tuple(key)
                if key not in total:
                    total[key] = np.zeros((bins, width))
                add_cells(total[key], raw)
        out = {key[1:]: v for key, v in total.items() if key[0]}
        for (level, k, j, f), v in total.items():
            if not level:
                had = [c for c in (2 * j, 2 * j + 1) if (k, c, f) in out]
                if len(had) == 1:
                    rest = v - out[k, had[0], f]
                    rest[rest[:, 0] < 0.5] = 0  # no row: no rounding error either
                    out[k, 4 * j + 1 - had[0], f] = rest
                elif not had:  # the child summed has no row: the other has them all
                    raise ValueError("a split without rows on the summed side")
        if out:
            keys = sorted(out)
            yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int32()) for c in zip(*keys)), pa.array([pack_cells(out[k]) for k in keys], pa.binary())], ["tree", "node", "feature", "sums"])

    own = sums.withColumn("level", F.lit(1)).withColumn("at", F.floor(F.col("node") / 2).cast("int"))
    slices = () if groups is None else (slices_of(groups, sums.sparkSession.sparkContext.defaultParallelism, 2 * 8 * bins * width),)
    if parents is not None:
        own = own.unionByName(parents.withColumn("level", F.lit(0)).withColumn("at", F.col("node")))
        return own.repartition(*slices, "tree", "at", "feature").drop("at").mapInArrow(run, SUMS)
    return own.repartition(*slices, "tree", "node", "feature").drop("at").mapInArrow(run, SUMS)


def best_splits(sums: DataFrame, cfg: BoostConfig, scalar: bool, bins: int, layer_rows: float = 1, together: bool = False, groups: int | None = None) -> DataFrame:
    """Rows of SPLIT, one a (tree, node): the greatest gain, then the least feature, then the least bin. together: sums
    have met already; else groups: how many meet, where that is known."""
    width = 1 + hessian_for(cfg, scalar).c + hessian_for(cfg, scalar).width

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple[int, int, int], np.ndarray] = {}
        for b in batches:
            for *key, raw in zip(*(b.column(c).to_pylist() for c in ("tree", "node", "feature", "sums"))):
                key = tuple(key)
                if key not in total:
                    total[key] = np.zeros((bins, width))
                add_cells(total[key], raw)
        if not total:
            return
        keys = sorted(total)
        found = best_of(np.array(keys), np.stack([total[k] for k in keys]), cfg, scalar, layer_rows)
        kinds = [pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.bool_(), pa.float64(), pa.int64(), pa.int64(), pa.int64(), *[pa.list_(pa.float64())] * 3]
        names = [x.split()[0] for x in SPLIT.split(", ")]
        yield pa.RecordBatch.from_arrays([pa.array([getattr(r, n) for r in found], t) for n, t in zip(names, kinds)], names)

    slices = () if groups is None else (slices_of(groups, sums.sparkSession.sparkContext.defaultParallelism, 8 * bins * width),)
    each = (sums if together else sums.repartition(*slices, "tree", "node", "feature")).mapInArrow(find, SPLIT)
    rank = F.struct("gain", -F.col("feature"), -F.col("bin"))
    return each.groupBy("tree", "node").agg(F.max_by(F.struct(*each.columns), rank).alias("b")).select("b.*")


def cells(sums: DataFrame, bins: int, stats: list[str]) -> DataFrame:
    """(tree, node, feature, bin, n, stats..) of rows of SUMS, one a cell with rows: what people and SQL read."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for *key, raw in zip(*(b.column(c).to_pylist() for c in ("tree", "node", "feature", "sums"))):
                v = np.zeros((bins, 1 + len(stats)))
                add_cells(v, raw)
                at = np.flatnonzero(v[:, 0])
                yield pa.RecordBatch.from_arrays([*(pa.array([k] * len(at), pa.int32()) for k in key), pa.array(at, pa.int32()), pa.array(np.rint(v[at, 0]).astype(np.int64)), *(pa.array(v[at, 1 + k]) for k in range(len(stats)))], ["tree", "node", "feature", "bin", "n", *stats])

    return sums.mapInArrow(run, "tree int, node int, feature int, bin int, n long, " + ", ".join(f"{s} double" for s in stats))


class Rows:
    """Distributed rows of one round: a layer's splits, with the sums of the layer above kept for subtraction."""

    def __init__(self, base: DataFrame, n_rows: int | None = None):
        self.base, self.n_rows, self.above = base, n_rows, None

    def splits(self, model: Model, wips: list[Wip], layer: int, fresh: bool, features: int | None = None) -> list[Split]:
        cfg, scalar, bins = model.config, wips[0].direction is not None, bins_of(model)
        q = cfg.quota(layer)
        rows = self.base if q is None or features else quota_slice(self.base, q, self.n_rows, layer, len(model.trees), cfg.seed)
        read = (q if q is not None and q < (self.n_rows or 0) else self.n_rows) or 1
        whole = None if features is None else (0, features)
        groups = sum(len(w.open) for w in wips) * (features or len(model.edges))
        if fresh or q is not None or features:
            return [Split(**r.asDict()) for r in best_splits(layer_sums(rows, model, wips, fresh, features=whole), cfg, scalar, bins, read, groups=groups).collect()]  # a row an open node
        if layer == 0 or self.above is None:
            now = met(layer_sums(rows, model, wips, fresh), cfg, scalar, bins, groups=groups)
        else:
            split = [(k, j // 2) for k, w in enumerate(wips) for j in w.open if j % 2 == 0]
            kept = F.lit(False)
            for k, j in split:
                kept = kept | ((F.col("tree") == k) & (F.col("node") == j))
            summed = [tuple(j if w.tree.n[j] <= w.tree.n[j + 1] else j + 1 for j in w.open if j % 2 == 0) for w in wips]
            now = met(layer_sums(rows, model, wips, fresh, summed), cfg, scalar, bins, self.above.where(kept), groups // 2)
        now = now.persist()
        found = [Split(**r.asDict()) for r in best_splits(now, cfg, scalar, bins, read, together=True).collect()]
        self.forget()
        self.above = now
        tidy(self.base.sparkSession)
        return found

    def forget(self) -> None:
        if self.above is not None:
            self.above.unpersist()
        self.above = None


class Local(LocalRows):
    """LocalRows by the same calls."""

    def splits(self, model, wips, layer, fresh, features=None):
        return super().splits(model, wips, fresh, features)

    def forget(self) -> None:
        pass


def grow_layer(rows: Rows | Local | JvmRows, model: Model, wips: list[Wip], layer: int, fresh: bool) -> bool:
    """Adds one layer below the open nodes of every tree; False if nothing could be split."""
    cfg, scalar = model.config, wips[0].direction is not None
    return apply_splits(rows.splits(model, wips, layer, fresh), cfg, wips, layer, fresh, scalar)


def apply_splits(found: list[Split], cfg: BoostConfig, wips: list[Wip], layer: int, fresh: bool, scalar: bool = False, cut=None) -> bool:
    """Puts the splits found into the trees being grown; cut(feature, bin): the threshold to be kept with a node."""
    following: list[list[int]] = [[] for _ in wips]
    for r in sorted(found, key=lambda r: (r.tree, r.node)):
        wip = wips[r.tree]
        t, j = wip.tree, r.node
        vector = (lambda v: np.array(v)) if not scalar else (lambda v: v[0] * wip.commit)  # noqa: B023
        if layer == 0:
            t.n[1] = r.n
            if not fresh:
                t.delta[1] = cfg.eta * vector(r.w)
        ok = np.isfinite(r.gain) and (r.gain > 0 or cfg.pruning == "post")
        if not ok:
            continue
        t.split(j, r.feature, r.bin, r.default_left, r.gain, None if cut is None else cut(r.feature, r.bin))
        for child, w, n in ((2 * j, r.wl, r.nl), (2 * j + 1, r.wr, r.nr)):
            t.delta[child], t.n[child] = cfg.eta * vector(w), n
            following[r.tree].append(child)
        if not fresh:
            t.delta[j] = 0  # in tree mode only leaves hold weights
    for wip, some in zip(wips, following):
        wip.open = tuple(some)
    return any(following)


def write_slices(base: DataFrame, path: str, slices: int = 64, seed: int = 7) -> DataFrame:
    """Writes binned rows by a hash into `slices` folders and reads them back: a quota then reads some folders only."""
    what = [c for c in ("key", "bins", "y") if c in base.columns]
    base.withColumn("slice", F.pmod(F.xxhash64(*what, F.lit(seed)), F.lit(slices)).cast("int")).write.partitionBy("slice").parquet(path)
    return base.sparkSession.read.schema(StructType([*base.schema.fields, StructField("slice", IntegerType())])).parquet(path)


def quota_slice(base: DataFrame, quota: int, n: int, layer: int, tree: int, seed: int, slices: int = 64) -> DataFrame:
    """About quota of the n rows, another part of the data for each layer: no sort and no shuffle.

    Rows from write_slices (a column slice; `slices` of them) are taken by whole folders, the next ones for each layer, which
    prunes the others from the scan; what is more than the quota in the folders goes by a hash, as do all rows without that
    column. The hash takes the column key where there is one, so that equal rows are drawn one by one.
    """
    if n <= quota:
        return base
    share = quota / n
    what = ["group"] if "group" in base.columns else [c for c in ("key", "bins", "y") if c in base.columns]  # a list is drawn whole
    if "slice" in base.columns:
        several = max(1, -(-quota * slices // n))
        step = tree * 31 + layer
        base = base.where(F.col("slice").isin([(step * several + k) % slices for k in range(several)]))
        share = min(1.0, share * slices / several)
    kept = round(share * (1 << 30))
    return base.where(F.pmod(F.xxhash64(*what, F.lit(seed), F.lit(tree), F.lit(layer)), F.lit(1 << 30)) < kept)


def root_step(rows: Rows | Local | JvmRows, model: Model, wips: list[Wip]) -> None:
    """Layer by layer, the root's own contribution: totals of one feature suffice."""
    scalar = wips[0].direction is not None
    for r in rows.splits(model, wips, 0, True, features=1):
        w = wips[r.tree]
        w.tree.delta[1] = model.config.eta * (np.array(r.w) if not scalar else r.w[0] * w.commit)
        w.tree.n[1] = r.n


def grow(rows: Rows | Local | JvmRows, model: Model, wips: list[Wip]) -> list[Tree]:
    cfg = model.config
    fresh = cfg.layered
    if fresh and cfg.root_contributes:
        root_step(rows, model, wips)
    for layer in range(cfg.depth):
        if not grow_layer(rows, model, wips, layer, fresh):
            break
    rows.forget()
    for w in wips:
        if cfg.pruning == "post":
            w.tree.collapse()
            if not fresh:
                _leaf_weights_after_pruning(rows, model, w)
    return [w.tree for w in wips]


def _leaf_weights_after_pruning(rows: Rows | Local | JvmRows, model: Model, wip: Wip) -> None:
    """Nodes that became leaves get their own optimum: one pass over their rows."""
    lost = tuple(j for j in wip.tree.leaves() if not wip.tree.delta[j].any())
    if not lost:
        return
    own = Wip(wip.tree, wip.direction, wip.commit, lost)
    for r in rows.splits(model, [own], 0, False, features=1):
        wip.tree.delta[r.node] = model.config.eta * (np.array(r.w) if wip.direction is None else r.w[0] * wip.commit)


def prior_scores(base: DataFrame | LocalRows, cfg: BoostConfig) -> np.ndarray:
    """Logarithms of the classes' shares; of one output the log odds, of real targets the means. Weights count."""
    local, kind = isinstance(base, LocalRows), loss_for(cfg).kind
    if local:
        weight = base.weight if base.copies is None else base.copies if base.weight is None else base.weight * base.copies
    else:
        weight = (F.col("weight") if "weight" in base.columns else F.lit(1.0)) * (F.col("copies") if "copies" in base.columns else F.lit(1.0))
    if kind in ("real", "multi", "rank"):
        if local:
            mean = np.average(np.reshape(base.y, (len(base.y), -1)), axis=0, weights=weight)
        elif kind == "rank":
            return np.zeros(cfg.outputs)
        else:
            mean = np.array(base.agg(*[F.sum(F.element_at("y", k + 1) * weight) / F.sum(weight) for k in range(cfg.outputs)]).first(), float)
        return mean if kind == "real" else np.zeros(cfg.outputs) if kind == "rank" else np.log((mean + 1e-9) / (1 - mean + 1e-9))
    if local:
        n = dict(enumerate(np.bincount(base.y, weight, 2)))
    else:
        n = {r.y: r.c for r in base.groupBy("y").agg(F.sum(weight).alias("c")).collect()}
    if kind == "binary":
        return np.array([np.log((n.get(1, 0) + 1e-9) / (n.get(0, 0) + 1e-9))])
    p = np.array([n.get(k, 0) for k in range(cfg.outputs)], float) + 1e-9
    return np.log(p / p.sum())


def one_hot(c: int, k: int) -> np.ndarray:
    return np.eye(c)[k]


def round_of(cfg: BoostConfig, model: Model, how: str, base_class: int = 0) -> list[Wip]:
    """The trees of one round: vector, per_class, logitboost, abc."""
    c = cfg.outputs
    new = lambda k=None: Tree(c, cfg.depth, k)
    if how == "vector":
        return [Wip(new())]
    if how == "per_class":
        return [Wip(new(k), one_hot(c, k), one_hot(c, k)) for k in range(c)]
    if how == "logitboost":
        return [Wip(new(k), one_hot(c, k), (c - 1) / c * (one_hot(c, k) - 1 / c)) for k in range(c)]
    return [Wip(new(k), one_hot(c, k) - one_hot(c, base_class), one_hot(c, k) - one_hot(c, base_class)) for k in range(c) if k != base_class]


def training_loss(base: DataFrame | LocalRows, model: Model, by_class: bool = False):
    """Mean loss over the rows (or the mean of each class)."""
    if isinstance(base, LocalRows):
        return base.loss(model, by_class)
    cfg = model.config
    loss, base = loss_for(cfg), by_group(base, cfg)

    def run(batches):
        for b in whole_groups(batches) if loss.kind == "rank" else batches:
            if b.num_rows:
                y = targets(b, loss.kind)
                k = y if loss.kind == "class" else np.zeros(len(y), int)
                n = b.column("copies").to_numpy(zero_copy_only=False) if counted else np.ones(len(y))
                v = loss.value(model.scores(byte_matrix(b.column("bins"))), y) * n
                yield pa.RecordBatch.from_pydict({"k": pa.array(np.arange(cfg.outputs), pa.int32()), "v": np.bincount(k, v, cfg.outputs), "n": np.bincount(k, n, cfg.outputs)})

    counted = "copies" in base.columns
    sums = base.select("bins", "y", *(["copies"] if counted else []), *(["group"] if loss.kind == "rank" else [])).mapInArrow(run, "k int, v double, n double").groupBy("k").agg(F.sum("v").alias("v"), F.sum("n").alias("n")).collect()
    if by_class:
        return {r.k: r.v / r.n for r in sums if r.n}
    return sum(r.v for r in sums) / max(1.0, sum(r.n for r in sums))


def carry(base: DataFrame, model: Model, first: int, scored: DataFrame | None, keep: list[str]) -> DataFrame:
    """The rows with the scores of all committed trees: those before `first` come from `scored`."""
    had = scored is not None
    trees, c = model.trees[first:], model.config.outputs
    fields = base.select("bins", *keep).schema

    def run(batches):
        for b in batches:
            s = list_matrix(b.column("scores")).copy() if had and b.num_rows else np.tile(model.base, (b.num_rows, 1))
            if b.num_rows:
                x = byte_matrix(b.column("bins"))
                for t in trees:
                    t.descend(x, s)
            yield pa.RecordBatch.from_arrays([*(b.column(f.name) for f in fields), to_lists(s)], [*(f.name for f in fields), "scores"])

    source = scored if had else base.select("bins", *keep)
    if not had and loss_for(model.config).kind != "rank":
        source = source.coalesce(TASKS * base.sparkSession.sparkContext.defaultParallelism)  # as sums do, once for all rounds
    return source.mapInArrow(run, StructType([*fields.fields, StructField("scores", ArrayType(DoubleType()))]))


def fit(base: DataFrame | LocalRows | JvmRows, cfg: BoostConfig, edges: list[list[float]], how: str | None = None, classes: list | None = None, validation: DataFrame | LocalRows | None = None, base_class: str | int = "worst_class", model: Model | None = None) -> Model:
    """Trains on binned rows (bins BINARY, y label or target array; weight, copies, and for ranking group, optional; copies is
    how many equal rows a row stands for).

    how: vector (default), per_class, logitboost or abc. base_class, for abc: a class, 'worst_class' (greatest training
    loss) or 'exhaustive' (every class tried each round). model: one to go on from. Rows stay where they are; the
    model, which is small by construction, goes to every task. rescore='carried' keeps the committed trees' scores in a
    persisted column: each round adds its trees to the column of the last, and every REBASE rounds the column is made
    from the input and the whole model again, so lineage stays short and a lost executor costs little. With a quota a
    layer reads a slice only (whole folders of write_slices, where base comes from there), so its rows are scored there
    and the rows are counted once. A LocalRows base is trained on in this process, with the same arithmetic; a JvmRows base
    by column expressions alone.
    """
    if isinstance(base, JvmRows):
        model = model or Model(cfg, edges, classes or [])
        while len(model.trees) < cfg.n_trees:
            model.trees += grow(base, model, round_of(cfg, model, "vector"))
        base.release()
        model.stamp += 1
        return model
    local = isinstance(base, LocalRows)
    if local and cfg.rows_per_layer is not None:
        raise ValueError("quotas are drawn from distributed rows")
    if (base.copies is not None if local else "copies" in base.columns) and (cfg.rows_per_layer is not None or loss_for(cfg).kind == "rank"):
        raise ValueError("quotas and lists take rows one by one, not rows with copies")
    how = how or ("per_class" if cfg.schedule == "per_class" else "vector")
    model = model or Model(cfg, edges, classes or [], prior_scores(base, cfg) if cfg.base == "prior" else None)
    if local:
        own = Local(base.x, base.y, base.weight, base.group, base.copies)
        keep, n_rows = [], len(base)
    else:
        base = by_group(base, cfg)
        keep = ["y", *(c for c in ("weight", "copies", "group") if c in base.columns)]
        n_rows = (base.agg(F.sum("copies")).first()[0] if "copies" in base.columns else base.count()) if cfg.rows_per_layer is not None or cfg.l2_mode == "per_instance" else None
    held, spent, at, rounds = None, None, 0, 0  # held, spent: (persisted, its rows)
    best, since = np.inf, 0
    while len(model.trees) < cfg.n_trees:
        rows = base
        if not local and cfg.rescore == "carried" and cfg.rows_per_layer is None and model.trees:
            anew = held is None or rounds % REBASE == 0
            now = carry(base, model, 0 if anew else at, None if anew else held[1], keep).persist()
            spent, held, at, rounds = held, (now, flat(now)), len(model.trees), rounds + 1
            rows = held[1]
        source = own if local else Rows(rows, n_rows)
        if how == "per_class" and cfg.refresh in ("tree", "layer"):
            trees = grow(source, model, [round_of(cfg, model, how)[len(model.trees) % cfg.outputs]])
        elif how == "abc" and base_class == "exhaustive":
            tried = []
            for b in range(cfg.outputs):
                grown = grow(source, model, round_of(cfg, model, how, b))
                tried.append((training_loss(base, Model(cfg, edges, classes or [], model.base, model.trees + grown)), b, grown))
            trees = min(tried, key=lambda x: x[:2])[2]
        elif how == "abc":
            by = training_loss(base, model, True) if base_class == "worst_class" else {}
            trees = grow(source, model, round_of(cfg, model, how, max(by, key=lambda k: (by[k], -k)) if by else base_class))
        else:
            trees = grow(source, model, round_of(cfg, model, how))
        model.trees += trees
        if spent is not None:  # only now is the column that was made from it complete
            spent[0].unpersist()
            spent = None
        if cfg.patience and validation is not None:
            v = training_loss(validation, model)
            best, since = (v, 0) if v < best - 1e-12 else (best, since + 1)
            if since >= cfg.patience:
                model.trees = model.trees[: -since * len(trees)]
                break
    if held is not None:
        held[0].unpersist()
    model.stamp += 1
    return model
