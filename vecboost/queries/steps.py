"""The steps of the method one by one, at the first layer of the small workload unless said."""

from __future__ import annotations


import numpy as np
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..config import BoostConfig
from ..functions.losses import Logistic, codewords, loss_of
from ..operators import native as N
from ..operators.binning import bin_expr, binned, edges, range_join_bins
from ..operators.derivatives import derivatives
from ..plans.boost import Rows, cells, layer_sums, met, quota_slice, write_slices
from ..plans.jvm import node_expr
from ..plans.kernel import Wip, bins_of
from ..plans.model import Model, Tree
from ..plans.workloads import T3_EDGES, T3_FEATURES, oblique, slice3, sliced, table
from ..sources.io import scratch
from ..streaming.minibatch import StampedStore, Trainer
from . import query
from .boosters import Y_SQL, Sql, base_sql, booster_sql

BINS = ["b0", "b1", "b2", "b3"]


def t3(spark, sf_dir):
    d = slice3(spark, sf_dir)
    return d.select("test", *[bin_expr(c, e).alias(b) for b, c, e in zip(BINS, T3_FEATURES, T3_EDGES)], "y", F.lit(1).alias("node"))


def engine(spark, sf_dir, **k):
    """The training rows of the small workload, an empty model and its first tree, as the engine takes them."""
    rows = binned(slice3(spark, sf_dir).where("not test"), T3_FEATURES, T3_EDGES, ["y"])
    cfg = BoostConfig(outputs=3, depth=2, **k)
    return rows, Model(cfg, T3_EDGES), Wip(Tree(3, 2))


def split_once(wip: Wip) -> Wip:
    """The tree with its root split at the fourth price edge."""
    wip.tree.split(1, 1, 4, True, 1.0)
    wip.tree.n[2], wip.tree.n[3] = 1, 2
    wip.open = (2, 3)
    return wip


def train(spark, sf_dir, stats):
    return t3(spark, sf_dir).where("not test").select("node", *BINS, *N.named(*stats))


def softmax0(packed: bool):
    """Derivatives at zero scores."""
    return N.softmax_stats([F.lit(0.0)] * 3, F.col("y"), packed)


def r6(*names):
    return [F.round(n, 6).alias(n) for n in names]


STATS = [f"g{k}" for k in range(3)] + [f"h{k}" for k in range(3)]
FULL = [f"g{k}" for k in range(3)] + [f"h{k}" for k in range(6)]

# ---- derived once for the SQL side: root sums under zero scores, where p = 1/3
ROOT = f"""
z AS ({base_sql("class")}),
r AS (SELECT *, 1.0/3 - (y=0)::INT AS g0, 1.0/3 - (y=1)::INT AS g1, 1.0/3 - (y=2)::INT AS g2, 2.0/9 AS h0, 2.0/9 AS h1, 2.0/9 AS h2, -1.0/9 AS h3, -1.0/9 AS h4, -1.0/9 AS h5 FROM z WHERE NOT test),
c AS (SELECT feature, bin, count(*) AS n, {", ".join(f"sum({s})::DOUBLE AS {s}" for s in FULL)} FROM (
  SELECT *, 0 AS feature, b0 AS bin FROM r UNION ALL SELECT *, 1, b1 FROM r UNION ALL SELECT *, 2, b2 FROM r UNION ALL SELECT *, 3, b3 FROM r) GROUP BY ALL)"""


def best_sql(f: Sql, top: int = 1, extra: str = "") -> str:
    G, H = [f"g{k}" for k in range(3)], [f"h{k}" for k in range(3 if f.hessian in ("diagonal", "identity") else 6)]
    over = "OVER (PARTITION BY feature ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)"
    L, R, T = ([[f"l{x}" for x in v] for v in (G, H)], [[f"(t{x}-l{x})" for x in v] for v in (G, H)], [[f"t{x}" for x in v] for v in (G, H)])
    return f"""WITH {ROOT}, p AS (SELECT feature, bin, {", ".join(f"sum({x}) {over} AS l{x}, sum({x}) OVER (PARTITION BY feature) AS t{x}" for x in ["n", *G, *H])} FROM c),
k AS (SELECT feature, bin, ln::BIGINT AS nl, (tn-ln)::BIGINT AS nr, round({f.gain(*L, "ln")} + {f.gain(*R, "(tn-ln)")} - {f.gain(*T, "tn")}, 9) AS gain FROM p WHERE ln < tn)
SELECT 1 AS node, feature, bin, nl, nr, round(gain, 4) AS gain, place::INT AS place FROM (SELECT *, row_number() OVER (ORDER BY gain DESC, feature, bin) AS place FROM k) WHERE place <= {top} {extra}"""


def splits(spark, sf_dir, hessian="diagonal"):
    """The engine's best split of the root."""
    rows, model, wip = engine(spark, sf_dir, hessian=hessian)
    source = Rows(rows)
    found = source.splits(model, [wip], 0, False)
    source.forget()
    return spark.createDataFrame([(r.node, r.feature, r.bin, r.nl, r.nr, round(r.gain, 4), 1) for r in found], "node int, feature int, bin int, nl long, nr long, gain double, place int")


def ranked(spark, sf_dir, top):
    """The best splits of the root by column expressions, as JvmRows has them."""
    rows = train(spark, sf_dir, softmax0(False))
    c = N.candidates(N.prefix(N.histogram(rows, BINS, STATS), STATS), 3, 3, 1.0)
    return N.best(c, top=top).withColumn("gain", F.round("gain", 4))


@query(best_sql(Sql(3)))
def best_split_root(spark, sf_dir):
    return splits(spark, sf_dir)


@query(best_sql(Sql(3, hessian="full")))
def best_split_full_c3(spark, sf_dir):
    return splits(spark, sf_dir, "full")


@query(best_sql(Sql(3, hessian="pair")))
def best_split_pairblock(spark, sf_dir):
    return splits(spark, sf_dir, "pair")


@query(best_sql(Sql(3, hessian="identity")))
def best_split_firstorder(spark, sf_dir):
    return splits(spark, sf_dir, "identity")


@query(best_sql(Sql(3), 5))
def topk_splits(spark, sf_dir):
    return ranked(spark, sf_dir, 5)


@query(best_sql(Sql(3), 99, "AND gain > 500"))
def preprune_filter(spark, sf_dir):
    """Candidates left when a split must gain more than 500: pruning while growing."""
    return ranked(spark, sf_dir, 99).where("gain > 500")


@query(f"WITH {ROOT}, w AS (SELECT feature, bin, sum(n) OVER u AS nl, sum(g0) OVER u AS gl0, sum(h0) OVER u AS hl0, sum(n) OVER (PARTITION BY feature) AS nt FROM c WINDOW u AS (PARTITION BY feature ORDER BY bin ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)) SELECT feature, bin, nl::BIGINT AS nl, nt::BIGINT AS nt, round(gl0, 6) AS gl0, round(hl0, 6) AS hl0 FROM w")
def prefix_gains_root(spark, sf_dir):
    rows = train(spark, sf_dir, softmax0(False))
    p = N.prefix(N.histogram(rows, BINS, STATS), STATS)
    return p.select("feature", "bin", F.col("l_n").alias("nl"), F.col("t_n").alias("nt"), F.round("l_g0", 6).alias("gl0"), F.round("l_h0", 6).alias("hl0"))


#: The order in which the engine holds the pairs of a full Hessian.
PACKED = ["g0", "g1", "g2", "h0", "h3", "h4", "h1", "h5", "h2"]


def root_cells(spark, sf_dir, hessian, stats):
    rows, model, wip = engine(spark, sf_dir, hessian=hessian)
    return cells(met(layer_sums(rows, model, [wip], False), model.config, False, bins_of(model)), bins_of(model), stats)


@query(f"WITH {ROOT} SELECT feature, bin, n, {', '.join(f'round({s}, 6) AS {s}' for s in STATS)} FROM c")
def hist_softmax_root(spark, sf_dir):
    return root_cells(spark, sf_dir, "diagonal", STATS).select("feature", "bin", "n", *r6(*STATS))


@query(f"WITH {ROOT} SELECT feature, bin, n, {', '.join(f'round({s}, 6) AS {s}' for s in FULL)} FROM c")
def hist_full_root(spark, sf_dir):
    return root_cells(spark, sf_dir, "full", PACKED).select("feature", "bin", "n", *r6(*FULL))


@query(f"WITH {ROOT} SELECT feature, bin, n, round(g0, 6) AS g0 FROM c")
def hist_decimal_exact(spark, sf_dir):
    """Decimal sums do not depend on the order in which rows are added."""
    h = N.histogram(train(spark, sf_dir, softmax0(False)), BINS, ["g0"], decimal=True)
    return h.select("feature", "bin", "n", F.round(F.col("g0").cast("double"), 6).alias("g0"))


@query(f"WITH {ROOT} SELECT feature, bin, count(*) AS n, round(sum(g0), 6) AS g0 FROM (SELECT *, 0 AS feature, b0 AS bin FROM r UNION ALL SELECT *, 1, b1 FROM r UNION ALL SELECT *, 2, b2 FROM r UNION ALL SELECT *, 3, b3 FROM r) WHERE b1 > 4 GROUP BY ALL")
def hist_sibling_subtract(spark, sf_dir):
    """The right child's histogram as the parent's minus the left child's, which alone is summed."""
    rows, model, wip = engine(spark, sf_dir)
    root = met(layer_sums(rows, model, [wip], False), model.config, False, bins_of(model))
    left = layer_sums(rows, model, [split_once(wip)], False, summed=[(2,)])
    both = met(left, model.config, False, bins_of(model), root)
    return cells(both, bins_of(model), STATS).where("node = 3").select("feature", "bin", "n", F.round("g0", 6).alias("g0"))


@query(f"WITH {ROOT} SELECT CASE WHEN b1 <= 4 THEN 2 ELSE 3 END AS node, count(*) AS n, {', '.join(f'round(sum({s}), 6) AS {s}' for s in STATS)} FROM r GROUP BY 1")
def node_totals(spark, sf_dir):
    """One feature's cells hold every row of a node once."""
    rows, model, wip = engine(spark, sf_dir)
    one = cells(layer_sums(rows, model, [split_once(wip)], False, features=(0, 1)), bins_of(model), STATS)
    return one.groupBy("node").agg(F.sum("n").alias("n"), *[F.round(F.sum(s), 6).alias(s) for s in STATS])


def leaf_sql(f: Sql) -> str:
    H = [f"h{k}" for k in range(3 if f.hessian in ("diagonal", "identity") else 6)]
    w = f.weight(["g0", "g1", "g2"], H, "n")
    return f"WITH {ROOT}, t AS (SELECT CASE WHEN b1 <= 4 THEN 2 ELSE 3 END AS node, count(*) AS n, {', '.join(f'sum({s}) AS {s}' for s in FULL)} FROM r GROUP BY 1) SELECT node, {', '.join(f'round({x}, 6) AS w{k}' for k, x in enumerate(w))} FROM t"


def leaves(spark, sf_dir, hessian, zero_sum=None):
    rows, model, wip = engine(spark, sf_dir, hessian=hessian, zero_sum=zero_sum)
    found = Rows(rows).splits(model, [split_once(wip)], 1, False, features=1)
    return spark.createDataFrame([(r.node, *[round(v, 6) for v in r.w]) for r in found], "node int, w0 double, w1 double, w2 double")


@query(leaf_sql(Sql(3)))
def leaf_weights_diag(spark, sf_dir):
    return leaves(spark, sf_dir, "diagonal")


@query(leaf_sql(Sql(3, hessian="full")))
def leaf_weights_full_c3(spark, sf_dir):
    return leaves(spark, sf_dir, "full")


@query(leaf_sql(Sql(3, zero_sum=True)))
def leaf_weights_zero_sum(spark, sf_dir):
    return leaves(spark, sf_dir, "diagonal", "multiplier")


@query(f"WITH z AS ({base_sql('class')}) SELECT test, CASE WHEN b1 <= 4 THEN CASE WHEN b2 <= 3 THEN 4 ELSE 5 END ELSE CASE WHEN b3 <= 5 THEN 6 ELSE 7 END END AS node, y, count(*) AS n FROM z GROUP BY ALL")
def split_apply_fixed(spark, sf_dir):
    """Rows by node of a fixed depth-2 tree."""
    t = Tree(3, 2)
    for j, f, b in ((1, 1, 4), (2, 2, 3), (3, 3, 5)):
        t.split(j, f, b, True, 1.0)
    return t3(spark, sf_dir).groupBy("test", node_expr(t, BINS).alias("node"), "y").agg(F.count("*").alias("n"))


# ---- bins and edges
@query("SELECT DISTINCT * FROM (" + " UNION ALL ".join(f"SELECT {i} AS feature, round(quantile_cont({c}, {k / 8}), 6) AS edge FROM lineitem" for i, c in enumerate(T3_FEATURES) for k in range(1, 8)) + ")")
def quantile_edges_exact(spark, sf_dir):
    cuts = edges(table(spark, sf_dir, "lineitem"), T3_FEATURES, 8, "exact")
    return spark.createDataFrame([(i, round(e, 6)) for i, c in enumerate(cuts) for e in c], "feature int, edge double")


@query("SELECT b AS bin, max(l_extendedprice) AS edge, count(*) AS n FROM (SELECT l_extendedprice, ntile(8) OVER (ORDER BY l_extendedprice) AS b FROM lineitem) GROUP BY b".replace("b AS bin", "b::INT AS bin"))
def ntile_edges(spark, sf_dir):
    """Equal-count bins by a global order: exact, and only for tables that one window may hold."""
    d = table(spark, sf_dir, "lineitem").select("l_extendedprice", F.ntile(8).over(W.orderBy("l_extendedprice")).alias("bin"))
    return d.groupBy("bin").agg(F.max("l_extendedprice").alias("edge"), F.count("*").alias("n"))


@query("SELECT (0) AS feature, true AS within UNION ALL SELECT 1, true")
def quantile_edges_sketch(spark, sf_dir):
    """Whether the ranks that rows equal to each KLL edge take come within 4 % of the asked one."""
    d = table(spark, sf_dir, "lineitem")
    cols, n = ["l_extendedprice", "l_quantity"], 16
    cuts = edges(d, cols, n, "kll")
    checks = []
    for i, (c, e) in enumerate(zip(cols, cuts)):
        worst = F.greatest(*[F.greatest((k + 1) / n - F.avg((F.col(c) <= x).cast("double")), F.avg((F.col(c) < x).cast("double")) - (k + 1) / n) - 0.04 for k, x in enumerate(e)]) if len(e) == n - 1 else F.lit(1.0)
        checks.append(F.struct(F.lit(i).alias("feature"), (worst <= 0).alias("within")))
    return d.agg(*[c.alias(f"c{i}") for i, c in enumerate(checks)]).select(F.explode(F.array("c0", "c1")).alias("x")).select("x.*")


@query("SELECT least(greatest(ceil((l_extendedprice - lo) / ((hi - lo) / 16)), 1), 16)::INT AS bin, count(*) AS n FROM lineitem CROSS JOIN (SELECT min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem) GROUP BY 1")
def bin_uniform(spark, sf_dir):
    d = table(spark, sf_dir, "lineitem").select("l_extendedprice")
    cuts = edges(d, ["l_extendedprice"], 16, "uniform")[0]
    return d.groupBy(bin_expr("l_extendedprice", cuts).alias("bin")).agg(F.count("*").alias("n"))


@query("SELECT " + "CASE " + " ".join(f"WHEN l_extendedprice <= {e} THEN {i + 1}" for i, e in enumerate(T3_EDGES[1])) + " ELSE 8 END AS bin, count(*) AS n FROM lineitem GROUP BY 1")
def bin_by_range_join(spark, sf_dir):
    """Bins by a range join with the table of edges."""
    return range_join_bins(table(spark, sf_dir, "lineitem").select("l_extendedprice"), "l_extendedprice", T3_EDGES[1]).groupBy("bin").agg(F.count("*").alias("n"))


# ---- labels and derivatives
@query("SELECT vec_id, (list_position(embedding[1:10], list_max(embedding[1:10])) - 1)::INT AS y FROM embeddings")
def argmax_label_emb10(spark, sf_dir):
    first = F.slice("embedding", 1, 10)
    return table(spark, sf_dir, "embeddings").select("vec_id", (F.array_position(first, F.array_max(first)) - 1).cast("int").alias("y"))


def code_query(kind):
    def run(spark, sf_dir):
        m = codewords(5, kind)
        y = F.col("label") % 5
        return table(spark, sf_dir, "embeddings").groupBy(y.cast("int").alias("y")).agg(F.count("*").alias("n")).select("y", "n", *[F.round(F.element_at(F.array(*[F.lit(float(v)) for v in m[:, k]]), F.col("y") + 1), 6).alias(f"u{k}") for k in range(5)])

    run.__name__ = {"onehot": "label_code_onehot", "centered": "label_code_centered", "simplex": "label_code_simplex"}[kind]
    return run


def code_sql(on, off):
    return "SELECT (label % 5)::INT AS y, count(*) AS n, " + ", ".join(f"round(CASE WHEN label % 5 = {k} THEN {on} ELSE {off} END::DOUBLE, 6) AS u{k}" for k in range(5)) + " FROM embeddings GROUP BY label % 5"


query(code_sql("1.0", "0.0"))(code_query("onehot"))
query(code_sql("1.0", "-0.25"))(code_query("centered"))
query(code_sql("(1-1.0/5)/sqrt(1-1.0/5)", "(-1.0/5)/sqrt(1-1.0/5)"))(code_query("simplex"))

KEY = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]


def scored_lines(spark, sf_dir):
    """Lines with three made-up scores and the slice label."""
    d = table(spark, sf_dir, "lineitem")
    return d.select(*KEY, "l_tax", (F.col("l_quantity") / 25 - 1).alias("s0"), (F.col("l_discount") * 10 - 0.5).alias("s1"), (F.col("l_tax") * 5).alias("s2"), sliced(oblique(), [1.6, 2.4]).alias("y"))


LINES = f"(SELECT {', '.join(KEY)}, l_tax, l_quantity/25 - 1 AS s0, l_discount*10 - 0.5 AS s1, l_tax*5 AS s2, {Y_SQL} AS y FROM lineitem)"


def grads_sql(f: Sql) -> str:
    e, g, _, loss = f.row()
    return f"SELECT {', '.join(KEY)}, {', '.join(f'round({x}, 6) AS g{k}' for k, x in enumerate(g))}, round({loss}, 6) AS loss FROM (SELECT *, {', '.join(f'{x} AS e{k}' for k, x in enumerate(e))} FROM {LINES})"


def of_loss(d, name, encoding):
    out = derivatives(d, loss_of(name, 3, encoding), ["s0", "s1", "s2"], "y", KEY)
    return out.select(*KEY, *r6("g0", "g1", "g2", "loss"))


@query(grads_sql(Sql(3)))
def softmax_gradients(spark, sf_dir):
    return of_loss(scored_lines(spark, sf_dir), "softmax", "onehot")


@query(grads_sql(Sql(3)))
def softmax_gradients_columns(spark, sf_dir):
    """The same by column expressions, as JvmRows has them."""
    d = scored_lines(spark, sf_dir)
    s = [F.col(f"s{k}") for k in range(3)]
    g, _ = N.softmax_stats(s, F.col("y"))
    loss = -F.log(F.greatest(F.element_at(F.array(*N.softmax_columns(s)), F.col("y") + 1), F.lit(1e-15)))
    return d.select(*KEY, *[F.round(x, 6).alias(f"g{k}") for k, x in enumerate(g)], F.round(loss, 6).alias("loss"))


@query(grads_sql(Sql(3, loss="multiexp")))
def exp_gradients(spark, sf_dir):
    return of_loss(scored_lines(spark, sf_dir), "multiexp", "centered")


@query(grads_sql(Sql(3, loss="marginexp")))
def margin_exp_gradients(spark, sf_dir):
    return of_loss(scored_lines(spark, sf_dir), "marginexp", "simplex")


@query(f"SELECT {', '.join(KEY)}, round(1/(1+exp(-s0)) - (y > 0)::INT, 6) AS g0, round(1/(1+exp(-s1)) - (l_tax > 0.04)::INT, 6) AS g1, round(1/(1+exp(-s0))*(1-1/(1+exp(-s0))), 6) AS h0 FROM {LINES}")
def multilabel_gradients(spark, sf_dir):
    d = scored_lines(spark, sf_dir).withColumn("y0", (F.col("y") > 0).cast("double")).withColumn("y1", (F.col("l_tax") > 0.04).cast("double"))
    out = derivatives(d, loss_of("multilabel", 2), ["s0", "s1"], ["y0", "y1"], KEY)
    return out.select(*KEY, *r6("g0", "g1", "h0"))


@query(f"SELECT {', '.join(KEY)}, round(1/(1+exp(-s0)) - (y > 0)::INT, 6) AS g0, round(-((y > 0)::INT*ln(1/(1+exp(-s0))) + (1-(y > 0)::INT)*ln(1-1/(1+exp(-s0)))), 6) AS loss FROM {LINES}")
def logistic_gradients(spark, sf_dir):
    d = scored_lines(spark, sf_dir).withColumn("y", (F.col("y") > 0).cast("double"))
    return derivatives(d, Logistic(), ["s0"], "y", KEY).select(*KEY, *r6("g0", "loss"))


# ---- machinery
#: The stamp of each of the batches that the lines are dealt to by their orders.
STAMPS = [3, 4, 4, 5]
PARTS = base_sql("class").replace("SELECT ", "SELECT l_orderkey % 4 AS part, ", 1)


@query("SELECT CASE WHEN b1 <= 4 THEN 2 ELSE 3 END AS node, feature, bin, count(*) AS n, round(sum(1/3::DOUBLE - (y = 0)::INT), 3) AS g FROM (" + " UNION ALL ".join(f"SELECT part, y, b1, {f} AS feature, b{f} AS bin FROM ({PARTS})" for f in range(4)) + ") WHERE part IN (1, 2) GROUP BY ALL")
def stale_stamp_filter(spark, sf_dir):
    """The store's sums of one stamp over lineitem in four batches: other stamps are stale, a batch that was sent twice counts once."""
    d = table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") % 4).alias("part"), *T3_FEATURES, sliced(oblique(), [1.6, 2.4]).alias("y"))
    store = StampedStore(spark, scratch(spark, "stamps"))
    model, wip = Model(BoostConfig(outputs=3, depth=2), T3_EDGES), split_once(Wip(Tree(3, 2)))
    for batch, stamp in [*enumerate(STAMPS)] * 2:  # every batch is pushed twice
        base = binned(d.where(F.col("part") == batch).drop("part"), T3_FEATURES, T3_EDGES, ["y"])
        store.push(layer_sums(base, model, [wip], False), stamp, batch)
    held = cells(store.current(4, [1, 2]), bins_of(model), ["g0", "g1", "g2", "h0", "h1", "h2"])
    return held.groupBy("node", "feature", "bin").agg(F.sum("n").alias("n"), F.round(F.sum("g0"), 3).alias("g"))


@query("SELECT k::INT AS layer, (SELECT count(*) FROM lineitem WHERE l_orderkey % 5 <> 0) // 8 * CASE WHEN k = 4 THEN 4 ELSE 1 END AS quota, true AS near, k = 4 OR TRUE AS pruned FROM (VALUES (0), (1), (2), (3), (4)) a(k)")
def rows_per_layer_slices(spark, sf_dir):
    """A slice of the rows for each of four layers and four times as much for the fifth, from whole folders: whether the rows
    drawn come near the quota, and whether the scan reads no more folders than that takes."""
    base = binned(table(spark, sf_dir, "lineitem").where("l_orderkey % 5 <> 0").withColumn("key", F.xxhash64(*table(spark, sf_dir, "lineitem").columns)), T3_FEATURES, T3_EDGES, ["key"])
    held = write_slices(base, scratch(spark, "slices"), 16)
    n, out = held.count(), []
    for layer in range(5):
        q = n // 8 * (4 if layer == 4 else 1)
        d = quota_slice(held, q, n, layer, 0, 7, 16)
        got = d.agg(F.count("*").alias("n"), F.count_distinct("slice").alias("folders")).first()
        out.append((layer, q, abs(got.n - q) < 6 * q**0.5 + 0.15 * q, got.folders <= -(-q * 16 // n)))
    return spark.createDataFrame(out, "layer int, quota long, near boolean, pruned boolean")


@query(booster_sql(Sql(3), 2, 2, 0.3, layered=True, root=False, measured=False))
def minibatch_replays(spark, sf_dir):
    """The mini-batch trainer over all training rows a layer, in three batches of which each comes twice, one is stale, and
    with a new trainer on the same path after every layer: the trees of the full batch, as SQL has them."""
    d = slice3(spark, sf_dir).where("not test").select(F.array(*[F.col(c).cast("double") for c in T3_FEATURES]).alias("x"), "y", F.pmod(F.xxhash64(*T3_FEATURES), F.lit(3)).alias("part")).persist()
    n, path = d.count(), scratch(spark, "minibatch")
    cfg = BoostConfig(outputs=3, n_trees=2, depth=2, schedule="layer", root_contributes=False, rows_per_layer=n)
    for layer in range(4):
        t = Trainer(spark, path, cfg, 4, T3_EDGES)
        for k in range(3):
            part = d.where(F.col("part") == k).select("x", "y")
            t.batch(part, 3 * layer + k, stamp=99)
            t.batch(part, 3 * layer + k)
            t.batch(part, 3 * layer + k)
    d.unpersist()
    rows = [(i, j, int(x.feature[j]), T3_EDGES[x.feature[j]].index(x.cut[j]) + 1, int(x.n[j]), round(float(x.gain[j]), 4)) for i, x in enumerate(t.model.trees) for j in x.nodes() if x.feature[j] >= 0]
    return spark.createDataFrame(rows, "tree int, node int, feature int, bin int, n long, gain double")


#: The splits of a fixed tree of depth 3, and what each costs as a share of the rows.
PRUNE = ["l_extendedprice <= 60000", "l_tax <= 0.04", "l_tax <= 0.04", "l_quantity <= 25", "l_discount <= 0.08", "l_discount <= 0.03", "l_extendedprice <= 95000"]
COST = 0.002


def leaf_of(j: int = 1) -> str:
    return f"CASE WHEN {PRUNE[j - 1]} THEN {leaf_of(2 * j)} ELSE {leaf_of(2 * j + 1)} END" if j < 8 else str(j)


@query(f"""WITH leaf AS (SELECT {leaf_of()} AS node, count(*) AS n, sum(y) AS g FROM (SELECT *, {Y_SQL} AS y FROM lineitem) GROUP BY 1),
s AS (SELECT node >> k AS node, sum(n) AS n, sum(g) AS g FROM leaf CROSS JOIN (VALUES (0), (1), (2), (3)) b(k) GROUP BY ALL),
t AS (SELECT p.node, 0.5 * (sum(c.g*c.g / (c.n + 1.0)) - any_value(p.g*p.g / (p.n + 1.0))) - {COST} * (SELECT n FROM s WHERE node = 1) AS gain FROM s p JOIN s c ON c.node // 2 = p.node GROUP BY p.node),
""" + """d2 AS (SELECT node, gain AS total FROM t WHERE node >= 4), d1 AS (SELECT p.node, p.gain + coalesce(sum(greatest(c.total, 0)), 0) AS total FROM t p LEFT JOIN d2 c ON c.node // 2 = p.node WHERE p.node IN (2, 3) GROUP BY p.node, p.gain),
d0 AS (SELECT p.node, p.gain + sum(greatest(c.total, 0)) AS total FROM t p JOIN d1 c ON c.node // 2 = p.node WHERE p.node = 1 GROUP BY p.node, p.gain),
x AS (SELECT * FROM d2 UNION ALL SELECT * FROM d1 UNION ALL SELECT * FROM d0)
SELECT x.node::INT AS node, x.total > 0 AND (x.node = 1 OR p.total > 0) AND (x.node < 4 OR (g.total > 0)) AS stays FROM x LEFT JOIN x p ON p.node = x.node // 2 LEFT JOIN x g ON g.node = x.node // 4""")
def postprune_collapse(spark, sf_dir):
    """Which splits of a fixed tree stay when negative subtrees are collapsed bottom-up. Their gains are those of the summed
    class numbers of lineitem's rows, less a cost."""
    d = table(spark, sf_dir, "lineitem").withColumn("y", sliced(oblique(), [1.6, 2.4]))
    n, g = np.zeros(16), np.zeros(16)
    for r in d.groupBy(F.expr(leaf_of()).alias("node")).agg(F.count("*").alias("n"), F.sum("y").alias("g")).collect():  # a row a leaf
        n[r.node], g[r.node] = r.n, r.g
    for j in range(7, 0, -1):
        n[j], g[j] = n[2 * j] + n[2 * j + 1], g[2 * j] + g[2 * j + 1]
    own = g * g / (n + 1)
    t = Tree(1, 3)
    for j in range(1, 8):
        t.split(j, 0, 1, True, 0.5 * (own[2 * j] + own[2 * j + 1] - own[j]) - COST * n[1])
    t.collapse()
    return spark.createDataFrame([(j, bool(t.feature[j] >= 0)) for j in range(1, 8)], "node int, stays boolean")
