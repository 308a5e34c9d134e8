"""Predictions of a fixed model, and the accuracy and cost measures."""

from __future__ import annotations


import numpy as np
from pyspark.sql import functions as F

from ..config import BoostConfig
from ..functions.significance import best_set, unpaired_t
from ..operators import metrics
from ..operators.binning import binned
from ..operators.native import softmax_columns
from ..plans.baselines import round_budget
from ..plans.boost import fit
from ..plans.model import Model, Tree, score_expr
from ..plans.workloads import T3_EDGES, oblique, sliced, table
from . import query
from .boosters import Y_SQL, Sql, booster_sql, fixed_rows

KEY = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
COLS = ["l_quantity", "l_extendedprice", "l_discount"]
#: A fixed model: edges of its features, and (node, feature, bin) and (node, deltas) of two trees.
EDGES = [[25.0, 40.0], [30000.0, 60000.0], [0.03, 0.06]]
SPLITS = [[(1, 1, 2), (2, 0, 1), (3, 2, 1)], [(1, 2, 2), (2, 1, 1), (3, 0, 2)]]
DELTAS = [{1: [0.1, 0.0, -0.1], 2: [0.2, 0.1, -0.3], 3: [-0.2, 0.1, 0.1], 4: [0.5, -0.1, -0.4], 5: [-0.1, 0.2, -0.1], 6: [0.0, 0.3, -0.3], 7: [-0.4, -0.1, 0.5]}, {1: [0.0, 0.05, -0.05], 2: [0.1, 0.1, -0.2], 3: [-0.1, 0.0, 0.1], 4: [0.3, 0.0, -0.3], 5: [0.0, 0.1, -0.1], 6: [-0.2, 0.2, 0.0], 7: [-0.3, -0.1, 0.4]}]


def fixed_model() -> Model:
    m = Model(BoostConfig(outputs=3, n_trees=2, depth=2, schedule="layer"), EDGES)
    for s, d in zip(SPLITS, DELTAS):
        t = Tree(3, 2)
        for j, f, b in s:
            t.split(j, f, b, True, 1.0)
        for j, v in d.items():
            t.delta[j] = v
        m.trees.append(t)
    return m


def side(j, f, b):
    return f"{COLS[f]} <= {EDGES[f][b - 1]}"


def path_sql(t: int, k: int, layers: int = 2) -> str:
    """A tree's score k down to `layers` below the root, as text."""
    (_, *root), left, right = SPLITS[t]
    top = side(1, *root)
    d = DELTAS[t]
    out = f"{d[1][k]}"
    if layers > 0:
        out += f" + CASE WHEN {top} THEN {d[2][k]} ELSE {d[3][k]} END"
    if layers > 1:
        out += f" + CASE WHEN {top} THEN CASE WHEN {side(*left)} THEN {d[4][k]} ELSE {d[5][k]} END ELSE CASE WHEN {side(*right)} THEN {d[6][k]} ELSE {d[7][k]} END END"
    return out


SCORED = f"(SELECT {', '.join(KEY)}, l_orderkey % 5 = 0 AS test, {Y_SQL} AS y, {', '.join(f'({path_sql(0, k)} + {path_sql(1, k)})::DOUBLE AS s{k}' for k in range(3))} FROM lineitem)"
PROB = f"(SELECT *, {', '.join(f'exp(s{k})/(exp(s0)+exp(s1)+exp(s2)) AS p{k}' for k in range(3))}, CASE WHEN s0 >= s1 AND s0 >= s2 THEN 0 WHEN s1 >= s2 THEN 1 ELSE 2 END AS prediction FROM {SCORED})"


def scored(spark, sf_dir):
    d = table(spark, sf_dir, "lineitem")
    s = score_expr(fixed_model(), COLS)
    d = d.select(*KEY, (F.col("l_orderkey") % 5 == 0).alias("test"), sliced(oblique(), [1.6, 2.4]).alias("y"), *[x.alias(f"s{k}") for k, x in enumerate(s)])
    p = softmax_columns([F.col(f"s{k}") for k in range(3)])
    d = d.withColumn("probability", F.array(*p))
    # ties go to the lowest class: compared on the rounded scores that SQL sees alike
    r = [F.round(f"s{k}", 9) for k in range(3)]
    return d.withColumn("prediction", F.when((r[0] >= r[1]) & (r[0] >= r[2]), 0).when(r[1] >= r[2], 1).otherwise(2))


PROB = PROB.replace("s0 >= s1 AND s0 >= s2", "round(s0,9) >= round(s1,9) AND round(s0,9) >= round(s2,9)").replace("WHEN s1 >= s2", "WHEN round(s1,9) >= round(s2,9)")


@query(f"SELECT {', '.join(KEY)}, prediction, {', '.join(f'round(s{k}, 6) AS s{k}' for k in range(3))} FROM {PROB}")
def predict_fixed_model(spark, sf_dir):
    return scored(spark, sf_dir).select(*KEY, "prediction", *[F.round(f"s{k}", 6).alias(f"s{k}") for k in range(3)])


@query(f"SELECT {', '.join(KEY)}, {', '.join(f'round(s{k}, 6) AS s{k}' for k in range(3))} FROM {SCORED}")
def predict_join_leafboxes(spark, sf_dir):
    """Scores by a range join with the leaves' boxes (four a tree, fixed)."""
    inf, boxes = float("inf"), []
    for t, tree in enumerate(fixed_model().fold().trees):
        for j in tree.leaves():
            lo, hi = [-inf] * 3, [inf] * 3
            k = j
            while k > 1:
                f, e = int(tree.feature[k // 2]), EDGES[int(tree.feature[k // 2])][int(tree.bin[k // 2]) - 1]
                if k % 2:
                    lo[f] = max(lo[f], e)
                else:
                    hi[f] = min(hi[f], e)
                k //= 2
            boxes.append((t, *lo, *hi, *tree.delta[j].tolist()))
    b = F.broadcast(spark.createDataFrame(boxes, "tree int, lo0 double, lo1 double, lo2 double, hi0 double, hi1 double, hi2 double, d0 double, d1 double, d2 double"))
    d = table(spark, sf_dir, "lineitem").withColumn("_row", F.monotonically_increasing_id())
    inside = None
    for k, c in enumerate(COLS):
        cond = (F.col(c) > F.col(f"lo{k}")) & (F.col(c) <= F.col(f"hi{k}"))
        inside = cond if inside is None else inside & cond
    return d.join(b, inside).groupBy("_row", *KEY).agg(*[F.round(F.sum(f"d{k}"), 6).alias(f"s{k}") for k in range(3)]).drop("_row")


@query(" UNION ALL ".join(f"SELECT {', '.join(KEY)}, {n} AS layers, {', '.join(f'round(({path_sql(0, k, n)})::DOUBLE, 6) AS s{k}' for k in range(3))} FROM lineitem" for n in range(3)))
def layered_prediction_fixed(spark, sf_dir):
    """Scores of the first tree after its root, its first and its second layer."""
    d, m = table(spark, sf_dir, "lineitem"), fixed_model()
    out = None
    for n in range(3):
        t = Tree(3, 2, delta=None)
        for j, f, b in SPLITS[0]:
            if j.bit_length() <= n:
                t.split(j, f, b, True, 1.0)
        t.delta[:] = m.trees[0].delta
        t.delta[2 ** (n + 1) :] = 0
        part = d.select(*KEY, F.lit(n).alias("layers"), *[F.round(x, 6).alias(f"s{k}") for k, x in enumerate(score_expr(Model(m.config, EDGES, trees=[t]), COLS))])
        out = part if out is None else out.unionAll(part)
    return out


@query(f"SELECT test, round(avg((prediction = y)::INT::DOUBLE), 6) AS accuracy FROM {PROB} GROUP BY test")
def accuracy_fixed(spark, sf_dir):
    return metrics.accuracy(scored(spark, sf_dir), by=["test"]).select("test", F.round("accuracy", 6).alias("accuracy"))


@query(f"SELECT round(avg(-ln(greatest(CASE y WHEN 0 THEN p0 WHEN 1 THEN p1 ELSE p2 END, 1e-15))), 6) AS cross_entropy FROM {PROB}")
def cross_entropy_fixed(spark, sf_dir):
    return metrics.cross_entropy(scored(spark, sf_dir)).select(F.round("cross_entropy", 6).alias("cross_entropy"))


@query(f"SELECT y, prediction, count(*) AS n FROM {PROB} GROUP BY ALL")
def confusion_matrix(spark, sf_dir):
    return metrics.confusion(scored(spark, sf_dir))


@query(f"SELECT y, prediction, count(*) AS n, grouping_id(y, prediction)::BIGINT AS level FROM {PROB} GROUP BY ROLLUP (y, prediction)")
def confusion_rollup(spark, sf_dir):
    return scored(spark, sf_dir).rollup("y", "prediction").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


@query(f"SELECT y, test, round(avg((prediction = y)::INT::DOUBLE), 6) AS accuracy, count(*) AS n FROM {PROB} GROUP BY CUBE (y, test)")
def accuracy_cube(spark, sf_dir):
    return scored(spark, sf_dir).withColumn("hit", (F.col("prediction") == F.col("y")).cast("double")).cube("y", "test").agg(F.round(F.avg("hit"), 6).alias("accuracy"), F.count("*").alias("n"))


MOMENTS = f"(SELECT test, avg((prediction = y)::INT::DOUBLE) AS m, stddev_samp((prediction = y)::INT::DOUBLE) AS s, count(*) AS n FROM {PROB} GROUP BY test)"


@query(f"SELECT test, round(m, 6) AS mean, round(s, 6) AS sd, n FROM {MOMENTS}")
def ttest_moments(spark, sf_dir):
    m = metrics.moments(scored(spark, sf_dir), by=["test"])
    return m.select("test", F.round("accuracy", 6).alias("mean"), F.round("accuracy_sd", 6).alias("sd"), F.col("n_test").alias("n"))


@query(f"SELECT round((a.m - b.m) / sqrt(a.s*a.s/a.n + b.s*b.s/b.n), 4) AS t, round(power(a.s*a.s/a.n + b.s*b.s/b.n, 2) / (power(a.s*a.s/a.n, 2)/(a.n-1) + power(b.s*b.s/b.n, 2)/(b.n-1)), 2) AS df FROM {MOMENTS} a JOIN {MOMENTS} b ON a.test AND NOT b.test")
def ttest_unpaired(spark, sf_dir):
    r = {x.test: x for x in metrics.moments(scored(spark, sf_dir), by=["test"]).collect()}  # two rows
    t, df, _ = unpaired_t(r[True].accuracy, r[True].accuracy_sd, r[True].n_test, r[False].accuracy, r[False].accuracy_sd, r[False].n_test)
    return spark.createDataFrame([(round(t, 4), round(df, 2))], "t double, df double")


#: Rules that predict the class: parts of the fixed model, as (tree, layers) each.
RULES = {"root": [(0, 0)], "one_layer": [(0, 1)], "one_tree": [(0, 2)], "second_tree": [(1, 2)], "both_one_layer": [(0, 1), (1, 1)], "both": [(0, 2), (1, 2)], "both_twice": [(0, 2), (1, 2)] * 2}


def part_of(m: Model, t: int, layers: int) -> Tree:
    """A tree of the fixed model down to `layers` below the root."""
    out = Tree(3, 2, delta=None)
    for j, f, b in SPLITS[t]:
        if j.bit_length() <= layers:
            out.split(j, f, b, True, 1.0)
    out.delta[:] = m.trees[t].delta
    out.delta[2 ** (layers + 1) :] = 0
    return out


def rule_sql(parts: list) -> str:
    s = ", ".join(f"round(({' + '.join(path_sql(t, k, n) for t, n in parts)})::DOUBLE, 9) AS s{k}" for k in range(3))
    return f"SELECT (CASE WHEN s0 >= s1 AND s0 >= s2 THEN 0 WHEN s1 >= s2 THEN 1 ELSE 2 END = y)::INT::DOUBLE AS hit FROM (SELECT {Y_SQL} AS y, {s} FROM lineitem WHERE l_orderkey % 5 = 0)"


@query("WITH e AS (" + " UNION ALL ".join(f"SELECT '{m}' AS method, avg(hit) AS m, stddev_samp(hit) AS s, count(*) AS n FROM ({rule_sql(p)})" for m, p in RULES.items()) + "), t AS (SELECT e.method, e.m, e.n, abs(b.m - e.m) AS d, b.s*b.s/b.n AS v, e.s*e.s/e.n AS w FROM e CROSS JOIN (SELECT * FROM e ORDER BY m DESC, method LIMIT 1) b) SELECT method, round(m, 6) AS accuracy, d = 0 OR d / sqrt(v + w) < 1.959964 + 2.372271 * (v*v + w*w) / (n - 1) / power(v + w, 2) AS in_best FROM t")
def best_set_rule(spark, sf_dir):
    """Parts of the fixed model that the t-test does not tell from the best on the test rows. The SQL takes the critical value
    from the normal one and the degrees of freedom."""
    m, d = fixed_model(), table(spark, sf_dir, "lineitem").where("l_orderkey % 5 = 0").withColumn("y", sliced(oblique(), [1.6, 2.4]))
    hits = []
    for name, parts in RULES.items():
        r = [F.round(x, 9) for x in score_expr(Model(m.config, EDGES, trees=[part_of(m, *p) for p in parts]), COLS)]
        best = F.when((r[0] >= r[1]) & (r[0] >= r[2]), 0).when(r[1] >= r[2], 1).otherwise(2)
        hits.append((best == F.col("y")).cast("double").alias(name))
    got = d.select(*hits).agg(F.count("*").alias("n"), *[f(c).alias(f"{c}_{k}") for c in RULES for k, f in (("m", F.avg), ("s", F.stddev_samp))]).first()
    rows = [{"method": c, "accuracy": got[f"{c}_m"], "accuracy_sd": got[f"{c}_s"], "n_test": got.n} for c in RULES]
    held = best_set(rows)
    return spark.createDataFrame([(r["method"], round(r["accuracy"], 6), r["method"] in held) for r in rows], "method string, accuracy double, in_best boolean")


#: Columns of lineitem that serve as labels: their numbers of classes are counted.
LABELS = ["l_linestatus", "l_returnflag", "l_linenumber", "l_discount"]
COUNTED = "(" + " UNION ALL ".join(f"SELECT '{c}' AS label, count(DISTINCT {c}) AS c, count(*) AS n FROM lineitem" for c in LABELS) + ")"


def counted(spark, sf_dir) -> list[tuple[str, int, int]]:
    """(label, classes, rows) of each label."""
    r = table(spark, sf_dir, "lineitem").agg(F.count("*").alias("n"), *[F.count_distinct(c).alias(c) for c in LABELS]).first()
    return [(c, r[c], r.n) for c in LABELS]


@query(f"SELECT label, t::INT AS trees, c::INT AS classes, ceil(t / c::DOUBLE)::INT AS rounds, (ceil(t / c::DOUBLE) * c)::INT AS built, ceil(t / c::DOUBLE) * c < 2 * t AS counts FROM (VALUES (10), (25), (50), (100)) a(t) CROSS JOIN {COUNTED} b")
def round_budget_grid(spark, sf_dir):
    """Rounds of a tree a class for each label of lineitem."""
    return spark.createDataFrame([(label, t, c, *round_budget(t, c)) for label, c, _ in counted(spark, sf_dir) for t in (10, 25, 50, 100)], "label string, trees int, classes int, rounds int, built int, counts boolean")


@query(f"SELECT 2 AS n_trees, count(*) + 2 AS n_leaves, 3 * (count(*) + 2) AS n_params, 3 * (2 * count(*) + 2) AS n_params_unfolded FROM ({booster_sql(Sql(3), 2, 2, 0.3, layered=True, measured=False)})")
def model_size_fixed(spark, sf_dir):
    """The size of a layered model that is trained on the small workload; its equal rows are counted first."""
    d = fixed_rows(spark, sf_dir)
    base = d.where("not test").groupBy("bins", "y").agg(F.count("*").alias("copies")).persist()
    s = metrics.model_size(fit(base, BoostConfig(outputs=3, n_trees=2, depth=2, schedule="layer"), T3_EDGES))
    base.unpersist()
    d.unpersist()
    return spark.createDataFrame([tuple(s.values())], "n_trees int, n_leaves long, n_params long, n_params_unfolded long")


def after(n: int) -> str:
    """Rows of lineitem with the fixed model's probabilities after its first n trees, as SQL."""
    s = ", ".join("(" + " + ".join(path_sql(t, k) for t in range(n)) + f")::DOUBLE AS s{k}" for k in range(3))
    one = f"(SELECT l_orderkey % 5 = 0 AS test, {Y_SQL} AS y, {s} FROM lineitem)"
    return f"(SELECT *, {', '.join(f'exp(s{k})/(exp(s0)+exp(s1)+exp(s2)) AS p{k}' for k in range(3))}, CASE WHEN s0 >= s1 AND s0 >= s2 THEN 0 WHEN s1 >= s2 THEN 1 ELSE 2 END AS prediction FROM (SELECT test, y, {', '.join(f'round(s{k}, 9) AS s{k}' for k in range(3))} FROM {one}))"


CURVES = "(" + " UNION ALL ".join(f"SELECT test::VARCHAR AS test, {n} AS n_trees, round(avg((prediction = y)::INT::DOUBLE), 6) AS accuracy, round(avg(-ln(CASE y WHEN 0 THEN p0 WHEN 1 THEN p1 ELSE p2 END)), 6) AS cross_entropy FROM {after(n)} GROUP BY test" for n in (1, 2)) + ")"


def curves(spark, sf_dir):
    """The fixed model's measures after each of its trees, on either side of the split."""
    m = fixed_model()
    for t in m.trees:
        t.delta[:] = np.round(t.delta, 9)
    return metrics.curve(binned(table(spark, sf_dir, "lineitem").select(*COLS, (F.col("l_orderkey") % 5 == 0).alias("test"), sliced(oblique(), [1.6, 2.4]).alias("y")), COLS, EDGES, ["test", "y"]), m, "test")


@query(f"SELECT * FROM {CURVES}")
def curve_by_tree(spark, sf_dir):
    return curves(spark, sf_dir).select("test", "n_trees", F.round("accuracy", 6).alias("accuracy"), F.round("cross_entropy", 6).alias("cross_entropy"))


@query(f"SELECT test, min(CASE WHEN cross_entropy <= 1.0 THEN n_trees END) AS n_trees, min(CASE WHEN accuracy >= 0.3 THEN n_trees END) AS by_accuracy FROM {CURVES} GROUP BY test")
def trees_to_target(spark, sf_dir):
    c = curves(spark, sf_dir).persist()
    return metrics.trees_to_target(c, 1.0, "cross_entropy", False, "test").join(metrics.trees_to_target(c, 0.3, by="test").withColumnRenamed("n_trees", "by_accuracy"), "test")


@query(f"SELECT label, c::INT AS classes, h AS hessian, (CASE h WHEN 'diagonal' THEN 2*c+1 ELSE 1+c+c*(c+1)//2 END)::INT AS sums_per_cell, (CASE h WHEN 'diagonal' THEN c ELSE c*c*c END)::INT AS solve_per_candidate, 8*32*20*8*(CASE h WHEN 'diagonal' THEN 2*c+1 ELSE 1+c+c*(c+1)//2 END)::BIGINT AS task_bytes, 40 * n AS row_visits FROM {COUNTED} a CROSS JOIN (VALUES ('diagonal'), ('full')) b(h)")
def cost_model_grid(spark, sf_dir):
    """The cost of ten trees of depth 4 for each label of lineitem."""
    rows = []
    for label, c, n in counted(spark, sf_dir):
        for h in ("diagonal", "full"):
            m = metrics.cost_model(BoostConfig(outputs=c, hessian=h, depth=4, bins=32, n_trees=10), n, 20)
            rows.append((label, c, h, m["sums_per_cell"], m["solve_per_candidate"], m["task_bytes"], m["row_visits"]))
    return spark.createDataFrame(rows, "label string, classes int, hessian string, sums_per_cell int, solve_per_candidate int, task_bytes long, row_visits long")
