"""The experiments at depth 4 and ten trees or more, and the workloads' class counts with SQL.

What a registered query leaves out of its experiment is in the README; bench/run_grid.py runs them whole.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from ..plans import experiments as E
from ..plans import workloads as WL
from . import query
from .boosters import ONE, Z_SQL, Sql, booster_sql

ONE_EACH = [(ONE[k % 3], ONE[k % 3]) for k in range(12)]
#: The methods on the small workload with fixed edges, ten trees (twelve of the rounds), depth 4, as SQL.
T3_SQL = {
    "ovr_default": (12, booster_sql(Sql(3, scale=2.0), 12, 4, 0.3, direction=ONE_EACH, snapshot=3, min_child=1.0, measured=None)),
    "per_class": (10, booster_sql(Sql(3), 10, 4, 0.3, direction=ONE_EACH, measured=None)),
    "full": (10, booster_sql(Sql(3, hessian="full"), 10, 4, 0.3, measured=None)),
    "diag": (10, booster_sql(Sql(3), 10, 4, 0.3, measured=None)),
    "diag_lbl": (10, booster_sql(Sql(3), 10, 4, 0.3, layered=True, measured=None)),
}


def union(parts: dict) -> str:
    return " UNION ALL ".join(f"SELECT {head}, * FROM ({sql})" for head, sql in parts.items())


@query(union({f"'{m}' AS method, {n} AS n_trees": sql for m, (n, sql) in T3_SQL.items()}).replace("test_loss", "cross_entropy"))
def exp_main_comparison(spark, sf_dir):
    """Every untuned method at ten trees on the small workload."""
    d = E.main_comparison(spark, sf_dir, ("slice3",), list(T3_SQL), (10,))
    return d.select("method", "n_trees", F.round("accuracy", 4).alias("accuracy"), F.round("cross_entropy", 4).alias("cross_entropy"))


@query()
def exp_main_workloads(spark, sf_dir):
    """The untuned methods at the two small sizes on workloads of 3 and 10 classes."""
    return E.main_comparison(spark, sf_dir, ("role3", "emb10"), [m for m in E.METHODS if m != "ovr_tuned"], (10, 25))


@query()
def exp_tuned_baseline(spark, sf_dir):
    """The search at ten trees on the 3-class workload: 20 draws, 5 folds, the grid grown once at its edges."""
    return E.main_comparison(spark, sf_dir, ("role3",), ["ovr_tuned", "diag_lbl"], (10,), expansions=1)


@query()
def exp_convergence(spark, sf_dir):
    return E.convergence(spark, sf_dir, "emb10", n_trees=25)


@query()
def exp_grid_swapped(spark, sf_dir):
    """All twelve cells of depth and rate, with 20 trees each."""
    return E.grid_swapped(spark, sf_dir, n_trees=20)


@query()
def exp_full_vs_diag(spark, sf_dir):
    return E.hessian_costs(spark, sf_dir, ("role3", "emb10")).drop("seconds_per_tree")


@query()
def exp_layer_ablation(spark, sf_dir):
    return E.layer_ablation(spark, sf_dir, n_trees=10)


@query(union({f"'{how}' AS refresh, 12 AS n_trees": booster_sql(Sql(3), 12, 4, 0.3, direction=ONE_EACH, measured=None, **k) for how, k in (("tree", {}), ("round", {"snapshot": 3}), ("layer", {"layered": True}))}).replace("test_loss", "cross_entropy"))
def exp_refresh(spark, sf_dir):
    d = E.refresh(spark, sf_dir, "slice3", 12)
    return d.select("refresh", "n_trees", F.round("accuracy", 4).alias("accuracy"), F.round("cross_entropy", 4).alias("cross_entropy"))


@query()
def exp_class_count(spark, sf_dir):
    return E.class_counts(spark, sf_dir, ("role3", "emb10"), 2)


@query()
def exp_rows_per_layer(spark, sf_dir):
    """Drawn from distributed rows: three trees, whose layers each read another part of the data."""
    return E.quotas(spark, sf_dir, "slice3", n_trees=3)


@query()
def exp_significance(spark, sf_dir):
    return E.significance(spark, sf_dir, "emb10", n_trees=10)


PRESET_SQL = {
    "logitboost_compact": Sql(3), "samme_like": Sql(3, loss="multiexp", hessian="identity", zero_sum=True), "gamble_like": Sql(3, loss="multiexp", hessian="least", lam=0),
    "aoso_like": Sql(3, hessian="pair"), "gd_mc_like": Sql(3, loss="marginexp", hessian="identity"),
}


@query(union({f"'{m}' AS method": f"SELECT accuracy FROM ({booster_sql(f, 5, 2, 0.3, measured=None)})" for m, f in PRESET_SQL.items()}))
def exp_presets(spark, sf_dir):
    """The presets at five trees of depth 2 on the small workload."""
    return E.preset_scores(spark, sf_dir, ("slice3",), 5, depth=2).select("method", F.round("accuracy", 4).alias("accuracy"))


@query(union({f"'{n}' AS dataset": f"SELECT {c} AS classes, true AS near" for n, c in (("null_label", 10), ("null_flag", 3), ("null_priority", 5), ("null_event", 5))}))
def null_control(spark, sf_dir):
    """Labels without signal: test accuracy stays near the share of the largest class."""
    return E.null_controls(spark, sf_dir, ("null_label", "null_flag", "null_priority", "null_event")).select("dataset", "classes", "near")


def counts(make):
    def run(spark, sf_dir):
        return make(spark, sf_dir).groupBy((F.col("key") % 5 == 0).alias("test"), F.col("y").cast("int").alias("y")).agg(F.count("*").alias("n"))

    return run


def workload(name: str, make, key: str, y: str, source: str):
    f = counts(make)
    f.__name__ = f"workload_{name}"
    f.__doc__ = f"Rows by side and class of the workload {name}."
    query(f"SELECT {key} % 5 = 0 AS test, ({y})::INT AS y, count(*) AS n FROM {source} GROUP BY ALL")(f)


def top_of(n):
    return f"list_position(embedding[1:{n}], list_max(embedding[1:{n}])) - 1"


def slices(cuts):
    return " + ".join(f"({Z_SQL} > {c})::INT" for c in cuts)


STAR = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN customer ON o_custkey = c_custkey"
workload("emb10", WL.WORKLOADS["emb10"][0], "vec_id", top_of(10), "embeddings")
workload("letter26", WL.WORKLOADS["letter26"][0], "vec_id", top_of(26), "embeddings")
workload("role3", WL.role3, "conv_id", "CASE role WHEN 'user' THEN 0 WHEN 'assistant' THEN 1 ELSE 2 END", "conversations")
workload("cover7", WL.cover7, "l_orderkey", "CASE WHEN l_quantity <= 25 AND l_extendedprice < 60000 THEN 0 WHEN l_quantity > 25 AND l_discount <= 0.06 THEN 1 WHEN l_shipdate < TIMESTAMP '1996-01-01' THEN 3 WHEN l_tax >= 0.06 AND l_extendedprice >= 60000 THEN 2 WHEN l_extendedprice >= 95000 THEN 4 WHEN l_linenumber <= 3 THEN 5 ELSE 6 END", STAR)
workload("cover7_oblique", WL.cover7_oblique, "l_orderkey", slices([1.0, 1.6, 2.1, 2.4, 2.6, 2.9]), "lineitem")
workload("letter26_large", WL.letter26_large, "l_orderkey", "2*floor((l_quantity-1)/4) + (l_extendedprice >= 52000)::INT", "lineitem JOIN orders ON l_orderkey = o_orderkey")
workload("langwide", WL.langwide, "doc_id", "CASE lang WHEN 'en' THEN 0 WHEN 'fr' THEN 1 WHEN 'de' THEN 2 ELSE 3 END", "documents")
workload("pages4", WL.pages4, "page_id", "CASE regexp_extract(html, '<html lang=\"(\\w+)\"', 1) WHEN 'en' THEN 0 WHEN 'fr' THEN 1 WHEN 'de' THEN 2 ELSE 3 END", "pages")
workload("events5", WL.events5, "event_id", "CASE WHEN value < 15 THEN 0 WHEN value < 35 AND CAST(json_extract_string(props, '$.k') AS DOUBLE) < 50 THEN 1 WHEN value < 35 THEN 2 WHEN hour(ts) < 12 THEN 3 ELSE 4 END", "events")
