"""The relational operators around training: scans, joins, windows, encoders, folds, streams in batch form."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators import features as X
from ..plans.baselines import one_vs_one
from ..plans.workloads import T3_EDGES, cover7, hand10, oblique, sliced, table
from . import query
from .boosters import Y_SQL, Sql, booster_sql, fixed_rows


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 4) AS qty, round(avg(l_extendedprice), 4) AS price FROM lineitem WHERE l_discount BETWEEN 0.02 AND 0.08 GROUP BY ALL")
def scan_lineitem(spark, sf_dir):
    d = table(spark, sf_dir, "lineitem").where(F.col("l_discount").between(0.02, 0.08))
    return d.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 4).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"))


@query("SELECT l_orderkey % 5 = 0 AS test, count(*) AS n, min(l_orderkey) AS least FROM lineitem GROUP BY 1")
def fold_counts(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy((F.col("l_orderkey") % 5 == 0).alias("test")).agg(F.count("*").alias("n"), F.min("l_orderkey").alias("least"))


@query("SELECT count(*) AS n FROM (SELECT l_orderkey FROM lineitem WHERE l_orderkey % 5 = 0 INTERSECT SELECT l_orderkey FROM lineitem WHERE l_orderkey % 5 <> 0)")
def fold_disjoint(spark, sf_dir):
    d = table(spark, sf_dir, "lineitem").select("l_orderkey")
    return d.where("l_orderkey % 5 = 0").intersect(d.where("l_orderkey % 5 <> 0")).agg(F.count("*").alias("n"))


@query("SELECT vec_id, ((vec_id // 5) % 4)::INT AS fold FROM embeddings WHERE vec_id % 5 <> 0")
def kfold_assign(spark, sf_dir):
    return X.kfold(table(spark, sf_dir, "embeddings").where("vec_id % 5 <> 0"), 4, "vec_id").select("vec_id", "fold")


@query("SELECT vec_id, label, ((row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1) % 5)::INT AS fold FROM embeddings")
def stratified_folds(spark, sf_dir):
    return X.stratified_kfold(table(spark, sf_dir, "embeddings"), 5, "vec_id", "label").select("vec_id", "label", "fold")


@query("SELECT (row_number() OVER (ORDER BY role) - 1)::INT AS label_id, role AS label_value, n FROM (SELECT role, count(*) AS n FROM conversations GROUP BY role)")
def class_dictionary(spark, sf_dir):
    return X.class_dictionary(table(spark, sf_dir, "conversations"), "role")


@query("SELECT lang, count(*) AS n, count(quality) AS labelled, sum(coalesce(toxic, 0))::BIGINT AS toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id GROUP BY lang")
def label_coverage(spark, sf_dir):
    d, lab = table(spark, sf_dir, "documents").select("doc_id", "lang"), table(spark, sf_dir, "labels")
    return d.join(lab, "doc_id", "left").groupBy("lang").agg(F.count("*").alias("n"), F.count("quality").alias("labelled"), F.sum(F.coalesce("toxic", F.lit(0))).alias("toxic"))


@query("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def docs_labelled(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", "lang").join(table(spark, sf_dir, "labels"), "doc_id", "left_semi")


@query("SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def docs_unlabelled(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", "lang").join(table(spark, sf_dir, "labels"), "doc_id", "left_anti")


STAR = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"


def star(spark, sf_dir):
    t = lambda n: table(spark, sf_dir, n)
    n = F.broadcast(t("nation").select("n_nationkey", "n_regionkey"))  # 25 rows
    return t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey"))


@query(f"SELECT n_regionkey, o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS price, round(avg(p_retailprice), 4) AS retail FROM {STAR} GROUP BY ALL")
def join_star_features(spark, sf_dir):
    return star(spark, sf_dir).groupBy("n_regionkey", "o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("price"), F.round(F.avg("p_retailprice"), 4).alias("retail"))


FEATURES_SQL = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber::DOUBLE", "date_diff('day', DATE '1992-01-01', l_shipdate::DATE)::DOUBLE", "p_size::DOUBLE", "p_retailprice", "o_totalprice", "c_acctbal"] + [f"({c} = {v!r})::INT::DOUBLE" for c, vs in (("l_returnflag", "ANR"), ("l_linestatus", "FO"), ("o_orderstatus", "FOP"), ("n_regionkey", range(5))) for v in vs]
COVER_SQL = "CASE WHEN l_quantity <= 25 AND l_extendedprice < 60000 THEN 0 WHEN l_quantity > 25 AND l_discount <= 0.06 THEN 1 WHEN l_shipdate < TIMESTAMP '1996-01-01' THEN 3 WHEN l_tax >= 0.06 AND l_extendedprice >= 60000 THEN 2 WHEN l_extendedprice >= 95000 THEN 4 WHEN l_linenumber <= 3 THEN 5 ELSE 6 END"


@query(f"SELECT l_orderkey AS key, {', '.join(f'{e} AS x{k}' for k, e in enumerate(FEATURES_SQL))}, 3.0 AS hashed, {COVER_SQL} AS y FROM {STAR}")
def feature_matrix_cover7(spark, sf_dir):
    """The star join's features; of the 24 hashed indicators, which DuckDB cannot hash alike, three are set."""
    d, n = cover7(spark, sf_dir), len(FEATURES_SQL)
    return d.select("key", *[F.element_at("x", k + 1).alias(f"x{k}") for k in range(n)], F.aggregate(F.slice("x", n + 1, 24), F.lit(0.0), lambda a, b: a + b).alias("hashed"), "y")


@query("SELECT o_orderkey, " + ", ".join(f"(o_orderpriority = '{v}')::DOUBLE AS p{k}" for k, v in enumerate(["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"])) + " FROM orders")
def onehot_flags(spark, sf_dir):
    return X.one_hot(table(spark, sf_dir, "orders"), "o_orderpriority", ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"], "p").select("o_orderkey", *[f"p{k}" for k in range(5)])


@query("SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, (dayofweek(o_orderdate) + 1)::INT AS w, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS d FROM orders")
def date_features(spark, sf_dir):
    d = F.col("o_orderdate")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.dayofweek(d).alias("w"), F.datediff(d, F.lit("1992-01-01")).alias("d"))


@query(r"SELECT doc_id, length(text) AS n, len(regexp_extract_all(text, '[^a-zA-Z]')) AS other, len(regexp_extract_all(lower(text), 'the')) AS the_, len(regexp_extract_all(text, '[äöüß]')) AS german FROM documents")
def text_features_lang(spark, sf_dir):
    t = F.col("text")
    count = lambda e, p: F.regexp_count(e, F.lit(p)).cast("long")
    return table(spark, sf_dir, "documents").select("doc_id", F.length(t).cast("long").alias("n"), count(t, "[^a-zA-Z]").alias("other"), count(F.lower(t), "the").alias("the_"), count(t, "[äöüß]").alias("german"))


@query("SELECT event_type, (CAST(json_extract_string(props, '$.k') AS BIGINT) // 25)::BIGINT AS quarter, count(*) AS n, round(avg(value), 4) AS value FROM events GROUP BY ALL")
def events_json_feature(spark, sf_dir):
    k = F.get_json_object("props", "$.k").cast("long")
    return table(spark, sf_dir, "events").groupBy("event_type", F.floor(k / 25).alias("quarter")).agg(F.count("*").alias("n"), F.round(F.avg("value"), 4).alias("value"))


@query("SELECT conv_id, turn, role, length(text)::INT AS n, coalesce(lag(length(text)) OVER w, -1)::INT AS before, row_number() OVER w AS so_far FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def role_features_lag(spark, sf_dir):
    w = W.partitionBy("conv_id").orderBy("turn")
    n = F.length("text")
    return table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", n.alias("n"), F.coalesce(F.lag(n).over(w), F.lit(-1)).alias("before"), F.row_number().over(w).cast("long").alias("so_far"))


FIVE = "(SELECT l_orderkey, l_partkey % 13 AS r, l_suppkey % 4 AS s, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_extendedprice) AS k FROM lineitem)"


@query(f"SELECT l_orderkey, {', '.join(f'max(CASE WHEN k = {i} THEN r END) AS r{i}' for i in range(1, 6))} FROM {FIVE} WHERE k <= 5 GROUP BY l_orderkey HAVING count(*) = 5")
def hand_pivot(spark, sf_dir):
    w = W.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
    d = table(spark, sf_dir, "lineitem").select("l_orderkey", (F.col("l_partkey") % 13).alias("r"), F.row_number().over(w).alias("k")).where("k <= 5")
    return d.groupBy("l_orderkey").pivot("k", [1, 2, 3, 4, 5]).agg(F.max("r")).where(F.col("5").isNotNull()).select("l_orderkey", *[F.col(str(i)).alias(f"r{i}") for i in range(1, 6)])


@query(f"""WITH f AS (SELECT * FROM {FIVE} WHERE k <= 5), g AS (SELECT l_orderkey, count(DISTINCT r) AS kinds, max(r) - min(r) AS span, count(DISTINCT s) AS suits, count(*) AS n FROM f GROUP BY 1),
m AS (SELECT l_orderkey, max(c) AS most FROM (SELECT l_orderkey, r, count(*) AS c FROM f GROUP BY ALL) GROUP BY 1)
SELECT g.l_orderkey AS key, (CASE WHEN most = 5 THEN 9 WHEN kinds = 5 AND span = 4 AND suits = 1 THEN 8 WHEN most = 4 THEN 7 WHEN most = 3 AND kinds = 2 THEN 6 WHEN suits = 1 THEN 5 WHEN kinds = 5 AND span = 4 THEN 4 WHEN most = 3 THEN 3 WHEN kinds = 3 THEN 2 WHEN kinds = 4 THEN 1 ELSE 0 END)::INT AS y FROM g JOIN m ON g.l_orderkey = m.l_orderkey WHERE n = 5""")
def hand_classes(spark, sf_dir):
    return hand10(spark, sf_dir).select("key", "y")


PAIRS = [(0, 1), (0, 2), (1, 2)]


@query(" UNION ALL ".join(f"SELECT {a} AS a, {b} AS b, * FROM ({booster_sql(Sql(1, loss='multilabel'), 1, 2, 0.3, kind=f'{a}{b}', measured=False)})" for a, b in PAIRS))
def ovo_pairs(spark, sf_dir):
    """The binary trees of one-vs-one, a pair of classes each."""
    base = fixed_rows(spark, sf_dir).where("not test").drop("test")
    models = one_vs_one(base, T3_EDGES, 3, 1, depth=2)
    rows = [(a, b, t, j, int(x.feature[j]), int(x.bin[j]), int(x.n[j]), round(float(x.gain[j]), 4)) for (a, b), m in models.items() for t, x in enumerate(m.trees) for j in x.nodes() if x.feature[j] >= 0]
    return spark.createDataFrame(rows, "a int, b int, tree int, node int, feature int, bin int, n long, gain double")


@query("SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_purchase FROM events")
def asof_last_purchase(spark, sf_dir):
    return X.as_of(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], F.when(F.col("event_type") == "purchase", F.col("event_id")), "last_purchase").select("event_id", "last_purchase")


@query("SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 2 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def interval_click_purchase(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    c, p = e.where("event_type = 'click'").alias("c"), e.where("event_type = 'purchase'").alias("p")
    return c.join(p, (F.col("c.user_id") == F.col("p.user_id")) & (F.col("p.ts") >= F.col("c.ts")) & (F.col("p.ts") <= F.col("c.ts") + F.expr("INTERVAL 2 HOURS"))).select(F.col("c.event_id").alias("click"), F.col("p.event_id").alias("purchase"))


@query("SELECT batch, count(*) AS n, sum(event_id)::BIGINT AS ids FROM (SELECT 0 AS batch, event_id FROM events WHERE event_id % 2 = 0 UNION ALL SELECT 1, event_id FROM events WHERE event_id % 2 = 1 UNION ALL SELECT 1, event_id FROM events WHERE event_id % 10 = 0) GROUP BY batch")
def union_batches(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id")
    a, b, c = (e.where(x).withColumn("batch", F.lit(k)) for x, k in (("event_id % 2 = 0", 0), ("event_id % 2 = 1", 1), ("event_id % 10 = 0", 1)))
    return a.unionByName(b).unionByName(c).groupBy("batch").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


@query("SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '1970-01-01'), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 4) AS value FROM events GROUP BY ALL")
def tumbling_event_stats(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("value")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n", "value")


@query("SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 4) AS value FROM (SELECT value, unnest([time_bucket(INTERVAL 30 MINUTE, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 30 MINUTE, ts, TIMESTAMP '1970-01-01') - INTERVAL 30 MINUTE]) AS s FROM events) GROUP BY s")
def sliding_event_stats(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("value")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", "value")


@query("SELECT user_id, count(*) AS n, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS fresh FROM events)) GROUP BY user_id, s")
def session_users(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select("user_id", "n", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"))


@query(f"SELECT {Y_SQL} AS y, count(*) AS n, round(avg(l_tax), 6) AS mean, round(stddev_samp(l_tax), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r, round(median(l_extendedprice), 4) AS mid, max_by(l_orderkey, l_extendedprice * 1000 + l_quantity + l_linenumber / 100.0) > 0 AS any_ FROM lineitem GROUP BY 1")
def moments_by_class(spark, sf_dir):
    d = table(spark, sf_dir, "lineitem").withColumn("y", sliced(oblique(), [1.6, 2.4]))
    return d.groupBy("y").agg(F.count("*").alias("n"), F.round(F.avg("l_tax"), 6).alias("mean"), F.round(F.stddev_samp("l_tax"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.median("l_extendedprice"), 4).alias("mid"), (F.max_by("l_orderkey", F.col("l_extendedprice") * 1000 + F.col("l_quantity") + F.col("l_linenumber") / 100) > 0).alias("any_"))


@query("SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 6) AS norm FROM embeddings")
def vector_norms(spark, sf_dir):
    x = F.col("embedding").cast("array<double>")
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate(x, F.lit(0.0), lambda a, v: a + v * v)), 6).alias("norm"))


@query("SELECT lang, source, round(count(*)::DOUBLE / sum(count(*)) OVER (PARTITION BY source), 6) AS share FROM documents GROUP BY lang, source")
def class_prob_map(spark, sf_dir):
    """Class shares of a source as a map, and its entries again as rows."""
    n = table(spark, sf_dir, "documents").groupBy("source", "lang").agg(F.count("*").alias("n"))
    m = n.groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("m"), F.sum("n").alias("t"))
    return m.select("source", F.explode(F.transform_values("m", lambda k, v: F.round(v / F.col("t"), 6))).alias("lang", "share"))


@query("SELECT vec_id, round(avg((label % 2 = vec_id % 2)::INT::DOUBLE) OVER (ORDER BY vec_id ROWS BETWEEN 49 PRECEDING AND CURRENT ROW), 6) AS moving_accuracy FROM embeddings")
def moving_accuracy(spark, sf_dir):
    from ..operators.metrics import moving_accuracy as moving

    d = table(spark, sf_dir, "embeddings").select("vec_id", (F.col("label") % 2).alias("y"), (F.col("vec_id") % 2).alias("prediction"))
    return moving(d, "vec_id", rows=50).select("vec_id", F.round("moving_accuracy", 6).alias("moving_accuracy"))


@query("SELECT nullif(c_mktsegment, '') AS segment, count(*) AS n, round(sum(c_acctbal), 2) AS balance FROM customer GROUP BY 1")
def roundtrip_csv(spark, sf_dir):
    """Rows written as CSV and read again with a given schema."""
    return _roundtrip(spark, sf_dir, "csv")


@query("SELECT nullif(c_mktsegment, '') AS segment, count(*) AS n, round(sum(c_acctbal), 2) AS balance FROM customer GROUP BY 1")
def roundtrip_json(spark, sf_dir):
    return _roundtrip(spark, sf_dir, "json")


def _roundtrip(spark, sf_dir, kind):
    from ..sources.io import read, scratch, write

    d = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment", "c_acctbal")
    path = scratch(spark, kind)
    write(d, kind, path)
    back = read(spark, kind, path, d.schema)
    return back.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))
