"""The experiment workloads on the given tables: features, planted labels, folds."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.arrays import to_lists

#: Bin edges of the small SQL-checked workload (x <= edge goes left).
T3_FEATURES = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
T3_EDGES = [
    [6.0, 12.0, 18.0, 25.0, 31.0, 37.0, 44.0],
    [14000.0, 27000.0, 40000.0, 53000.0, 66000.0, 79000.0, 92000.0],
    [0.005, 0.015, 0.025, 0.045, 0.055, 0.075, 0.085],
    [0.005, 0.015, 0.025, 0.035, 0.045, 0.055, 0.065],
]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def oblique():
    tax = F.when(F.month("l_shipdate") <= 6, 12.5 * F.col("l_tax")).otherwise(1 - 12.5 * F.col("l_tax"))
    return F.col("l_quantity") / 50 + F.col("l_extendedprice") / 105000 + 5 * F.col("l_discount") + tax


def sliced(z, cuts: list[float]):
    """Number of cuts under z: a value equal to a cut belongs to the lower slice."""
    return sum(((z > c).cast("int") for c in cuts), F.lit(0))


def slice3(spark, sf_dir) -> DataFrame:
    """T3: four features, three oblique slices."""
    d = table(spark, sf_dir, "lineitem")
    return d.select((F.col("l_orderkey") % 5 == 0).alias("test"), *T3_FEATURES, sliced(oblique(), [1.6, 2.4]).alias("y"))


def emb(spark, sf_dir, classes: int = 10, width: int = 64) -> DataFrame:
    """Dense vectors; the class is the place of the largest of the first coordinates."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), F.slice(F.col("embedding").cast("array<double>"), 1, width).alias("x"))
    first = F.slice("x", 1, classes)
    return e.select("key", "x", (F.array_position(first, F.array_max(first)) - 1).cast("int").alias("y"))


def role3(spark, sf_dir) -> DataFrame:
    """Who speaks, from the turn, its text's size and what came before."""
    c = table(spark, sf_dir, "conversations")
    w = W.partitionBy("conv_id").orderBy("turn")
    n = F.length("text")
    x = F.array(F.col("turn"), F.col("turn") % 2, n, F.size(F.split("text", " ")), F.coalesce(F.lag(n).over(w), F.lit(-1)), F.row_number().over(w)).cast("array<double>")
    return c.select(F.col("conv_id").alias("key"), x.alias("x"), F.when(F.col("role") == "user", 0).when(F.col("role") == "assistant", 1).otherwise(2).alias("y"))


def cover7(spark, sf_dir) -> DataFrame:
    """The star join with indicators; seven axis-aligned regions."""
    li, o, p, c, n = (table(spark, sf_dir, t) for t in ("lineitem", "orders", "part", "customer", "nation"))
    n = n.select("n_nationkey", "n_regionkey")  # 25 rows
    j = li.join(o, li.l_orderkey == o.o_orderkey).join(p, li.l_partkey == p.p_partkey).join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), c.c_nationkey == n.n_nationkey)
    days = F.datediff("l_shipdate", F.lit("1992-01-01"))
    flags = [("l_returnflag", ["A", "N", "R"]), ("l_linestatus", ["F", "O"]), ("o_orderstatus", ["F", "O", "P"]), ("n_regionkey", range(5))]
    one = [(F.col(col) == v).cast("double") for col, vs in flags for v in vs]
    hashed = [(F.pmod(F.crc32(F.col(col).cast("binary")), F.lit(8)) == k).cast("double") for col in ("o_orderpriority", "c_mktsegment", "p_type") for k in range(8)]
    y = F.when((F.col("l_quantity") <= 25) & (F.col("l_extendedprice") < 60000), 0).when((F.col("l_quantity") > 25) & (F.col("l_discount") <= 0.06), 1).when(F.col("l_shipdate") < "1996-01-01", 3).when((F.col("l_tax") >= 0.06) & (F.col("l_extendedprice") >= 60000), 2).when(F.col("l_extendedprice") >= 95000, 4).when(F.col("l_linenumber") <= 3, 5).otherwise(6)
    x = F.array(*[F.col(k).cast("double") for k in ("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber")], days.cast("double"), F.col("p_size").cast("double"), F.col("p_retailprice").cast("double"), F.col("o_totalprice").cast("double"), F.col("c_acctbal").cast("double"), *one, *hashed)
    return j.select(F.col("l_orderkey").alias("key"), x.alias("x"), y.alias("y"))


def cover7_oblique(spark, sf_dir) -> DataFrame:
    d = table(spark, sf_dir, "lineitem")
    x = F.array("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber", F.month("l_shipdate"), F.dayofweek("l_shipdate")).cast("array<double>")
    return d.select(F.col("l_orderkey").alias("key"), x.alias("x"), sliced(oblique(), [1.0, 1.6, 2.1, 2.4, 2.6, 2.9]).alias("y"))


def letter26_large(spark, sf_dir) -> DataFrame:
    """26 cells of a quantity and price grid, over numeric columns of lines and orders."""
    li, o = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    j = li.join(o, li.l_orderkey == o.o_orderkey)
    ship, day = F.col("l_shipdate"), F.col("o_orderdate")
    x = F.array("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber", "o_totalprice", F.month(ship), F.dayofweek(ship), F.year(ship), F.dayofmonth(ship), F.month(day), F.dayofweek(day), F.year(day), F.dayofmonth(day), F.datediff(ship, day), F.col("l_partkey") % 16).cast("array<double>")
    y = (2 * F.floor((F.col("l_quantity") - 1) / 4) + (F.col("l_extendedprice") >= 52000).cast("int")).cast("int")
    return j.select(F.col("l_orderkey").alias("key"), x.alias("x"), y.alias("y"))


def hand10(spark, sf_dir) -> DataFrame:
    """An order's first five lines as a hand of cards: ranks by part, suits by supplier."""
    d = table(spark, sf_dir, "lineitem")
    w = W.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
    card = F.struct(F.row_number().over(w).alias("k"), (F.col("l_partkey") % 13).alias("r"), (F.col("l_suppkey") % 4).alias("s"))
    five = d.select("l_orderkey", card.alias("c")).where("c.k <= 5").groupBy("l_orderkey").agg(F.sort_array(F.collect_list("c")).alias("h")).where(F.size("h") == 5)
    five = five.select("l_orderkey", F.col("h.r").alias("r"), F.col("h.s").alias("s"))
    same = F.array_sort(F.transform(F.array_distinct("r"), lambda x: F.size(F.filter("r", lambda v: v == x))))
    kinds, most = F.size(F.array_distinct("r")), F.element_at(same, -1)
    run = (kinds == 5) & (F.array_max("r") - F.array_min("r") == 4)
    flush = F.size(F.array_distinct("s")) == 1
    y = F.when(most == 5, 9).when(run & flush, 8).when(most == 4, 7).when((most == 3) & (kinds == 2), 6).when(flush, 5).when(run, 4).when(most == 3, 3).when(kinds == 3, 2).when(kinds == 4, 1).otherwise(0)
    return five.select(F.col("l_orderkey").alias("key"), F.concat("r", "s").cast("array<double>").alias("x"), y.alias("y"))


def langwide(spark, sf_dir, width: int = 1024, label: str = "lang") -> DataFrame:
    """Hashed character 3-grams of whole texts; label: lang (4 classes) or source (20, no signal)."""
    d = table(spark, sf_dir, "documents")
    y = F.when(F.col("lang") == "en", 0).when(F.col("lang") == "fr", 1).when(F.col("lang") == "de", 2).otherwise(3) if label == "lang" else F.regexp_extract("source", r"(\d+)$", 1).cast("int")
    return wide_counts(d.select(F.col("doc_id").alias("key"), F.col("text"), y.alias("y")), width)


def wide_counts(d: DataFrame, width: int) -> DataFrame:
    """Hashed 3-gram counts of a text column, in place of it."""

    def run(batches):
        for b in batches:
            rows = []
            for t in b.column("text").to_pylist():
                c = np.frombuffer((t or "").lower().encode(), np.uint8).astype(np.int64)
                g = (c[:-2] * 65599 * 65599 + c[1:-1] * 65599 + c[2:]) % 1000003 % width if len(c) > 2 else np.zeros(0, np.int64)
                rows.append(np.bincount(g, minlength=width).astype(float))
            yield pa.RecordBatch.from_arrays([b.column("key"), to_lists(np.stack(rows) if rows else np.zeros((0, width))), b.column("y")], ["key", "x", "y"])

    return d.mapInArrow(run, f"key long, x array<double>, y {dict(d.dtypes)['y']}")


def pages4(spark, sf_dir, width: int = 1024) -> DataFrame:
    """The language of a page from its text without tags."""
    p = table(spark, sf_dir, "pages")
    lang = F.regexp_extract("html", r'<html lang="(\w+)"', 1)
    y = F.when(lang == "en", 0).when(lang == "fr", 1).when(lang == "de", 2).otherwise(3)
    return wide_counts(p.select(F.col("page_id").alias("key"), F.regexp_replace("html", r"<[^>]*>", " ").alias("text"), y.alias("y")), width)


def events5(spark, sf_dir) -> DataFrame:
    """Five regions of value, a JSON number and the hour."""
    e = table(spark, sf_dir, "events")
    k, v = F.get_json_object("props", "$.k").cast("double"), F.col("value")
    y = F.when(v < 15, 0).when((v < 35) & (k < 50), 1).when(v < 35, 2).when(F.hour("ts") < 12, 3).otherwise(4)
    x = F.array(v, k, F.hour("ts"), F.dayofweek("ts"), F.col("user_id") % 10, F.minute("ts")).cast("array<double>")
    return e.select(F.col("event_id").alias("key"), "ts", x.alias("x"), y.alias("y"))


def labelled_documents(spark, sf_dir, label: str, width: int = 256) -> DataFrame:
    """Documents that have labels, by hashed 3-grams and the share of signs that aren't letters. label: quality, or both for (quality, toxic)."""
    d = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id")
    y = F.col("quality").cast("int") if label == "quality" else F.array(F.col("quality").cast("double"), F.col("toxic").cast("double"))
    share = F.regexp_count("text", F.lit(r"[^\p{L}]")) / F.greatest(F.length("text"), F.lit(1))
    rows = wide_counts(d.select(F.col("doc_id").alias("key"), "text", F.struct(y.alias("y"), share.alias("share")).alias("y")), width)
    return rows.select("key", F.concat("x", F.array("y.share")).alias("x"), F.col("y.y").alias("y"))


def vecreg2(spark, sf_dir, unit: float = 1000) -> DataFrame:
    """Two real outputs of a line: its net price, and that with tax, in thousands or another unit."""
    d = table(spark, sf_dir, "lineitem")
    net = F.col("l_extendedprice") * (1 - F.col("l_discount")) / unit
    x = F.array("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber", F.month("l_shipdate")).cast("array<double>")
    return d.select(F.col("l_orderkey").alias("key"), x.alias("x"), F.array(net, net * (1 + F.col("l_tax"))).alias("y"))


def rank_docs(spark, sf_dir) -> DataFrame:
    """Lines of an order as a list to be ranked by a grade of quantity and price; groups are orders."""
    d = table(spark, sf_dir, "lineitem")
    x = F.array("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber").cast("array<double>")
    grade = (F.col("l_quantity") > 20).cast("int") + (F.col("l_extendedprice") > 50000).cast("int") + (F.col("l_discount") > 0.05).cast("int")
    return d.select(F.col("l_orderkey").alias("key"), F.col("l_orderkey").alias("group"), x.alias("x"), grade.alias("y"))


def null_label(spark, sf_dir, kind: str) -> DataFrame:
    """Features that say nothing about the label."""
    if kind == "null_label":
        return emb(spark, sf_dir).drop("y").join(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), F.col("label").cast("int").alias("y")), "key")
    if kind == "null_event":
        names = ["click", "login", "purchase", "signup", "view"]
        e = events5(spark, sf_dir).drop("y", "ts")
        own = table(spark, sf_dir, "events").select(F.col("event_id").alias("key"), F.coalesce(*[F.when(F.col("event_type") == n, k) for k, n in enumerate(names)], F.lit(0)).alias("y"))
        return e.join(own, "key")
    li = table(spark, sf_dir, "lineitem")
    x = F.array("l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber").cast("array<double>")
    if kind == "null_flag":
        y = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2)
        return li.select(F.col("l_orderkey").alias("key"), x.alias("x"), y.alias("y"))
    o = table(spark, sf_dir, "orders").select("o_orderkey", (F.substring("o_orderpriority", 1, 1).cast("int") - 1).alias("y"))
    return li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("l_orderkey").alias("key"), x.alias("x"), "y")


def t3(spark, sf_dir) -> DataFrame:
    """The small workload by its fixed edges, as the others are given."""
    d = slice3(spark, sf_dir)
    return d.select(F.when(F.col("test"), 0).otherwise(1).alias("key"), F.array(*[F.col(c).cast("double") for c in T3_FEATURES]).alias("x"), "y")


#: Edges that aren't learned from the training rows.
FIXED_EDGES = {"slice3": T3_EDGES}
WORKLOADS = {
    "slice3": (t3, 3, 4), "multilabel2": (lambda s, d: labelled_documents(s, d, "both"), 2, 257), "bin_quality": (lambda s, d: labelled_documents(s, d, "quality"), 2, 257),
    "vecreg2": (vecreg2, 2, 6), **{n: (lambda s, d, n=n: null_label(s, d, n), c, w) for n, c, w in (("null_label", 10, 64), ("null_flag", 3, 5), ("null_priority", 5, 5), ("null_event", 5, 6))},
    "emb10": (lambda s, d: emb(s, d), 10, 64), "role3": (role3, 3, 6), "cover7": (cover7, 7, 47), "cover7_oblique": (cover7_oblique, 7, 7),
    "letter26": (lambda s, d: emb(s, d, 26, 26), 26, 26), "letter26_large": (letter26_large, 26, 16), "hand10": (hand10, 10, 10),
    "langwide": (langwide, 4, 1024), "source20": (lambda s, d: langwide(s, d, label="source"), 20, 1024), "pages4": (pages4, 4, 1024), "events5": (events5, 5, 6),
}


def is_test(key: str = "key"):
    return F.col(key) % 5 == 0


def made(spark, sf_dir, name: str, bins: int = 32):
    """(rows, edges, classes) of a workload: key, x, y, and the edges of the training rows."""
    from ..operators.binning import COLUMNS, array_edges, edges

    make, classes, width = WORKLOADS[name]
    y = F.col("y").cast("array<double>" if name in ("multilabel2", "vecreg2") else "int").alias("y")
    rows = make(spark, sf_dir).select("key", "x", y)
    learned = rows.where(~is_test())
    if name in FIXED_EDGES:
        cuts = FIXED_EDGES[name]
    elif width <= COLUMNS:
        cuts = edges(learned.select(*[F.get("x", F.lit(f)).alias(f"x{f}") for f in range(width)]), [f"x{f}" for f in range(width)], bins)
    else:
        cuts = array_edges(learned, "x", width, bins)
    return rows, cuts, classes


def prepared(spark, sf_dir, name: str, bins: int = 32):
    """(train, test, edges, classes) of a workload, binned by the training rows' edges."""
    from ..operators.binning import binned

    rows, cuts, classes = made(spark, sf_dir, name, bins)
    train, test = (binned(rows.where(side), "x", cuts, ["key", "y"]) for side in (~is_test(), is_test()))
    return train, test, cuts, classes


def grouped(spark, sf_dir, name: str, bins: int = 32):
    """(rows, edges, classes): both sides' rows (test, y, bins, copies) with equal bins and label as one, in one pass over the input."""
    from ..operators.binning import counted

    rows, cuts, classes = made(spark, sf_dir, name, bins)
    return counted(rows.select(is_test().alias("test"), "x", "y").where("test is not null"), "x", cuts, ["test", "y"]), cuts, classes
