"""Encoders, folds and as-of features."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import ArrayType, BooleanType, DateType, DoubleType, LongType, StringType, StructField, StructType, TimestampType


def class_dictionary(df: DataFrame, label: str) -> DataFrame:
    """(label_id, label_value, n): ids by the order of values, over the whole data; a row a class."""
    n = df.groupBy(F.col(label).alias("label_value")).agg(F.count("*").alias("n"))
    return n.select((F.row_number().over(W.orderBy("label_value")) - 1).alias("label_id"), "label_value", "n")


def string_index(df: DataFrame, label: str, out: str = "y") -> tuple[DataFrame, list]:
    """df with the label's id, and the values by id. The dictionary has a row a class, so it may be a literal map."""
    values = [r.label_value for r in class_dictionary(df.where(F.col(label).isNotNull()), label).orderBy("label_id").collect()]
    pairs = [x for k, v in enumerate(values) for x in (F.lit(v), F.lit(k))]
    return df.withColumn(out, F.element_at(F.create_map(*pairs), F.col(label))), values


def one_hot(df: DataFrame, col: str, values: list, prefix: str) -> DataFrame:
    return df.withColumns({f"{prefix}{k}": (F.col(col) == v).cast("double") for k, v in enumerate(values)})


def encode_label(y: Column, c: int, kind: str = "onehot") -> Column:
    """The code vector of a label as an array column."""
    from ..functions.losses import codewords

    m = codewords(c, kind)
    return F.element_at(F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in m]), y + 1)


def kfold(df: DataFrame, k: int, key: str, out: str = "fold") -> DataFrame:
    """Folds by key arithmetic, apart from the test rule (key modulo 5): no shuffle."""
    return df.withColumn(out, (F.floor(F.col(key) / 5) % k).cast("int"))


def stratified_kfold(df: DataFrame, k: int, key: str, label: str, out: str = "fold") -> DataFrame:
    """Each class dealt over the folds in turn, so that a rare class is in as many as it can be."""
    w = W.partitionBy(label).orderBy(key)
    return df.withColumn(out, ((F.row_number().over(w) - 1) % k).cast("int"))


def as_of(df: DataFrame, by: str, order: list[str], value: Column, out: str) -> DataFrame:
    """The last earlier non-null value for each row of the same key."""
    w = W.partitionBy(by).orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    return df.withColumn(out, F.last(value, ignorenulls=True).over(w))


def hash_ngrams(text: Column, width: int, n: int = 3) -> Column:
    """Buckets of the character n-grams of a text, as an array of ints, in the JVM."""
    t = F.lower(text)
    return F.transform(F.sequence(F.lit(1), F.greatest(F.length(t) - (n - 1), F.lit(1))), lambda i: F.pmod(F.xxhash64(F.substring(t, i, F.lit(n))), F.lit(width)).cast("int"))


def impute_bin(col: Column, value: float) -> tuple[Column, Column]:
    """The column with nulls and NaN replaced, and an indicator of where."""
    missing = col.isNull() | F.isnan(col)
    return F.when(missing, F.lit(value)).otherwise(col), missing.cast("double")


def weighted_mean(df: DataFrame, by: str, value: str, weight: str) -> DataFrame:
    """(by, mean, n) by a user-defined aggregate in Python that combines: Arrow batches are folded to sums in the tasks that
    read them, and only a row a group and task is exchanged. Nulls in value or weight, and null groups, as in SQL."""
    kind = df.schema[by].dataType

    def fold(batches):
        held: dict = {}
        for b in batches:
            d = b.to_pandas()
            for k, part in d.groupby("k", dropna=False):
                k = None if k != k else k
                a = held.setdefault(k, [0.0, 0.0, 0])
                known = part["v"].notna() & part["w"].notna()
                a[0] += float((part["v"] * part["w"])[known].sum())
                a[1] += float(part["w"][known].sum())
                a[2] += len(part)
        if held:
            yield pa.RecordBatch.from_pydict({"k": pa.array(list(held), to_arrow_type(kind)), "s": [a[0] for a in held.values()], "w": [a[1] for a in held.values()], "n": pa.array([a[2] for a in held.values()], pa.int64())})

    rows = df.select(F.col(by).alias("k"), F.col(value).cast("double").alias("v"), F.col(weight).cast("double").alias("w"))
    parts = rows.mapInArrow(fold, StructType([StructField("k", kind), *(StructField(n, t) for n, t in (("s", DoubleType()), ("w", DoubleType()), ("n", LongType())))]))
    return parts.groupBy(F.col("k").alias(by)).agg((F.sum("s") / F.nullif(F.sum("w"), F.lit(0.0))).alias("mean"), F.sum("n").alias("n"))


def draw(key: Column, seed: str = "") -> Column:
    """0 to 999 by the key's MD5: the same in any engine."""
    return F.conv(F.substring(F.md5(F.concat(key.cast("string"), F.lit(seed)).cast("binary")), 1, 8), 16, 10).cast("long") % 1000


def sample_by(df: DataFrame, key: str, by: str, shares: dict, seed: str = "") -> DataFrame:
    """About a share of each class's rows (none of classes not named), by a hash of the key."""
    most = F.lit(0)
    for v, share in shares.items():
        most = F.when(F.col(by) == v, F.lit(round(share * 1000))).otherwise(most)
    return df.where(draw(F.col(key), seed) < most)


def bootstrap(df: DataFrame, key: str, out: str = "times", seed: str = "") -> DataFrame:
    """df with how often a bootstrap takes each row: a Poisson count of mean one, to a thousandth and four at most."""
    d, times = draw(F.col(key), seed), F.lit(4)
    for n, below in ((3, 981), (2, 920), (1, 736), (0, 368)):
        times = F.when(d < below, F.lit(n)).otherwise(times)
    return df.withColumn(out, times)


def assemble(df: DataFrame, cols: list[str], out: str = "x") -> DataFrame:
    """One array<double> of numeric, boolean, date, timestamp, array and (flattened) struct columns, in order."""
    parts: list[Column] = []

    def add(name: str, kind) -> None:
        c = F.col(name)
        if isinstance(kind, StructType):
            for f in kind.fields:
                add(f"{name}.{f.name}", f.dataType)
        elif isinstance(kind, ArrayType):
            parts.append(c.cast("array<double>"))
        elif isinstance(kind, TimestampType):
            parts.append(F.array(F.unix_micros(c).cast("double")))
        elif isinstance(kind, DateType):
            parts.append(F.array(F.unix_date(c).cast("double")))
        elif isinstance(kind, StringType):
            raise ValueError(f"{name}: strings must be indexed or hashed first")
        else:
            parts.append(F.array((c.cast("int") if isinstance(kind, BooleanType) else c).cast("double")))

    for name in cols:
        add(name, df.schema[name].dataType)
    return df.withColumn(out, F.concat(*parts))
