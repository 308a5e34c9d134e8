"""Quantile edges of features and the byte-binned training table."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arrays import to_bytes

MISSING = 0  # the bin of null and NaN
#: Features up to which edges are had by one aggregate of columns; edges of all features up to which bins are column expressions
#: (beyond, a task's generated method grows too large to be compiled).
COLUMNS, EXPRESSED = 16, 160


def edges(df: DataFrame, cols: list[str], bins: int = 32, method: str = "gk", accuracy: int = 10_000, k: int = 200) -> list[list[float]]:
    """Ascending edges of each feature: x belongs to the first bin whose edge is >= x, and to the last beyond all.

    method: gk (percentile_approx), kll (mergeable sketch), exact (percentile), uniform (between least and most).
    One aggregate over the data; sketches of some KB per feature are all that moves. Those of gk meet in one task, which takes the
    longer the more there are, so slices are coalesced to two a core before.
    """
    if bins < 2:
        return [[] for _ in cols]
    probs = [k_ / bins for k_ in range(1, bins)]
    clean = [F.when(F.isnan(F.col(c).cast("double")), None).otherwise(F.col(c).cast("double")) for c in cols]
    if method == "uniform":
        row = df.agg(*[F.struct(F.min(c), F.max(c)) for c in clean]).first()
        found = [[a + (b - a) * p for p in probs] if a is not None else [] for a, b in row]
    elif method == "kll":
        made = df.agg(*[F.kll_sketch_agg_double(c, k).alias(f"k{i}") for i, c in enumerate(clean)])
        row = made.select(*[F.array(*[F.kll_sketch_get_quantile_double(f"k{i}", F.lit(p)) for p in probs]) for i in range(len(cols))]).first()
        found = list(row)
    else:
        if method == "gk":
            df = df.coalesce(2 * df.sparkSession.sparkContext.defaultParallelism)
        one = (lambda c: F.percentile_approx(c, probs, accuracy)) if method == "gk" else (lambda c: F.percentile(c, F.array(*map(F.lit, probs))))
        found = list(df.agg(*[one(c) for c in clean]).first())
    return [sorted({float(e) for e in f if e is not None and np.isfinite(e)}) if f else [] for f in found]


def array_edges(df: DataFrame, col: str, width: int, bins: int = 32, accuracy: int = 10_000) -> list[list[float]]:
    """Edges of every place of an array column: one pass by (place) groups, so that thousands of features stay narrow."""
    probs = [k / bins for k in range(1, bins)]
    got = df.select(F.posexplode(col).alias("f", "x")).where(~F.isnan("x")).groupBy("f").agg(F.percentile_approx("x", probs, accuracy).alias("e")).collect()
    by = {r.f: sorted({float(e) for e in r.e}) for r in got}
    return [by.get(f, []) for f in range(width)]


def bin_expr(col, cuts: list[float]):
    """Bin of a column as a balanced conditional: 0 for null and NaN, else 1 + the edges under x. All in codegen."""

    def tree(lo: int, hi: int):
        if lo == hi:
            return F.lit(lo + 1)
        mid = (lo + hi) // 2
        return F.when(x <= F.lit(cuts[mid]), tree(lo, mid)).otherwise(tree(mid + 1, hi))

    x = (F.col(col) if isinstance(col, str) else col).cast("double")
    return F.when(x.isNull() | F.isnan(x), F.lit(MISSING)).otherwise(tree(0, len(cuts))).cast("int")


def range_join_bins(df: DataFrame, col: str, cuts: list[float], out: str = "bin") -> DataFrame:
    """df with the bin of a column, by a range join with the table of edges (a row an edge, so it is broadcast); null and NaN: MISSING."""
    lo, hi = [float("-inf"), *cuts], [*cuts, float("inf")]
    e = df.sparkSession.createDataFrame([(i + 1, a, b) for i, (a, b) in enumerate(zip(lo, hi))], f"{out} int, _lo double, _hi double")
    x = F.col(col).cast("double")
    inside = ~F.isnan(x) & ((x > F.col("_lo")) & (x <= F.col("_hi")) | (x == float("-inf")) & (F.col(out) == 1))
    return df.join(F.broadcast(e), inside, "left").drop("_lo", "_hi").withColumn(out, F.coalesce(out, F.lit(MISSING)))


def counted(df: DataFrame, col: str, cuts: list[list[float]], keep: list[str]) -> DataFrame:
    """(*keep, bins BINARY: a byte a feature, copies): a row for all rows with equal bins of an array column and equal `keep`.

    With few edges rows are binned by column expressions, eight features a long, and summed up where they are read: they don't go
    through Python.
    """
    m = len(cuts)
    if sum(map(len, cuts)) > EXPRESSED:
        return binned(df, col, cuts, keep).groupBy(*keep, "bins").agg(F.count("*").alias("copies"))
    blocks = [range(f, min(f + 8, m)) for f in range(0, m, 8)]
    longs = [f"_b{k}" for k in range(len(blocks))]
    byte = lambda f, block: F.shiftleft(bin_expr(f"_x{f}", cuts[f]).cast("long"), 8 * (block[-1] - f))
    packed = [reduce(lambda a, b: a.bitwiseOR(b), [byte(f, block) for f in block]).alias(name) for name, block in zip(longs, blocks)]
    found = df.select(*keep, *[F.get(col, F.lit(f)).alias(f"_x{f}") for f in range(m)]).select(*keep, *packed).groupBy(*keep, *longs).agg(F.count("*").alias("copies"))
    whole = F.concat(*[F.unhex(F.lpad(F.hex(name), 2 * len(block), "0")) for name, block in zip(longs, blocks)])
    return found.select(*keep, whole.alias("bins"), "copies")


def is_scan(df: DataFrame) -> bool:
    """Whether df reads files and does nothing else but choose and compute columns."""
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    return all(x.strip(" +-:").startswith(("Project", "Relation ", "Filter")) for x in plan.strip().splitlines())


def spread(df: DataFrame) -> DataFrame:
    """df over as many tasks as there are cores, if it is a plain scan of fewer slices: a small single file would keep one
    core busy. Nothing is run to count slices; what has been through an exchange is left as it is."""
    n = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(n) if is_scan(df) and df.rdd.getNumPartitions() < n else df


def binned(df: DataFrame, features: str | list[str], cuts: list[list[float]], keep: list[str]) -> DataFrame:
    """(bins BINARY: a byte a feature, *keep). features: an array column, or a list of numeric columns."""
    x = F.col(features).cast("array<double>") if isinstance(features, str) else F.array(*[F.col(c).cast("double") for c in features])
    kept = [f for f in df.select(*keep).schema.fields]
    held = [np.asarray(c, np.float64) for c in cuts]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n, m = b.num_rows, len(held)
            flat = b.column("_x").flatten().to_numpy(zero_copy_only=False).reshape(n, m)
            out = np.empty((n, m), np.uint8)
            for f in range(m):
                out[:, f] = np.searchsorted(held[f], flat[:, f], side="left") + 1
            out[np.isnan(flat)] = MISSING
            yield pa.RecordBatch.from_arrays([to_bytes(out), *(b.column(c) for c in keep)], ["bins", *keep])

    from pyspark.sql.types import BinaryType, StructField, StructType

    return spread(df.select(x.alias("_x"), *keep)).mapInArrow(run, StructType([StructField("bins", BinaryType()), *kept]))
