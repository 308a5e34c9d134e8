"""What the corpus operators share: the shared folder, lineage cuts, files, components, prefix sums."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: A word is a run of anything but these six blanks; bytes.split() cuts at the same ones.
WORD = r"[^\x20\x09-\x0D]+"


#: Folders made within the innermost `scratch`.
_MADE: list[list[str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share (spark.checkpoint.dir); a temporary one only where none is set on one machine."""
    sc = spark.sparkContext
    base = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if base is None:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="vecboost-")
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(base)
    return base.rstrip("/")


def fresh_dir(spark: SparkSession, what: str) -> str:
    """A new folder's name in the shared one; what is written there is the caller's to remove, or scratch()'s."""
    at = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
    if _MADE:
        _MADE[-1].append(at)
    return at


@contextmanager
def scratch() -> Iterator[None]:
    """Removes the folders that fresh_dir named inside, once the block's own results are written elsewhere."""
    _MADE.append([])
    try:
        yield
    finally:
        for at in _MADE.pop():
            removed(at)


def is_scan(df: DataFrame) -> bool:
    """Whether df reads files and does nothing else but choose columns, so that its slices are the same each time."""
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    return all(x.strip(" +-:").startswith(("Project", "Relation ")) for x in plan.strip().splitlines())


def unused(name: str, columns: list[str]) -> str:
    """name, with as many underscores before it as it takes to clash with no column."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def cut(df: DataFrame) -> DataFrame:
    """df with its lineage cut by a reliable checkpoint in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def written(df: DataFrame, at: str) -> DataFrame:
    """df with its lineage cut by a table written at a folder of the shared one, which the caller may remove once it is done with."""
    df.write.parquet(at)
    return df.sparkSession.read.schema(df.schema).parquet(at)


def removed(at: str) -> None:
    store, path = filesystem(at)
    if store.get_file_info(path).type == pafs.FileType.Directory:
        store.delete_dir(path)


def n_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def spread(df: DataFrame) -> DataFrame:
    """df over as many tasks as there are cores, if it is a plain scan of fewer slices: one small file would keep one
    core busy. Nothing is run to count slices; what has been through an exchange is left as it is."""
    n = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(n) if is_scan(df) and df.rdd.getNumPartitions() < n else df


def filesystem(uri: str) -> tuple[pafs.FileSystem, str]:
    """File system and path of a URI or an absolute path; any store that pyarrow knows."""
    return pafs.FileSystem.from_uri(uri)


@contextmanager
def written_once(uri: str):
    """An output stream whose file appears under its name only when complete, so a retried task is harmless."""
    store, path = filesystem(uri)
    store.create_dir(path.rsplit("/", 1)[0], recursive=True)
    context = TaskContext.get()
    part = f"{path}.{context.taskAttemptId() if context else 0}.tmp"
    with store.open_output_stream(part, compression=None) as out:
        yield out
    store.move(part, path)


def open_input(uri: str):
    store, path = filesystem(uri)
    return store.open_input_file(path)


def unite(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> None:
    """Merges the classes of i[k] and j[k] in place; label holds the least member of each class."""
    while True:
        a, b = label[i], label[j]
        open_ = a != b
        if not open_.any():
            return
        i, j, a, b = i[open_], j[open_], a[open_], b[open_]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while not np.array_equal(up := label[label], label):
            label[:] = up


def components(edges: DataFrame) -> DataFrame:
    """Edges (a, b of long) to (node, root): root is the least node reachable, for all nodes with an edge but roots.

    Alternates large-star and small-star contractions, each a partial aggregate and an equi-join that
    adaptive execution may split, until the edge set no longer changes; every round is a table in the shared folder, and the
    one before it is removed.
    Repeated edges count once. Self-links and null ends are ignored; no edges give no rows.
    """
    spark, k = edges.sparkSession, 0
    folder = fresh_dir(spark, "components")
    e = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    e = written(e, f"{folder}/0")
    mark = None
    while True:
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == mark or not now[0]:
            return e.select(F.col("u").alias("node"), F.col("v").alias("root"))
        mark = now
        both = e.union(e.select("v", "u"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        e = written(small.union(least).distinct(), f"{folder}/{k + 1}")
        removed(f"{folder}/{k}")
        k += 1


def prefix_sums(df: DataFrame, groups: list[str], order: list[str], value: str, out: str, parts: int | None = None) -> DataFrame:
    """Adds out: the exclusive running sum of value within each group in the given order, by range partitions.

    No group meets in one task: rows are range-partitioned by (groups, order), each slice sums itself, and
    only one total per slice and group passes through a window. Ties in order must not matter to the caller. Null groups
    are groups; null values add nothing; an empty table gives no rows.
    """
    spark = df.sparkSession
    parts = parts or n_partitions(spark)
    dealt = cut(df.repartitionByRange(parts, *groups, *order).withColumn("_slice", F.spark_partition_id()))
    totals = dealt.groupBy(*groups, "_slice").agg(F.sum(value).alias("_sum"))
    before = totals.select(*groups, "_slice", F.coalesce(F.sum("_sum").over(W.partitionBy(*groups).orderBy("_slice").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    own = W.partitionBy(*groups, "_slice").orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    within = dealt.withColumn("_own", F.coalesce(F.sum(value).over(own), F.lit(0)))
    on = [F.col(f"l.{g}").eqNullSafe(F.col(f"r.{g}")) for g in [*groups, "_slice"]]
    cond = on[0]
    for c in on[1:]:
        cond = cond & c
    return within.alias("l").join(before.alias("r"), cond).select(*[F.col(f"l.{c}") for c in df.columns], (F.col("_before") + F.col("_own")).alias(out))
