"""Many models side by side: each is trained whole in a task of its own, on a table of a checked size.

Searches and comparisons train hundreds of ensembles on the same rows. Where the binned rows take no more than LOCAL bytes,
they are broadcast, or if they are counted sent from task to task, and the candidates are what is dealt to the tasks; beyond
that every model is trained by the distributed engine in turn. Both use the same arithmetic, so the results are the same but for the order in which rows are added.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arrays import byte_matrix
from .kernel import LocalRows

#: Bytes of binned rows that a table may have to be broadcast: rows x (features + the label and the key).
LOCAL = 64 << 20


def local_rows(base: DataFrame, width: int, most: int = LOCAL) -> tuple[LocalRows, np.ndarray] | None:
    """The rows and their keys in key order, or None where they take more than `most` bytes. Rows with copies come in the order of
    their bins; what stands for their keys is their copies."""
    if base.count() * (width + 16) > most:
        return None
    return in_order(base.select("copies" if "copies" in base.columns else "key", "bins", "y").toArrow(), width)


def in_order(t: pa.Table, width: int) -> tuple[LocalRows, np.ndarray]:
    """Of a table (copies or key, bins, y) what local_rows gives."""
    t, counted = t.combine_chunks(), t.column_names[0] == "copies"
    key = t.column(0).to_numpy()
    x = byte_matrix(t.column("bins").chunk(0)) if t.num_rows else np.zeros((0, width), np.uint8)
    y = t.column("y")
    y = np.array(y.to_pylist(), float) if str(y.type).startswith("list") else y.to_numpy()
    by = (*y.reshape(len(key), -1).T, *x.T) if counted else (*x.T[:8], key)
    order = np.lexsort(by) if len(key) else np.zeros(0, int)
    return LocalRows(np.ascontiguousarray(x[order]), y[order], copies=key[order] if counted else None), key[order]


def run_all(spark, jobs: list, work: Callable[[object], object]) -> list:
    """work(job) for each job, one a task, in the jobs' order; what it takes and gives is pickled, and must be small."""
    if not jobs:
        return []

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"k": b["k"], "out": [pickle.dumps(work(pickle.loads(j))) for j in b["job"]]})

    told = spark.createDataFrame([(k, pickle.dumps(j)) for k, j in enumerate(jobs)], "k int, job binary")
    got = told.repartitionByRange(len(jobs), "k").mapInPandas(run, "k int, out binary").orderBy("k").collect()  # a row a job
    return [pickle.loads(bytes(r.out)) for r in got]


def run_where(rows: DataFrame, width: int, jobs: list, work: Callable[[LocalRows, LocalRows, object], object]) -> list:
    """work(train, test, job) for each job, one a task, in the jobs' order. Every job's task gets all rows (test, y, bins, copies) from
    those that hold them: none pass through the driver, so its memory doesn't grow with them."""
    if not jobs:
        return []
    names = ["copies", "bins", "y"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        told = pa.Table.from_batches(batches)
        k = told.column("k")[0].as_py()
        sides = [in_order(told.filter(c).select(names), width)[0] for test in (False, True) for c in (pc.equal(told.column("test"), test),)]
        del told
        yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([pickle.dumps(work(*sides, jobs[k]))], pa.binary())], ["k", "out"])

    each = rows.select("test", *names, F.explode(F.array(*[F.lit(k) for k in range(len(jobs))])).alias("k"))
    got = each.repartitionById(len(jobs), F.col("k")).mapInArrow(run, "k int, out binary").collect()  # a row a job
    return [pickle.loads(bytes(r.out)) for r in sorted(got, key=lambda r: r.k)]


def fold_of(key: np.ndarray, folds: int) -> np.ndarray:
    """Folds by key, all rows of a key in one."""
    return key // 5 % folds


def with_fold(base: DataFrame, folds: int) -> DataFrame:
    return base.withColumn("fold", (F.floor(F.col("key") / 5) % folds).cast("int"))
