"""Reading and writing tables, and a dense LibSVM source."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def views(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> None:
    """Temporary views of the tables in the session's catalog, for SQL."""
    for n in names or TABLES:
        load(spark, sf_dir, n).createOrReplaceTempView(n)


def read(spark: SparkSession, kind: str, path: str, schema: StructType | None = None, **options) -> DataFrame:
    """kind: parquet, orc, csv, json or text. CSV and JSON want a schema: nothing is inferred."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    r = spark.read.format(kind).options(**options)
    return (r.schema(schema) if schema is not None else r).load(path)


def write(df: DataFrame, kind: str, path: str, mode: str = "overwrite", by: list[str] | None = None, **options) -> None:
    w = df.write.format(kind).mode(mode).options(**options)
    (w.partitionBy(*by) if by else w).save(path)


def scratch(spark: SparkSession, what: str) -> str:
    """A fresh path in the folder that executors share; a temporary one where none is set on one machine, as in tests."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if base is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="vecboost-")
    return f"{base.rstrip('/')}/{what}-{uuid.uuid4().hex}"


class Span(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


class LibsvmReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.width = options["path"], int(options["features"])
        self.span = int(options.get("span", 64 << 20))

    def partitions(self):
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(self.path)
        info = store.get_file_info(path)
        files = [info] if info.type == fs.FileType.File else [f for f in store.get_file_info(fs.FileSelector(path)) if f.type == fs.FileType.File and f.base_name[0] not in "._"]
        return [Span(f.path, a, min(a + self.span, f.size)) for f in files for a in range(0, f.size, self.span)]

    def read(self, part: Span):
        from pyarrow import fs

        store, _ = fs.FileSystem.from_uri(self.path)
        with store.open_input_file(part.path) as f:
            f.seek(max(0, part.start - 1))
            held, at = b"", max(0, part.start - 1)
            first = part.start == 0
            # a span owns the lines that begin in it
            while True:
                end = held.find(b"\n")
                if end < 0:
                    more = f.read(1 << 20)
                    if not more:
                        if held and first and at < part.end:
                            yield self.row(held)
                        return
                    held += more
                    continue
                line, held = held[:end], held[end + 1 :]
                if first and at < part.end and line.strip():
                    yield self.row(line)
                at += end + 1
                first = True
                if at >= part.end:
                    return

    def row(self, line: bytes):
        label, *pairs = line.split()
        x = [0.0] * self.width
        for p in pairs:
            k, v = p.split(b":")
            x[int(k) - 1] = float(v)
        return float(label), x


class LibsvmDense(DataSource):
    """format('libsvm_dense') with options path and features: (label double, x array<double>)."""

    @classmethod
    def name(cls):
        return "libsvm_dense"

    def schema(self):
        return "label double, x array<double>"

    def reader(self, schema):
        return LibsvmReader(dict(self.options))
