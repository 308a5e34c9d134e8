"""URL rules by a sort-merge range join on reversed-host keys.

A rule (host, path, action) covers its host and every subdomain, for urls whose path starts with the rule's.
With the labels of a host reversed and each ended by a full stop ("org.example."), that cover is the key
interval [key, key + U+10FFFF), and intervals nest or are disjoint. Pages and intervals are cut at the same
sampled page keys, every slice is sorted, and one sweep keeps the stack of open intervals; within a host of
the stack, paths are prefix intervals again, found by bisection and links to the enclosing prefix.
The longest rule (characters of host and path together, then of host, then in text order) wins.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import n_partitions

#: The rules of the production query, as (host, path, action).
RULES = [
    ("org", "/", "allow"),
    ("example.org", "/es/", "block"),
    ("example.org", "/en/1", "block"),
    ("com", "/fr/", "allow"),
    ("com", "/de/", "block"),
]
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def with_host_path(df: DataFrame, url: str = "url") -> DataFrame:
    """Adds host and path; both empty for a null url or one without '://'."""
    has = F.coalesce(F.col(url).contains("://"), F.lit(False))
    rest = F.substring_index(F.regexp_replace(F.col(url), r"(?s)^.*?://", ""), "#", 1)
    rest = F.substring_index(rest, "?", 1)
    host = F.substring_index(rest, "/", 1)
    path = F.when(F.instr(rest, "/") > 0, F.substring(rest, F.instr(rest, "/"), F.length(rest))).otherwise("")
    return df.withColumn("host", F.when(has, F.translate(host, UPPER, LOWER)).otherwise("")).withColumn("path", F.when(has, path).otherwise(""))


def host_key(host):
    """'a.example.org' to 'org.example.a.' (a column)."""
    return F.when(host == "", F.lit("")).otherwise(F.concat(F.concat_ws(".", F.reverse(F.split(host, r"\."))), F.lit(".")))


class PathRules:
    """The path prefixes of one rule host, with the longest that starts a path found by bisection."""

    def __init__(self, rules: list[tuple[str, str, str]]):
        rules = sorted(dict((r[0], r) for r in sorted(rules, reverse=True)).values())
        self.paths, self.rules, self.parent, open_ = [r[0] for r in rules], rules, [], []
        for k, (p, *_) in enumerate(rules):
            while open_ and not p.startswith(self.paths[open_[-1]]):
                open_.pop()
            self.parent.append(open_[-1] if open_ else -1)
            open_.append(k)

    def longest(self, path: str):
        k = bisect_right(self.paths, path) - 1
        while k >= 0 and not path.startswith(self.paths[k]):
            k = self.parent[k]
        return self.rules[k] if k >= 0 else None


def sweep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (slice, key, is_page, path): rules open before the pages they cover."""
    slice_, stack, last, found = None, [], (None, None), None
    for batch in batches:
        c = {n: batch.column(n).to_pylist() for n in ("_slice", "_key", "_page", "path", "_rules")}
        keep, rule, verdict = [], [], []
        for row, (s, key, page, path, rules) in enumerate(zip(*c.values())):
            if s != slice_:
                slice_, stack, last = s, [], (None, None)
            while stack and not key.startswith(stack[-1][0]):
                stack.pop()
            if not page:
                stack.append((key, PathRules([(r["path"], r["host"], r["action"]) for r in rules])))
                last = (None, None)
                continue
            if last != (key, path):
                hits = [h for _, own in stack if (h := own.longest(path))]
                found, last = max(hits, key=lambda h: (len(h[1]) + len(h[0]), len(h[1]), h[1] + h[0]), default=None), (key, path)
            keep.append(row)
            rule.append(found and found[1] + found[0])
            verdict.append(found and found[2])
        out = batch.take(pa.array(keep, pa.int64()))
        yield pa.RecordBatch.from_arrays([out.column("_id"), out.column("host"), out.column("path"), pa.array(rule, pa.string()), pa.array(verdict, pa.string())], ["_id", "host", "path", "rule", "verdict"])


def judge_urls(pages: DataFrame, rules: list[tuple[str, str, str]] | DataFrame = RULES, default: str = "allow", id_col: str = "page_id", url: str = "url", sample: int = 20) -> DataFrame:
    """(id, host, path, rule, verdict) for every row of pages.

    rules: a list, or a DataFrame (host, path, action) of any size. No rule gives a null rule and the default
    verdict. Null ids and repeated rows pass through one by one; an empty table gives no rows; of equal
    rules with different actions the first in text order holds. Extra columns are not read.
    The slices' bounds come from at most `sample` keys a slice (bounded); a host of any size is cut by path and id.
    """
    spark = pages.sparkSession
    if not isinstance(rules, DataFrame):
        rules = spark.createDataFrame(rules, "host string, path string, action string")
    id_type = dict(pages.dtypes)[id_col]
    keyed = with_host_path(pages.select(F.col(id_col).alias("_id"), F.col(url).alias("_url")), "_url").drop("_url").withColumn("_key", host_key(F.col("host")))
    held = rules.where("host is not null and path is not null and action is not null").withColumn("host", F.translate("host", UPPER, LOWER))
    by_host = held.groupBy("host").agg(F.sort_array(F.collect_set(F.struct("path", "host", "action"))).alias("_rules")).withColumn("_key", host_key(F.col("host")))
    parts = n_partitions(spark)
    # bounds in (key, path, id) order: a bounded sample of hashed rows
    spread = F.xxhash64("_id", "_key", "path")
    picked = keyed.select("_key", "path", F.col("_id").cast("string").alias("i"), spread.alias("h")).orderBy("h").limit(sample * parts)
    bounds = sorted({(r._key, r.path, r.i or "") for r in picked.collect()})
    bounds = [bounds[len(bounds) * k // parts] for k in range(1, parts)] if bounds else []
    bounds = sorted(set(bounds))  # at most parts - 1

    @F.pandas_udf("int")
    def slice_of(key: pd.Series, path: pd.Series, i: pd.Series) -> pd.Series:
        return pd.Series([bisect_right(bounds, row) for row in zip(key, path, i)], dtype="int32")

    sliced = keyed.select("_id", "host", "path", "_key", slice_of(F.col("_key"), F.col("path"), F.coalesce(F.col("_id").cast("string"), F.lit(""))).alias("_slice"), F.lit(True).alias("_page"), F.lit(None).cast("array<struct<path:string,host:string,action:string>>").alias("_rules"))
    first, final = slice_of(F.col("_key"), F.lit(""), F.lit("")), slice_of(F.concat("_key", F.lit("\U0010ffff")), F.lit(""), F.lit(""))
    opened = by_host.select(F.lit(None).cast(id_type).alias("_id"), "host", F.lit("").alias("path"), "_key", F.explode(F.sequence(first, final)).alias("_slice"), F.lit(False).alias("_page"), "_rules")
    dealt = sliced.unionByName(opened).repartition(parts, "_slice").sortWithinPartitions("_slice", "_key", "_page", "path")
    judged = dealt.mapInArrow(sweep, f"_id {id_type}, host string, path string, rule string, verdict string")
    return judged.select(F.col("_id").alias(id_col), "host", "path", "rule", F.coalesce("verdict", F.lit(default)).alias("verdict"))
