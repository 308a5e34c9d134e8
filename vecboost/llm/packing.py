"""Packing into optimal length buckets.

The global histogram of lengths is small whatever the corpus; dynamic programming over it chooses the bucket bounds that
pad least. Within a bucket every row is padded to the bound, and a batch takes as many as its token budget allows.
"""

from __future__ import annotations

from collections import deque

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WORD, cut, prefix_sums, spread

def n_words(text):
    """Words of a text column (null: none), in the JVM."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def optimal_bounds(lengths: np.ndarray, counts: np.ndarray, tokens: np.ndarray, k: int) -> tuple[list[int], int]:
    """Of ascending distinct lengths, their rows and those rows' tokens: at most k bounds of least padding, and that padding.

    best[j], over the first j lengths, is the least over i < j of best[i] + lengths[j-1] * rows(i..j) - tokens(i..j). For a
    fixed i that is a line in lengths[j-1] whose slope falls as i grows, so the lower hull of the lines answers all j in one
    sweep: a layer takes time in proportion to the lengths, all in whole numbers.
    """
    n = len(lengths)
    if not n:
        return [], 0
    at, rows, toks = [int(v) for v in lengths], [0], [0]
    for c, t in zip(counts.tolist(), tokens.tolist()):
        rows.append(rows[-1] + c)
        toks.append(toks[-1] + t)
    best: list[int | None] = [0] + [None] * n
    came: list[list[int]] = []
    for _ in range(min(k, n)):
        now, back = [0] + [None] * n, [0] * (n + 1)
        hull: deque[tuple[int, int, int]] = deque()  # (slope, height, i)
        for j in range(1, n + 1):
            if best[j - 1] is not None:
                m, b = -rows[j - 1], best[j - 1] + toks[j - 1]
                while len(hull) > 1 and (hull[-1][1] - hull[-2][1]) * (hull[-1][0] - m) >= (b - hull[-1][1]) * (hull[-2][0] - hull[-1][0]):
                    hull.pop()
                hull.append((m, b, j - 1))
            x = at[j - 1]
            while len(hull) > 1 and hull[1][0] * x + hull[1][1] <= hull[0][0] * x + hull[0][1]:
                hull.popleft()
            m, b, i = hull[0]
            now[j], back[j] = m * x + b + x * rows[j] - toks[j], i
        best = now
        came.append(back)
    bounds, j = [], n
    for back in reversed(came):
        if not j:
            break
        bounds.append(at[j - 1])
        j = back[j]
    return sorted(bounds), int(best[n])


def bucket_bounds(sized: DataFrame, k: int, length: str = "n_tokens") -> list[int]:
    """The optimal bounds over all rows; the histogram has one row a distinct length, so no more than the longest text has words."""
    h = sized.groupBy(F.col(length).alias("g")).agg(F.count("*").alias("n")).orderBy("g").toPandas()
    g, n = h["g"].to_numpy(np.int64), h["n"].to_numpy(np.int64)
    return optimal_bounds(g, n, g * n, k)[0]


def pack(docs: DataFrame, budget: int = 16_384, buckets: int = 16, id_col: str = "doc_id", text: str = "text", bounds: list[int] | None = None, seed: int = 1) -> DataFrame:
    """(id, n_tokens, bucket_length, batch, place) for every row: n_tokens is the words of the whole text.

    A batch holds rows of one bucket: max(1, budget // bucket_length) of them, in a seeded order of ids; it is named
    'bucket_length-number'. Texts are never cut: one longer than the budget is a batch of its own. Null and empty
    texts count one token (their end); null ids and repeated rows are placed each; an empty table gives no rows.
    Other columns are not read.
    """
    sized = spread(docs.select(F.col(id_col).alias("_id"), F.col(text).alias("_text"))).select("_id", F.greatest(n_words(F.col("_text")), F.lit(1)).alias("n_tokens"))
    sized = cut(sized)  # texts are read and counted once
    bounds = bucket_bounds(sized, buckets) if bounds is None else bounds
    length = F.lit(None).cast("long")
    for b in sorted(bounds, reverse=True):
        length = F.when(F.col("n_tokens") <= b, F.lit(b).cast("long")).otherwise(length)
    placed = sized.withColumn("bucket_length", length).withColumn("_one", F.lit(1).cast("long")).withColumn("_h", F.xxhash64("_id", F.lit(seed)))
    ranked = prefix_sums(placed, ["bucket_length"], ["_h", "_id"], "_one", "_rank")
    room = F.greatest(F.floor(F.lit(budget) / F.col("bucket_length")), F.lit(1)).cast("long")
    batch = F.floor(F.col("_rank") / room).cast("long")
    return ranked.select(F.col("_id").alias(id_col), "n_tokens", "bucket_length", F.concat_ws("-", "bucket_length", batch).alias("batch"), (F.col("_rank") % room).alias("place"))
