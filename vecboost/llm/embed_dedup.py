"""Embedding near-duplicates: int8 tile products with per-vector error bounds.

A unit vector x is stored as s*q + r with integer q in [-127, 127]; e = |r| is known exactly. Then
|x.y - s_x s_y q_x.q_y| <= e_x + e_y + e_x e_y, so a tile product of the integer codes (exact in float32, as
its sums over at most 1,040 columns stay under 2^24) decides every pair outside that band; only pairs within it are computed again from
the full vectors in double precision.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, cut, unite

#: Covers the rounding of double and float32 steps in the bounds.
SLACK = 1e-6
#: Columns of one float32 product: 127 ** 2 * WIDTH < 2 ** 24.
WIDTH = 1040


def quantise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Unit rows to (int8 codes, scale, norm of what the codes miss)."""
    s = np.maximum(np.abs(x).max(axis=1), 1e-300) / 127
    q = np.rint(x / s[:, None]).astype(np.int8)
    e = np.sqrt(((x - q * s[:, None]) ** 2).sum(axis=1))
    return q, s, e


def unit(m: np.ndarray) -> np.ndarray:
    """Rows scaled to length 1 in double precision, without overflow."""
    m = m.astype(np.float64)
    m = m / np.abs(m).max(axis=1, keepdims=True)
    return m / np.sqrt((m * m).sum(axis=1, keepdims=True))


def tile_links(a: tuple, b: tuple | None, threshold: float, rows: int = 512) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs with cosine >= threshold, between a and b or (b None) within a, i < j; sub-blocks at a time.

    a, b: (unit rows, codes, scales, errors).
    """
    same = b is None
    xa, qa, sa, ea = a
    xb, qb, sb, eb = b or a
    fb = qb.astype(np.float32).T
    s_least, s_most, e_most = sb.min(), sb.max(), eb.max()
    for k in range(0, len(xa), rows):
        fa, s, e = qa[k : k + rows].astype(np.float32), sa[k : k + rows], ea[k : k + rows]
        first = k if same else 0
        product = fa[:, :WIDTH] @ fb[:WIDTH, first:]
        for c in range(WIDTH, fa.shape[1], WIDTH):  # pieces are exact in float32, their sum in float64
            product = product.astype(np.float64) + fa[:, c : c + WIDTH] @ fb[c : c + WIDTH, first:]
        low = threshold - (e + e_most + e * e_most) - SLACK
        low = low / (s * np.where(low > 0, s_most, s_least))  # no pair of the row under it can reach the threshold
        i, j = np.nonzero(product >= low[:, None].astype(np.float32) - 1)
        if same:
            keep = j > i
            i, j = i[keep], j[keep]
        near = product[i, j].astype(np.float64) * s[i] * sb[first + j]
        band = e[i] + eb[first + j] + e[i] * eb[first + j] + SLACK
        sure = near - band >= threshold
        open_ = np.nonzero(~sure & (near + band >= threshold))[0]
        for m in range(0, len(open_), 1 << 16):
            o = open_[m : m + (1 << 16)]
            sure[o] = np.einsum("ij,ij->i", xa[k + i[o]], xb[first + j[o]]) >= threshold
        yield k + i[sure], first + j[sure]


def link_vectors(vectors: DataFrame, threshold: float = 0.95, id_col: str = "vec_id", vec: str = "embedding", block: int = 8192) -> DataFrame:
    """(id, n_links, component_id, kept) for every row: links are cosine >= threshold, in double precision.

    Null, zero and non-finite vectors, and those with a null component, link with nothing. Equal vectors are
    one class: they count as links of each other and are compared with others once. Vectors of different
    lengths do not link. Repeated ids are taken as separate rows of one component; an empty table gives no rows.
    Blocks of at most about `block` distinct vectors (fewer where that leaves cores idle) meet pair by pair in tiles; a tile emits per-vector counts and a spanning
    forest, never its pairs. Work grows with the square of the distinct vectors, which exactness needs here;
    the number of tiles, not their size, grows.
    """
    spark = vectors.sparkSession
    v = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec).cast("array<double>").alias("x"))
    fine = F.coalesce(F.col("x").isNotNull() & (F.size("x") > 0) & F.forall("x", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & F.exists("x", lambda c: c != 0), F.lit(False))
    v = v.withColumn("fine", fine)
    classes = cut(v.where("fine").groupBy("x").agg(F.min("id").alias("node"), F.count("*").alias("n")))
    count = classes.count()
    cores = spark.sparkContext.defaultParallelism
    blocks = max(1, -(-count // block), min(math.isqrt(4 * cores), -(-count // 512)))  # tiles enough for all cores
    spread = F.pmod(F.xxhash64("x", F.lit(7)), F.lit(blocks)).cast("int")
    homed = classes.withColumn("b", spread)
    tiles = homed.select("*", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("o")).select(F.least("b", "o").alias("ta"), F.greatest("b", "o").alias("tb"), "b", "x", "node", "n", F.size("x").alias("d"))

    def tile(key, pdf: pd.DataFrame) -> pd.DataFrame:
        ta, tb, _ = key
        x = unit(np.stack(pdf["x"].to_numpy()))
        node, n, home = pdf["node"].to_numpy(), pdf["n"].to_numpy(), pdf["b"].to_numpy()
        parts = [np.nonzero(home == t)[0] for t in ([ta] if ta == tb else [ta, tb])]
        sides = [(x[p], *quantise(x[p])) for p in parts]
        links, label = np.zeros(len(x), np.int64), np.arange(len(x))
        if all(len(p) for p in parts):
            left, right = parts[0], parts[-1]
            for i, j in tile_links(sides[0], sides[1] if len(sides) > 1 else None, threshold):
                i, j = left[i], right[j]
                np.add.at(links, i, n[j])
                np.add.at(links, j, n[i])
                unite(label, i, j)
        touched = np.nonzero(links)[0]
        return pd.DataFrame({"a": node[touched], "b": node[label[touched]], "links": links[touched]})

    found = cut(tiles.groupBy("ta", "tb", "d").applyInPandas(tile, "a long, b long, links long"))
    links = found.groupBy("a").agg(F.sum("links").alias("links")).withColumnRenamed("a", "node")
    roots = components(found.select("a", "b"))
    told = classes.join(links, "node", "left").join(roots, "node", "left").select("x", "n", F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("root", "node").alias("root"))
    own = v.where("fine").join(told, "x").select("id", (F.col("links") + F.col("n") - 1).alias("n_links"), F.col("root").alias("component_id"))
    rest = v.where("not fine").select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    return own.unionByName(rest).select(F.col("id").alias(id_col), "n_links", "component_id", F.col("id").eqNullSafe(F.col("component_id")).alias("kept"))
