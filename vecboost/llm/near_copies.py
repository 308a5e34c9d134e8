"""The SimHash operator for a similarity bound: near copies by the Jaccard similarity of word shingles.

Texts of one shingle set are one node. The vantage-point trees of simhash.py tie nodes whose fingerprints lie within their
radius; as texts at similarity 0.8 may lie further apart than any radius at which triangle bounds still prune, nodes that
agree in a band of minhashes are tied too. The components over both kinds of ties are clusters; within a cluster all pairs
are compared by their whole shingle sets, in tiles of bounded size. Ties only choose what is compared: a link is always an
exact similarity.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, cut, n_partitions, spread, unite
from .simhash import forests, majority, shingle_hashes

#: Words of a shingle, and the least similarity of a link: 4 / 5.
SHINGLE, SHARE = 5, (4, 5)
#: A pair at similarity s is compared but for (1 - s ** ROWS) ** BANDS: 7e-6 at 0.8, 2e-12 at 0.9.
BANDS, ROWS = 30, 5
#: Bounds: nodes of a cluster's block (a tile has two), tiled nodes that a task's bundle is meant to hold, columns of a product.
BLOCK, BUNDLE, COLUMNS = 128, 1024, 4096
_rng = np.random.default_rng(23)
FACTOR, SHIFT = _rng.integers(0, 2**63, BANDS * ROWS, np.uint64) * np.uint64(2) + np.uint64(1), _rng.integers(0, 2**63, BANDS * ROWS, np.uint64)


def shingle_set(text: bytes, width: int = SHINGLE) -> np.ndarray:
    """Distinct shingles as ascending 64-bit hashes; a shorter text is one shingle, one without words has none."""
    return np.unique(shingle_hashes(text, width))


def digest(s: np.ndarray) -> str:
    return xxhash.xxh3_128_hexdigest(s.tobytes())


def band_keys(s: np.ndarray) -> list[int]:
    """A signed 64-bit key for each band of minhashes; none for the empty set."""
    if not len(s):
        return []
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max)
    for k in range(0, len(s), 256):
        np.minimum(least, (s[k : k + 256, None] * FACTOR + SHIFT).min(axis=0), out=least)
    raw = least.astype("<u8").tobytes()
    size = 8 * ROWS
    keys = np.fromiter((xxhash.xxh64_intdigest(raw[k * size : (k + 1) * size], seed=k) for k in range(BANDS)), np.uint64)
    return keys.view(np.int64).tolist()


def shared(sets: list[np.ndarray]) -> np.ndarray:
    """How many shingles each two sets share."""
    if len(sets) == 2:
        both = len(np.intersect1d(*sets, assume_unique=True))
        return np.array([[len(sets[0]), both], [both, len(sets[1])]])
    row = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, col, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    often = times > 1  # the others are in no product
    row, col = row[often[col]], (np.cumsum(often) - 1)[col[often[col]]]
    order = np.argsort(col, kind="stable")
    row, col = row[order], col[order]
    out = np.zeros((len(sets), len(sets)), np.int64)
    for first in range(0, int(often.sum()), COLUMNS):
        a, b = np.searchsorted(col, [first, first + COLUMNS])
        x = np.zeros((len(sets), COLUMNS), np.float32)
        x[row[a:b], col[a:b] - first] = 1
        out += (x @ x.T).astype(np.int64)
    return out


def similar_pairs(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs i < j of non-empty sets with Jaccard similarity of SHARE or more, in whole numbers."""
    up, down = SHARE
    n = np.array([len(s) for s in sets])
    ok = shared(sets) * (up + down) >= up * (n[:, None] + n[None, :])
    return np.nonzero(np.triu(ok & (n > 0)[:, None] & (n > 0)[None, :], 1))


def links(nodes: DataFrame, docs: DataFrame) -> DataFrame:
    """nodes (digest, node, bands, fp) and docs (id, text) to (a, b): for each tile a spanning forest of its links."""
    led = nodes.where("node is not null")
    alike = cut(led.groupBy("fp").agg(F.min("node").alias("node"), F.count("*").alias("n")))
    close = led.join(alike.select("fp", F.col("node").alias("head")), "fp").where("head < node").select(F.col("node").alias("a"), F.col("head").alias("b"))
    close = close.union(forests(alike))
    ties = nodes.where("node is not null").select("node", F.explode("bands").alias("key"))
    heads = ties.groupBy("key").agg(F.min("node").alias("head"), F.max("node").alias("last")).where("head < last").select("key", "head")
    banded = ties.join(heads, "key").where("head < node").select(F.col("node").alias("a"), F.col("head").alias("b"))
    told = components(banded.union(close))
    told = told.union(told.select("root", "root").distinct())
    member = cut(nodes.join(told, "node").select("node", "digest", "root"))
    total = member.count()

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            wanted, sets, keep = b.column("digest").to_pylist(), [], []
            for k, t in enumerate(b.column("text").cast(pa.binary()).to_pylist()):
                s = shingle_set(t or b"")
                if digest(s) == wanted[k]:  # repeated ids may have other texts
                    keep.append(k)
                    sets.append(s.tobytes())
            take = pa.array(keep, pa.int64())
            yield pa.RecordBatch.from_arrays([*(b.column(c).take(take) for c in ("root", "node", "digest")), pa.array(sets, pa.binary())], ["root", "node", "digest", "s"])

    texts = docs.join(member.withColumnRenamed("node", "id"), "id").select("root", F.col("id").alias("node"), "digest", "text")
    sets = texts.mapInArrow(gather, "root long, node long, digest string, s binary").groupBy("root", "node", "digest").agg(F.first("s").alias("s"))
    blocks = member.groupBy("root").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"))
    homed = sets.join(blocks, "root").withColumn("b", F.pmod(F.xxhash64("digest"), F.col("blocks")).cast("int"))
    tiles = homed.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("root", F.least("b", "o").alias("ta"), F.greatest("b", "o").alias("tb"), "node", "s")
    bundles = max(n_partitions(docs.sparkSession), -(-total // BUNDLE))

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        a, b = [], []
        for _, at in pdf.groupby(["root", "ta", "tb"], sort=False).indices.items():
            if len(at) > 1:
                node, label = pdf["node"].to_numpy()[at], np.arange(len(at))
                unite(label, *similar_pairs([np.frombuffer(pdf["s"].iat[k], np.uint64) for k in at]))
                other = np.nonzero(label != np.arange(len(at)))[0]
                a.append(node[other])
                b.append(node[label[other]])
        return pd.DataFrame({"a": np.concatenate([*a, np.zeros(0, np.int64)]), "b": np.concatenate([*b, np.zeros(0, np.int64)])})

    bundle = F.pmod(F.xxhash64("root", "ta", "tb"), F.lit(bundles)).alias("bundle")
    return tiles.select(bundle, "*").groupBy("bundle").applyInPandas(search, "a long, b long")


def near_copies(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, component_id) for every row; component_id is the least id reachable over links of similarity 0.8 or more.

    Similarity is Jaccard's, of the sets of lower-case five-word shingles. Null, empty and blank texts have the same
    set, the empty one, and so are copies of each other. Null ids never lead a component that has others; rows that
    repeat an id share its component; an empty table gives no rows. All pairs of a cluster are compared, so work grows with the square of
    the different texts in the largest cluster, over many tasks.
    """
    plain = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).alias("text"))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            hashes = [shingle_hashes(t or b"", SHINGLE) for t in b.column("text").cast(pa.binary()).to_pylist()]
            sets, fps = [np.unique(h) for h in hashes], np.array([majority(h) for h in hashes], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array([digest(s) for s in sets], pa.string()), pa.array([band_keys(s) for s in sets], pa.list_(pa.int64())), pa.array(fps)], ["id", "digest", "bands", "fp"])

    signed = cut(spread(plain).mapInArrow(sign, "id long, digest string, bands array<long>, fp long"))
    nodes = cut(signed.groupBy("digest").agg(F.min("id").alias("node"), F.first("bands").alias("bands"), F.min("fp").alias("fp")))
    roots = components(links(nodes, plain))
    told = nodes.join(roots, "node", "left").select("digest", F.coalesce("root", "node").alias("component_id"))
    return signed.select("id", "digest").join(told, "digest").select(F.col("id").alias(id_col), "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """docs without all but the lowest id of each component; rows without an id, and repeats of a kept row, stay.

    Null and empty texts are copies of each other; columns of any names pass through; an empty table gives no rows.
    """
    spare = near_copies(docs, id_col, text).where("component_id <> " + f"`{id_col}`").select(id_col).distinct()
    return docs.join(spare, id_col, "left_anti")
