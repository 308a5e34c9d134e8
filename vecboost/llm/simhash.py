"""SimHash near-duplicates by sharded vantage-point trees.

Distinct fingerprints are dealt to the leaves of a vantage-point tree grown from a bounded sample. A
fingerprint lives in one leaf and visits each leaf of a lower number whose region comes within the radius
(triangle bounds); as two linked fingerprints always meet in the lower of their leaves, each leaf finds its
pairs alone, by further vantage points down to small blocks. Only spanning forests leave a leaf.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, cut, spread, unite

LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
SEED, SHINGLE, RADIUS = 42, 3, 3
#: Bounds: fingerprints in the sample (and for each leaf), shards, distinct fingerprints a shard is meant to hold, the same
#: where more shards would keep cores idle otherwise, visitors a member in one piece of a shard, block of brute force.
SAMPLE, A_LEAF, MAX_SHARDS, PER_SHARD, LEAST_SHARD, VISITORS, BLOCK = 1 << 16, 32, 1 << 16, 1 << 17, 1 << 13, 4, 256


def shingle_hashes(text: bytes, width: int = SHINGLE) -> np.ndarray:
    """64-bit hashes of the lower-case word shingles, repeats included; a shorter text is one shingle, one without words has none."""
    words = text.translate(LOWER).split()
    if not words:
        return np.zeros(0, np.uint64)
    shingles = map(b" ".join, zip(*(words[k:] for k in range(width)))) if len(words) >= width else [b" ".join(words)]
    return np.fromiter(map(xxhash.xxh64_intdigest, shingles, repeat(SEED)), np.uint64)


def majority(h: np.ndarray) -> int:
    """The 64 bits that over half the hashes set; zero for none."""
    ones = np.zeros(64, np.int64)
    for k in range(0, len(h), 4096):
        ones += np.unpackbits(h[k : k + 4096].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view("<u8")[0])


def fingerprint(text: bytes, width: int = SHINGLE) -> int:
    """64-bit SimHash over the word shingles (repeats count); zero without words."""
    return majority(shingle_hashes(text, width))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, fp long: the 64 bits as signed) for every row; a null text has no words."""
    kind = dict(docs.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = [fingerprint(t or b"") for t in b.column("text").cast(pa.binary()).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(np.array(fps, np.uint64).view(np.int64))], ["id", "fp"])

    return spread(docs.select(F.col(id_col).alias("id"), F.col(text).alias("text"))).mapInArrow(run, f"id {kind}, fp long")


def hamming(a, b):
    return np.bitwise_count(a ^ b).astype(np.int16)


def best_vantage(p: np.ndarray, rng: np.random.Generator, tries: int = 8) -> np.uint64:
    """The point, of a few, whose distances to a few hundred others spread most: the bounds prune best there."""
    some = p if len(p) <= 512 else rng.choice(p, 512, replace=False)
    tried = rng.choice(p, min(tries, len(p)), replace=False)
    return tried[int(np.argmax([hamming(some, v).astype(np.float32).var() for v in tried]))]


def grow(sample: np.ndarray, depth: int, rng: np.random.Generator | None = None, path: str = "") -> dict:
    """Inner nodes of a vantage-point tree by path: (vantage, split distance); inside is distance <= split."""
    rng = rng or np.random.default_rng(7)
    if not depth or len(sample) < 2:
        return {}
    v = best_vantage(sample, rng)
    d = hamming(sample, v)
    mu = int(np.median(d))
    inside = d <= mu
    if inside.all():
        mu = int(np.max(d)) - 1
        inside = d <= mu
        if not inside.any():
            return {}
    return {path: (int(v), mu)} | grow(sample[inside], depth - 1, rng, path + "0") | grow(sample[~inside], depth - 1, rng, path + "1")


def route(tree: dict, p: np.ndarray, radius: int) -> list[tuple[str, np.ndarray, np.ndarray]]:
    """(leaf, indexes, at home) for each leaf that points live in or come within the radius of."""
    out, todo = [], [("", np.arange(len(p)), np.ones(len(p), bool))]
    while todo:
        path, i, home = todo.pop()
        if not len(i):
            continue
        if path not in tree:
            out.append((path, i, home))
            continue
        v, mu = tree[path]
        d = hamming(p[i], np.uint64(v))
        inside = d <= mu
        near = inside | (d - radius <= mu)
        far = ~inside | (d + radius > mu)
        todo.append((path + "0", i[near], (home & inside)[near]))
        todo.append((path + "1", i[far], (home & ~inside)[far]))
    return out


def close_pairs(p: np.ndarray, members: np.ndarray, visitors: np.ndarray, radius: int, rng: np.random.Generator, own: bool = True) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs within the radius: member with member (once; if own), member with visitor."""
    todo = [(members, visitors)]
    while todo:
        m, v = todo.pop()
        if not len(m) or len(m) + len(v) < 2:
            continue
        if len(m) > BLOCK:
            at = best_vantage(p[m], rng)
            dm, dv = hamming(p[m], at), hamming(p[v], at)
            mu = int(np.median(dm))
            inside = dm <= mu
            if inside.all():
                mu = int(dm.max()) - 1
                inside = dm <= mu
            if inside.any():  # pairs across the split are found inside
                cross = ~inside & (dm - radius <= mu) & own
                todo.append((m[inside], np.concatenate([v[dv - radius <= mu], m[cross]])))
                todo.append((m[~inside], v[dv + radius > mu]))
                continue
        for k in range(0, len(m), BLOCK):
            some = m[k : k + BLOCK]
            rest = np.concatenate([m[k:], v]) if own else v
            for r in range(0, len(rest), 1 << 14):
                i, j = np.nonzero(hamming(p[some][:, None], p[rest[r : r + (1 << 14)]][None, :]) <= radius)
                keep = some[i] != rest[r + j]
                yield some[i[keep]], rest[r + j[keep]]


def pieces_of(tree: dict, sample: np.ndarray, radius: int) -> dict[str, int]:
    """Into how many pieces the visitors of each leaf go (1 if not named), by what the sample's points do."""
    home, visits = {}, {}
    own = np.empty(len(sample), object)
    places = route(tree, sample, radius)
    for leaf, i, at_home in places:
        own[i[at_home]] = leaf
        home[leaf] = int(at_home.sum())
    for leaf, i, _ in places:
        visits[leaf] = sum(leaf < x for x in own[i])
    return {leaf: n for leaf in visits if (n := -(-visits[leaf] // (VISITORS * max(1, home[leaf])))) > 1}


def forests(fps: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Distinct (fp, node, n) to (a, b): for each piece of a shard a spanning forest of its links of at most radius differing bits.

    A leaf is at most about PER_SHARD members; it meets its visitors in pieces of about VISITORS of them a member, so no
    task's memory grows with the number of fingerprints until there are PER_SHARD * MAX_SHARDS.
    """
    spark = fps.sparkSession
    n = fps.count()
    levels = lambda size: int(np.ceil(np.log2(max(1, n / size))))
    busy = int(np.ceil(np.log2(2 * spark.sparkContext.defaultParallelism)))
    depth = min(int(np.log2(MAX_SHARDS)), max(levels(PER_SHARD), min(busy, levels(LEAST_SHARD))))
    size = max(SAMPLE, A_LEAF << depth)
    share = min(1 << 20, -(-(size << 20) // max(1, n)))
    some = fps.where(F.pmod(F.xxhash64("fp", F.lit(3)), F.lit(1 << 20)) < share).select("fp").limit(2 * size) if depth else fps.limit(0).select("fp")
    sample = np.sort(some.toPandas()["fp"].to_numpy(np.int64).view(np.uint64))
    tree = grow(sample, depth)
    pieces = pieces_of(tree, sample, radius)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            p = b.column("fp").to_numpy(zero_copy_only=False).view(np.uint64)
            own = np.empty(len(p), object)
            places = route(tree, p, radius)
            for leaf, i, home in places:
                own[i[home]] = leaf
            for leaf, i, home in places:
                n_pieces = pieces.get(leaf, 1)
                guests = i[~home & np.array([leaf < x for x in own[i]], bool)]
                at = (p[guests] * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)).astype(np.int64) % n_pieces
                for k in range(n_pieces):  # members go to every piece
                    keep = np.concatenate([i[home], guests[at == k]])
                    take = pa.array(keep)
                    yield pa.RecordBatch.from_arrays([pa.array([leaf] * len(keep), pa.string()), pa.array([k] * len(keep), pa.int32()), b.column("fp").take(take), b.column("node").take(take), pa.array(np.arange(len(keep)) < home.sum())], ["leaf", "piece", "fp", "node", "home"])

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        p, node = pdf["fp"].to_numpy().view(np.uint64), pdf["node"].to_numpy()
        home, label, first = pdf["home"].to_numpy(bool), np.arange(len(pdf)), pdf["piece"].iat[0] == 0
        for i, j in close_pairs(p, np.nonzero(home)[0], np.nonzero(~home)[0], radius, np.random.default_rng(11), first):
            unite(label, i, j)
        other = np.nonzero(label != np.arange(len(label)))[0]
        return pd.DataFrame({"a": node[other], "b": node[label[other]]})

    dealt = fps.select("fp", "node").mapInArrow(deal, "leaf string, piece int, fp long, node long, home boolean")
    return dealt.groupBy("leaf", "piece").applyInPandas(search, "a long, b long")


def link(fps: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Distinct (fp, node, n) to (node, root): the components over links of at most radius differing bits."""
    return components(forests(fps, radius))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", radius: int = RADIUS) -> DataFrame:
    """(id, fingerprint, component_id) for every row; component_id is the least id reachable over links.

    Null, empty and blank texts have fingerprint zero and link like any other. Equal fingerprints are one node
    from a partial aggregate on, whatever the size of their group. Null ids never lead a component that has others; repeated
    rows share theirs; an empty table gives no rows. Columns besides id and text are not read.
    """
    fp = cut(fingerprints(docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).alias("text")), "id"))
    distinct = cut(fp.groupBy("fp").agg(F.min("id").alias("node"), F.count("*").alias("n")))
    roots = link(distinct.where("node is not null"), radius)
    told = distinct.join(roots, "node", "left").select("fp", F.coalesce("root", "node").alias("component_id"))
    return fp.join(told, "fp").select(F.col("id").alias(id_col), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """docs without all but the lowest id of each component; rows without an id, and repeats of a kept row, stay."""
    spare = near_duplicates(docs, id_col, text).where("component_id <> " + f"`{id_col}`").select(id_col).distinct()
    return docs.join(spare, id_col, "left_anti")
