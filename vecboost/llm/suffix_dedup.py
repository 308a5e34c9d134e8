"""Removal of passages that a smaller document has: suffix arrays by two-stage sorting over candidate stretches.

Any two equal strings of L bytes have the same anchor: the place of the least K-gram hash in them. So
1. every task gives the hashes of its anchors, and by hash range the shared ones are found (in two tasks or two documents);
2. texts give, for shared anchors only, the stretch all of whose L-byte strings have that anchor; equal stretches
   in one task are settled there and leave it as one;
3. per hash range, equal stretches are settled again, and the different stretches of one anchor go into a suffix
   array: suffixes smaller than their successors are sorted directly, the rest induced by scans of the character buckets, and adjacent
   common prefixes of L bytes give the classes of equal strings, each with its least document;
4. every text loses the bytes of its strings that a smaller document has.
Hash ranges, not passages, are dealt to tasks, and a passage of any frequency leaves each task once. What goes back
to a slice of the input is written to the shared folder under the slice's number; texts never move.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.parquet as pq
import xxhash
import zstandard
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import filesystem, fresh_dir, is_scan, n_partitions

LENGTH, GRAM = 50, 24
MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93)]
KEY_BITS = 38
POS = np.uint64(30)
#: Sizes of working pieces, which bound memory: bytes of text at a time, stretches held before they are shipped, bytes of one suffix array.
BLOCK, HELD, ARRAY = 1 << 20, 60_000, 1 << 19
#: An anchor that a slice has more often is dealt by SIDE bytes before it and by SIDE bytes after it: a string of LENGTH bytes
#: that has the anchor has one of the two, LENGTH being GRAM + 2 * SIDE.
OFTEN, SIDE = 256, (LENGTH - GRAM) // 2
LAST = np.iinfo(np.int64).max


def words_at_each(buf: bytes) -> np.ndarray:
    """Eight bytes from every place, big end first; places near the end see zeros."""
    padded = bytes(buf) + b"\0" * 8
    return np.ndarray((len(buf),), ">u8", padded, 0, (1,)).astype(np.uint64)


def anchors(buf: bytes, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of texts end to end in buf: (hash, text, first, last, place): the LENGTH-byte strings that start from first to
    last in that text have their least GRAM hash, leftmost if equal, at one place."""
    n, none = len(buf), np.zeros(0, np.int64)
    if n < LENGTH:
        return none.astype(np.uint64), none, none, none, none
    w = words_at_each(buf)
    m = n - GRAM + 1
    h = np.zeros(m, np.uint64)
    for k in range(0, GRAM, 8):
        h += w[k : k + m] * MIX[k // 8]
        h ^= h >> np.uint64(29)
    h *= MIX[3]
    h ^= h >> np.uint64(32)
    least, have, width = (h >> POS << POS) | np.arange(m, dtype=np.uint64), 1, LENGTH - GRAM + 1
    while have * 2 <= width:
        least = np.minimum(least[:-have], least[have:])
        have *= 2
    if have < width:
        least = np.minimum(least[: len(least) - (width - have)], least[width - have :])
    sizes = np.diff(np.concatenate([[0], ends]))
    text = np.repeat(np.arange(len(ends)), sizes)[: len(least)]
    starts = np.arange(len(least))
    inside = starts + LENGTH <= ends[text]
    starts, at = starts[inside], (least[inside] & np.uint64((1 << 30) - 1)).astype(np.int64)
    if not len(starts):
        return none.astype(np.uint64), none, none, none, none
    new = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
    first, last = starts[new], starts[np.concatenate([new[1:] - 1, [len(starts) - 1]])]
    return h[at[new]], text[first], first, last, at[new]


def blocks(batches: Iterator[pa.RecordBatch], text: str, others: list[str]) -> Iterator[tuple[int, bytes, np.ndarray, list[list], int]]:
    """(first row, texts end to end, their ends, other columns, offset) over pieces of a partition of about BLOCK bytes.

    A longer text comes alone, in pieces that begin at the offset and overlap so far that every string of LENGTH bytes
    lies in just one; what holds of its strings holds of the text's.
    """
    row = 0
    for b in batches:
        texts = b.column(text).cast(pa.binary()).to_pylist()
        rest = [b.column(c).to_pylist() for c in others]
        k = 0
        while k < len(texts):
            size, j = 0, k
            while j < len(texts) and (j == k or size + len(texts[j] or b"") <= BLOCK):
                size += len(texts[j] or b"")
                j += 1
            cols = [c[k:j] for c in rest]
            if size > BLOCK:
                for at in range(0, size, BLOCK):
                    piece = texts[k][at : at + BLOCK + LENGTH - 1]
                    yield row + k, piece, np.array([len(piece)]), cols, at
            else:
                some = [t or b"" for t in texts[k:j]]
                yield row + k, b"".join(some), np.cumsum([len(t) for t in some]), cols, 0
            k = j
        row += len(texts)


def ids_crc(ids: pa.Array, crc: int = 0) -> int:
    """A running check of a slice's ids, in their order."""
    ids = ids.cast(pa.int64())
    return zlib.crc32(pc.fill_null(ids, LAST).to_numpy(zero_copy_only=False).tobytes(), crc)


def pack5(v: np.ndarray) -> bytes:
    return (v & 0xFFFFFFFF).astype("<u4").tobytes() + (v >> 32).astype("u1").tobytes()


def unpack5(b: bytes) -> np.ndarray:
    n = len(b) // 5
    return np.frombuffer(b, "<u4", n).astype(np.int64) | (np.frombuffer(b, "u1", n, 4 * n).astype(np.int64) << 32)


def keyed(h: np.ndarray, bits: int) -> np.ndarray:
    """The hash's leading bits + KEY_BITS bits, as an integer; its leading `bits` are the range it belongs to."""
    return (h >> np.uint64(64 - bits - KEY_BITS)).astype(np.int64)


def suffix_order(text: np.ndarray, depth: int = LENGTH) -> np.ndarray:
    """All suffixes of the text (uint8) in order of their first `depth` bytes at least, by two-stage sorting.

    Suffixes smaller than their successors are sorted directly; the others are induced: buckets are scanned in
    ascending order, and each suffix met places its predecessor, if that is of the other kind, next in its bucket.
    """
    n = len(text)
    if n < 2:
        return np.arange(n)
    # kind of each suffix: by the next different byte; runs at the end are greater than the end of the text
    differs = np.flatnonzero(text[:-1] != text[1:])
    following = np.searchsorted(differs, np.arange(n - 1))
    smaller = np.zeros(n, bool)
    has = following < len(differs)
    at = differs[following[has]]
    smaller[:-1][has] = text[at] < text[at + 1]
    own = np.flatnonzero(smaller)
    w = words_at_each(text.tobytes())
    own = own[np.argsort(w[own], kind="stable")]
    group = np.cumsum(np.concatenate([[0], w[own][1:] != w[own][:-1]]))
    for k in range(8, depth, 8):  # only what is still tied is sorted on
        sizes = np.bincount(group, minlength=1)
        tied = np.flatnonzero(sizes[group] > 1) if len(own) else own
        if not len(tied):
            break
        place = own[tied] + k
        key = np.where(place < n, w[np.minimum(place, n - 1)], np.uint64(0))
        order = np.lexsort((key, group[tied]))
        own[tied] = own[tied][order]
        key, g = key[order], group[tied]
        step = np.zeros(len(own), np.int64)
        step[0] = 0
        step[1:] = group[1:] != group[:-1]
        inner = np.flatnonzero((g[1:] == g[:-1]) & (key[1:] != key[:-1])) + 1
        step[tied[inner]] = 1
        group = np.cumsum(step)
    byte = text[own]
    first_of = np.searchsorted(byte, np.arange(257))
    waiting: list[list[np.ndarray]] = [[] for _ in range(256)]
    waiting[text[n - 1]].append(np.array([n - 1]))  # the last suffix follows the end of the text
    out = []
    for c in range(256):
        held = np.concatenate(waiting[c]) if waiting[c] else np.zeros(0, np.int64)
        parts, fresh = [held], held
        while len(fresh):  # runs of the byte itself
            before = fresh[fresh > 0] - 1
            fresh = before[(text[before] == c) & ~smaller[before]]
            parts.append(fresh)
        parts.append(own[first_of[c] : first_of[c + 1]])
        bucket = np.concatenate(parts)
        out.append(bucket)
        before = bucket[bucket > 0] - 1
        before = before[text[before] > c]
        if len(before):
            b = text[before]
            order = np.argsort(b, kind="stable")
            b, before = b[order], before[order]
            cuts = np.flatnonzero(b[1:] != b[:-1]) + 1
            for part in np.split(before, cuts):
                waiting[text[part[0]]].append(part)
        waiting[c] = []
    return np.concatenate(out)


def same_prefix(w: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Whether LENGTH bytes from a and from b are equal (w: words_at_each)."""
    same = np.ones(len(a), bool)
    for k in [*range(0, LENGTH - 8, 8), LENGTH - 8]:
        left = np.flatnonzero(same)
        same[left] = w[a[left] + k] == w[b[left] + k]
    return same


def owned_by_smaller(stretches: list[bytes], least: np.ndarray) -> Iterator[tuple[int, int, int]]:
    """(stretch, first, last) runs of starts whose LENGTH-byte strings are in a stretch of a smaller document."""
    sizes = np.array([len(s) for s in stretches])
    buf = b"\xff".join(stretches) + b"\xff"  # no byte of UTF-8
    start = np.concatenate([[0], np.cumsum(sizes + 1)[:-1]])
    text = np.frombuffer(buf, np.uint8)
    which = np.repeat(np.arange(len(sizes)), sizes + 1)
    valid = np.arange(len(text)) - start[which] <= sizes[which] - LENGTH
    sa = suffix_order(text)
    sa = sa[valid[sa]]
    if not len(sa):
        return
    w = words_at_each(buf)
    new = np.concatenate([[True], ~same_prefix(w, sa[:-1], sa[1:])])
    doc = least[which[sa]]
    lowest = np.minimum.reduceat(doc, np.flatnonzero(new))[np.cumsum(new) - 1]
    hit = np.sort(sa[lowest < doc])
    if not len(hit):
        return
    cuts = np.flatnonzero((np.diff(hit) != 1) | (which[hit[1:]] != which[hit[:-1]])) + 1
    firsts, lasts = hit[np.concatenate([[0], cuts])], hit[np.concatenate([cuts - 1, [len(hit) - 1]])]
    for s, a, b in zip(which[firsts].tolist(), (firsts - start[which[firsts]]).tolist(), (lasts - start[which[lasts]]).tolist()):
        yield s, a, b


def marks_blob(row: np.ndarray, start: np.ndarray, end: np.ndarray) -> bytes:
    """Ranges by row, those that touch merged, compressed."""
    order = np.lexsort((start, row))
    row, start, end = row[order], start[order], end[order]
    if len(row):
        key = row.astype(np.int64) << 31
        reach = np.maximum.accumulate(key + end)
        new = np.concatenate([[True], key[1:] + start[1:] > reach[:-1]])
        firsts = np.flatnonzero(new)
        row, start, end = row[firsts], start[firsts], np.maximum.reduceat(end, firsts)
    return zstandard.ZstdCompressor(level=1).compress(np.stack([row, start, end]).astype("<i4").tobytes())


def read_marks(blob: bytes) -> np.ndarray:
    return np.frombuffer(zstandard.ZstdDecompressor().decompress(blob), "<i4").reshape(3, -1)


def side_blobs(folder: str, part: int) -> list[dict]:
    """What earlier steps left for slice `part`."""
    store, path = filesystem(f"{folder}/part={part}")
    if store.get_file_info(path).type == pafs.FileType.NotFound:
        return []
    out = []
    for f in sorted(x.path for x in store.get_file_info(pafs.FileSelector(path)) if x.path.endswith(".parquet")):
        with store.open_input_file(f) as g:
            out += pq.ParquetFile(g).read().to_pylist()
    return out


def sides(h: int, buf: bytes, first: int, end: int, place: int) -> tuple[int, ...]:
    """Hashes by which a stretch (first to end, its anchor at place) meets those that share SIDE bytes before or after the anchor."""
    after = place + GRAM
    out = []
    if place - first >= SIDE:
        out.append(xxhash.xxh64_intdigest(buf[place - SIDE : after], seed=1))
    if end - after >= SIDE:
        out.append(xxhash.xxh64_intdigest(buf[place : after + SIDE], seed=2))
    return tuple(out) or (h,)


class SuffixDedup:
    """The whole job over docs; marks() first, then digests() or cut_texts() read them slice by slice."""

    def __init__(self, docs: DataFrame, id_col: str = "doc_id", text: str = "text", folder: str | None = None):
        spark = docs.sparkSession
        self.folder = folder or fresh_dir(spark, "suffix")
        if not is_scan(docs):
            docs.write.parquet(f"{self.folder}/input.parquet")
            docs = spark.read.schema(docs.schema).parquet(f"{self.folder}/input.parquet")
        self.docs, self.id_col, self.text = docs, id_col, text
        self.parts = max(n_partitions(spark), self.docs.rdd.getNumPartitions())  # of a plain scan: nothing is run
        self.bits = max(1, (8 * self.parts - 1).bit_length())

    def _read(self) -> DataFrame:
        return self.docs.select(F.col(self.id_col).cast("long").alias("id"), F.col(self.text).alias("text"))

    def shared_keys(self) -> DataFrame:
        """(part, bucket, keys): for each slice, its anchors' keys that another document has too."""
        bits = self.bits

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            part, keys, rows = TaskContext.get().partitionId(), [], []
            for row, buf, ends, _, _ in blocks(batches, "text", []):
                h, t, *_ = anchors(buf, ends)
                keys.append(keyed(h, bits))
                rows.append(t + row)
            if not keys:
                return
            key, row = np.concatenate(keys), np.concatenate(rows)
            order = np.argsort(key, kind="stable")
            key, row = key[order], row[order]
            if not len(key):
                return
            firsts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
            several = np.minimum.reduceat(row, firsts) != np.maximum.reduceat(row, firsts)
            often = np.diff(np.append(firsts, len(key))) > OFTEN
            key = key[firsts]
            bucket, code = key >> KEY_BITS, ((key & ((1 << KEY_BITS) - 1)) << 2) | (often << 1) | several
            cuts = np.flatnonzero(bucket[1:] != bucket[:-1]) + 1
            at = np.concatenate([[0], cuts])
            yield pa.RecordBatch.from_pydict({"bucket": pa.array(bucket[at], pa.int32()), "part": pa.array([part] * len(at), pa.int32()), "keys": pa.array([pack5(c) for c in np.split(code, cuts)], pa.binary())})

        def meet(key, pdf: pd.DataFrame) -> pd.DataFrame:
            codes = [unpack5(k) for k in pdf["keys"]]
            code = np.concatenate(codes)
            part = np.repeat(pdf["part"].to_numpy(), [len(c) for c in codes])
            order = np.argsort(code, kind="stable")
            code = code[order]
            k, part = code >> 2, part[order]
            new = np.concatenate([[True], k[1:] != k[:-1]])
            g = np.cumsum(new) - 1
            firsts = np.flatnonzero(new)
            shared = (np.diff(np.concatenate([firsts, [len(k)]])) > 1) | (np.maximum.reduceat(code & 1, firsts) > 0)
            often = np.maximum.reduceat(code >> 1 & 1, firsts)
            k, part = ((k << 1) | often[g])[shared[g]], part[shared[g]]
            order = np.argsort(part, kind="stable")
            k, part = k[order], part[order]
            cuts = np.flatnonzero(part[1:] != part[:-1]) + 1
            at = np.concatenate([[0], cuts])[: len(part)]
            return pd.DataFrame({"part": part[at], "bucket": np.full(len(at), key[0]), "keys": [pack5(x) for x in np.split(k, cuts)] if len(k) else []})

        given = self._read().mapInArrow(run, "bucket int, part int, keys binary")
        return given.groupBy("bucket").applyInPandas(meet, "part int, bucket int, keys binary")

    def stretches(self, keys_at: str) -> DataFrame:
        """(bucket, part, kind, blob): stretches of shared anchors, one of a kind a slice, and marks already known."""
        bits = self.bits

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            part = TaskContext.get().partitionId()
            shared = [unpack5(r["keys"]) | (r["bucket"] << (KEY_BITS + 1)) for r in side_blobs(keys_at, part)]
            shared = np.sort(np.concatenate(shared)) if shared else np.zeros(0, np.int64)
            shared, often = shared >> 1, (shared & 1).astype(bool)
            z = zstandard.ZstdCompressor(level=1)
            seen: dict[bytes, int] = {}
            owner, places, hashes, marks, n_rows, crc = [], [], [], [], 0, 0

            def ship() -> Iterator[pa.RecordBatch]:
                out = []
                if marks:
                    m = np.array(marks, np.int64)
                    out.append((part % (1 << bits), part, 1, marks_blob(m[:, 0], m[:, 1], m[:, 2])))
                if owner:
                    texts, doc = list(seen), np.array(owner, np.int64)
                    which = np.repeat(np.arange(len(texts)), [len(x) for x in hashes])  # one that is often met goes to two ranges
                    hs = np.array([x for own in hashes for x in own], np.uint64)
                    bucket = (hs >> np.uint64(64 - bits)).astype(np.int64)
                    order = np.argsort(bucket, kind="stable")
                    for group in np.split(order, np.flatnonzero(np.diff(bucket[order])) + 1):
                        own = which[group].tolist()
                        some, at = [texts[g] for g in own], [places[g] for g in own]
                        flat = np.array([x for p in at for x in p], "<i4")
                        arrays = [np.array([len(group), len(flat)], "<i8"), hs[group].astype("<u8"), doc[own].astype("<i8"), np.array([len(s) for s in some], "<i4"), np.array([len(p) for p in at], "<i4"), np.ascontiguousarray(flat.T)]
                        out.append((int(bucket[group[0]]), part, 0, z.compress(b"".join([*(x.tobytes() for x in arrays), *some]))))
                for held in (seen, owner, places, hashes, marks):
                    held.clear()
                for k in range(0, len(out), 64):
                    cols = list(zip(*out[k : k + 64]))
                    yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.int32()), pa.array(cols[3], pa.binary())], ["bucket", "part", "kind", "blob"])

            for row, buf, ends, (doc_ids,), offset in blocks(batches, "text", ["id"]):
                n_rows, crc = row + len(doc_ids), crc if offset else ids_crc(pa.array(doc_ids, pa.int64()), crc)
                doc_ids = [LAST if d is None else d for d in doc_ids]
                if not len(shared):
                    continue
                h, t, first, last, place = anchors(buf, ends)
                k = keyed(h, bits)
                at = np.minimum(np.searchsorted(shared, k), len(shared) - 1)
                i = np.flatnonzero(shared[at] == k)
                begins = np.concatenate([[0], ends[:-1]]) - offset
                for hh, r, a, e, b, p, many in zip(h[i].tolist(), t[i].tolist(), first[i].tolist(), (last[i] + LENGTH).tolist(), begins[t[i]].tolist(), place[i].tolist(), often[at[i]].tolist()):
                    s, d = buf[a:e], doc_ids[r]
                    had = seen.get(s)
                    if had is None:
                        seen[s] = len(owner)
                        owner.append(d)
                        places.append([(row + r, a - b)])
                        hashes.append(sides(hh, buf, a, e, p) if many else (hh,))
                    elif d > owner[had]:
                        marks.append((row + r, a - b, e - b))
                    elif d == owner[had]:
                        places[had].append((row + r, a - b))
                    else:
                        marks += [(q, x, x + e - a) for q, x in places[had]]
                        owner[had], places[had] = d, [(row + r, a - b)]
                if len(owner) >= HELD or len(marks) >= 8 * HELD:
                    yield from ship()
            yield from ship()
            meta = z.compress(np.array([[n_rows], [crc >> 16], [crc & 0xFFFF]], "<i4").tobytes())
            yield pa.RecordBatch.from_arrays([pa.array([part % (1 << bits)], pa.int32()), pa.array([part], pa.int32()), pa.array([2], pa.int32()), pa.array([meta], pa.binary())], ["bucket", "part", "kind", "blob"])

        return self._read().mapInArrow(run, "bucket int, part int, kind int, blob binary")

    @staticmethod
    def settle(pdf: pd.DataFrame) -> pd.DataFrame:
        """One hash range: marks of all its stretches, by slice."""
        out = [(p, k, b) for p, k, b in zip(pdf["part"], pdf["kind"], pdf["blob"]) if k]
        classes: dict[tuple[int, bytes], int] = {}
        cls, part, doc, row, at, hashed, texts = [], [], [], [], [], [], []
        for p, k, blob in zip(pdf["part"], pdf["kind"], pdf["blob"]):
            if k:
                continue
            raw = zstandard.ZstdDecompressor().decompress(blob)
            n, m = np.frombuffer(raw, "<i8", 2).tolist()
            h, d = np.frombuffer(raw, "<u8", n, 16), np.frombuffer(raw, "<i8", n, 16 + 8 * n)
            size, times = np.frombuffer(raw, "<i4", 2 * n, 16 + 16 * n).reshape(2, n)
            r, a = np.frombuffer(raw, "<i4", 2 * m, 16 + 24 * n).reshape(2, m)
            ends = np.cumsum(size, dtype=np.int64) + 16 + 24 * n + 8 * m
            own = []
            for e, s, hh in zip(ends.tolist(), size.tolist(), h.tolist()):
                t = raw[e - s : e]
                c = classes.get((hh, t))
                if c is None:
                    c = classes[hh, t] = len(texts)
                    texts.append(t)
                    hashed.append(hh)
                own.append(c)
            cls.append(np.repeat(np.array(own, np.int64), times))
            part.append(np.full(m, p))
            doc.append(np.repeat(d, times))
            row.append(r)
            at.append(a)
        if texts:
            cls, part, doc, row, at = map(np.concatenate, (cls, part, doc, row, at))
            least = np.full(len(texts), LAST, np.int64)
            np.minimum.at(least, cls, doc)
            size = np.array([len(t) for t in texts])
            later = doc > least[cls]
            marks = [np.stack([part[later], row[later], at[later], at[later] + size[cls[later]]])]
            _, group, count = np.unique(np.array(hashed, np.uint64), return_inverse=True, return_counts=True)
            several = np.flatnonzero(count[group] > 1)
            if len(several):
                lead = np.flatnonzero(~later)  # the records of each stretch's least document
                lead = lead[np.argsort(cls[lead], kind="stable")]
                begin = np.searchsorted(cls[lead], np.arange(len(texts) + 1))
                several = several[np.argsort(group[several], kind="stable")]  # equal strings have one anchor: arrays may part between anchors
                upto, new = np.cumsum(size[several]), np.diff(group[several], prepend=-1) != 0
                piece, last = np.zeros(len(several), np.int64), 0
                for k in np.flatnonzero(new)[1:]:
                    if upto[k] - last > ARRAY:
                        piece[k:] += 1
                        last = upto[k - 1]
                for some in np.split(several, np.flatnonzero(np.diff(piece)) + 1):
                    found = owned_by_smaller([texts[c] for c in some], least[some])
                    more = [(part[i], row[i], at[i] + a, at[i] + z + LENGTH) for s, a, z in found for i in lead[begin[some[s]] : begin[some[s] + 1]]]
                    if more:
                        marks.append(np.array(more, np.int64).T)
            p, r, a, z = np.concatenate(marks, axis=1)
            order = np.argsort(p, kind="stable")
            cuts = np.flatnonzero(np.diff(p[order])) + 1
            out += [(int(p[g[0]]), 1, marks_blob(r[g], a[g], z[g])) for g in np.split(order, cuts) if len(g)]
        return pd.DataFrame(out, columns=["part", "kind", "blob"])

    def marks(self) -> str:
        """Folder of the marks, by slice."""
        keys_at, marks_at = f"{self.folder}/keys", f"{self.folder}/marks"
        self.shared_keys().repartition(self.parts, "part").write.partitionBy("part").parquet(keys_at)
        settled = self.stretches(keys_at).groupBy("bucket").applyInPandas(SuffixDedup.settle, "part int, kind int, blob binary")
        settled.repartition(self.parts, "part").write.partitionBy("part").parquet(marks_at)
        return marks_at

    @staticmethod
    def ranges(marks_at: str, part: int) -> tuple[dict[int, list[tuple[int, int]]], tuple[int, int] | None]:
        """Removed byte ranges by row, merged, and the number and check of the rows that the slice had."""
        held, had = [np.zeros((3, 0), np.int64)], None
        for r in side_blobs(marks_at, part):
            m = read_marks(r["blob"]).astype(np.int64)
            if r["kind"] == 2:
                had = int(m[0, 0]), int(m[1, 0]) << 16 | int(m[2, 0])
            else:
                held.append(m)
        m = read_marks(marks_blob(*np.concatenate(held, axis=1)))
        out: dict[int, list[tuple[int, int]]] = {}
        for row, a, z in m.T.tolist():
            out.setdefault(row, []).append((a, z))
        return out, had

    @staticmethod
    def check(part: int, had: tuple[int, int] | None, rows: int, crc: int) -> None:
        if had not in (None, (rows, crc)):
            raise ValueError(f"slice {part} holds other rows now ({rows}) than before ({had[0]})")

    def digests(self) -> DataFrame:
        """(id, n_bytes, n_removed, n_spans, kept_sha256) for every row."""
        marks_at = self.marks()

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            part, row, crc = TaskContext.get().partitionId(), 0, 0
            gone, had = SuffixDedup.ranges(marks_at, part)
            for b in batches:
                out, crc = [], ids_crc(b.column("id"), crc)
                for t in b.column("text").cast(pa.binary()).to_pylist():
                    t, spans = t or b"", gone.get(row, ())
                    row += 1
                    out.append((len(t), sum(z - a for a, z in spans), len(spans), hashlib.sha256(without(t, spans)).hexdigest()))
                cols = list(zip(*out)) or [()] * 4
                yield pa.RecordBatch.from_arrays([b.column("id"), *(pa.array(c, pa.int64()) for c in cols[:3]), pa.array(cols[3], pa.string())], ["id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])
            SuffixDedup.check(part, had, row, crc)

        read = self._read().mapInArrow(run, "id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")
        return read.withColumnRenamed("id", self.id_col)

    def cut_texts(self, n_chars: str | None = "n_chars") -> DataFrame:
        """The input, all columns and rows, with texts cut; half characters at cuts go, n_chars follows if there."""
        marks_at, id_col, text, schema = self.marks(), self.id_col, self.text, self.docs.schema
        n_chars = n_chars if n_chars in self.docs.columns else None

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            part, row, crc = TaskContext.get().partitionId(), 0, 0
            gone, had = SuffixDedup.ranges(marks_at, part)
            for b in batches:
                crc = ids_crc(b.column(id_col), crc)
                texts, sizes = b.column(text).to_pylist(), b.column(n_chars).to_pylist() if n_chars else None
                for k in range(len(texts)):
                    if spans := gone.get(row + k):
                        texts[k] = without(texts[k].encode(), spans).decode("utf-8", "ignore")
                        if sizes:
                            sizes[k] = len(texts[k])
                row += len(texts)
                new = {text: texts} | ({n_chars: sizes} if n_chars else {})
                yield pa.RecordBatch.from_arrays([pa.array(new[c], b.column(c).type) if c in new else b.column(c) for c in b.schema.names], b.schema.names)
            SuffixDedup.check(part, had, row, crc)

        return self.docs.mapInArrow(run, schema)


def without(t: bytes, spans) -> bytes:
    if not spans:
        return t
    edges = [0, *(x for s in spans for x in s), len(t)]
    return b"".join(t[a:z] for a, z in zip(edges[::2], edges[1::2]))


def passage_digests(docs: DataFrame, id_col: str = "doc_id", text: str = "text", folder: str | None = None) -> DataFrame:
    """(id, n_bytes, n_removed, n_spans, kept_sha256) for every row.

    A byte goes if a LENGTH-byte string over it also starts in a document of a smaller id; all is judged on the input. Null
    texts are empty; a null id comes after all others; rows of one id don't remove each other's bytes; texts under LENGTH bytes stay;
    an empty table gives no rows. Columns besides id and text are not read.
    """
    return SuffixDedup(docs.select(id_col, text), id_col, text, folder).digests()


def cut_passages(docs: DataFrame, id_col: str = "doc_id", text: str = "text", folder: str | None = None) -> DataFrame:
    """docs, all rows and columns, with the same bytes taken out of the texts; half characters at cuts go.

    Nulls, empty texts, repeated rows and empty tables as in passage_digests; a null text stays null. n_chars, if there,
    follows the text; columns of other names pass through.
    """
    return SuffixDedup(docs, id_col, text, folder).cut_texts()
