"""Token ids in bit-plane shuffled files.

A file is a run of chunks. A chunk holds a fixed number of ids as unsigned 32-bit integers, transposed into
planes (32 of bits or 4 of bytes), each plane compressed by zstandard on its own; small ids leave the high planes
all zero, which cost a few bytes. A footer indexes the chunks and the documents, so that any document is read from the chunks it spans.

Layout: magic, chunks, footer (zstandard JSON and arrays), 8-byte footer size, magic.
"""

from __future__ import annotations

import io
import json
import os
import struct
import zlib
from collections.abc import Iterator
from itertools import compress, repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import fresh_dir, n_partitions, open_input, written_once

MAGIC = b"BPLANES1"
CHUNK = 1 << 16
#: White space, as a set of RE2.
WHITE = r"\t-\r\x1c-\x20\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}"
#: A piece may begin at a blank unless both its neighbours are white (or it ends the text): only there do
#: the tokenizer's own pre-tokens cross it.
UNSAFE = f"[{WHITE}] (?:[{WHITE}]|$)"
#: Of a byte: 1 a blank, 2 ASCII other than a letter, 4 an ASCII letter, 8 ASCII that isn't white or the first of two
#: bytes that aren't.
KIND = np.zeros(256, np.uint8)
KIND[:128] = 2 | 8
KIND[[*range(65, 91), *range(97, 123)]] = 4 | 8
KIND[[*range(9, 14), *range(28, 32)]] = 2
KIND[32] = 1
KIND[0xC3:0xE0] = 8
#: Bytes of text that are encoded at a time.
SLICE = 16 << 20


def split_planes(ids: np.ndarray, bits: bool) -> list[bytes]:
    raw = ids.astype("<u4").view(np.uint8).reshape(-1, 4).T
    if not bits:
        return [p.tobytes() for p in raw]
    return [np.packbits((raw[k // 8] >> (k % 8)) & 1).tobytes() for k in range(32)]


def join_planes(planes: list[bytes], n: int, bits: bool) -> np.ndarray:
    raw = np.zeros((4, n), np.uint8)
    for k, p in enumerate(planes):
        if bits:
            raw[k // 8] |= np.unpackbits(np.frombuffer(p, np.uint8), count=n) << (k % 8)
        else:
            raw[k] = np.frombuffer(p, np.uint8)
    return np.ascontiguousarray(raw.T).view("<u4").ravel()


class PlaneWriter:
    """Takes documents' ids in order and writes chunks as they fill; holds one chunk of ids."""

    def __init__(self, out, chunk: int = CHUNK, bits: bool = False, level: int = 3):
        self.out, self.chunk, self.bits, self.z = out, chunk, bits, zstandard.ZstdCompressor(level=level)
        self.held, self.n_held, self.chunks, self.docs, self.at, self.n = [], 0, [], [], len(MAGIC), 0
        out.write(MAGIC)

    def add(self, doc_id, ids: np.ndarray) -> None:
        self.add_all([doc_id], ids, [len(ids)])

    def add_all(self, doc_ids: list, ids: np.ndarray, sizes: list[int]) -> None:
        """Documents in order, their ids end to end."""
        self.docs += zip(doc_ids, sizes)
        self.held.append(ids)
        self.n_held += len(ids)
        self.n += len(ids)
        if self.n_held >= self.chunk:
            joined = np.concatenate(self.held)
            whole = len(joined) - len(joined) % self.chunk
            for k in range(0, whole, self.chunk):
                self._write(joined[k : k + self.chunk])
            self.held, self.n_held = [joined[whole:]], len(joined) - whole

    def _write(self, ids: np.ndarray) -> None:
        planes = [self.z.compress(p) for p in split_planes(ids, self.bits)]
        self.out.write(struct.pack("<I", zlib.crc32(ids.astype("<u4").tobytes())) + struct.pack(f"<{len(planes)}I", *map(len, planes)) + b"".join(planes))
        size = 4 + 4 * len(planes) + sum(map(len, planes))
        self.chunks.append((self.at, len(ids)))
        self.at += size

    def close(self) -> None:
        if self.n_held:
            self._write(np.concatenate(self.held))
        head = json.dumps({"chunk": self.chunk, "bits": self.bits, "n_docs": len(self.docs), "n_chunks": len(self.chunks)}).encode()
        valid = np.array([d is not None for d, _ in self.docs], np.uint8)
        body = b"".join([struct.pack("<I", len(head)), head, valid.tobytes(), np.array([d or 0 for d, _ in self.docs], "<i8").tobytes(), np.array([n for _, n in self.docs], "<i8").tobytes(), np.array(self.chunks, "<i8").tobytes()])
        packed = self.z.compress(body)
        self.out.write(packed + struct.pack("<Q", len(packed)) + MAGIC)


class PlaneReader:
    def __init__(self, f):
        self.f = f
        end = f.seek(0, io.SEEK_END) if not hasattr(f, "size") else f.size()
        f.seek(end - 16)
        size, magic = struct.unpack("<Q8s", f.read(16))
        if magic != MAGIC:
            raise ValueError("not a plane file")
        f.seek(end - 16 - size)
        body = zstandard.ZstdDecompressor().decompress(f.read(size))
        n = struct.unpack("<I", body[:4])[0]
        head = json.loads(body[4 : 4 + n])
        at, d, c = 4 + n, head["n_docs"], head["n_chunks"]
        self.bits, self.chunk = head["bits"], head["chunk"]
        valid = np.frombuffer(body, np.uint8, d, at)
        ids = np.frombuffer(body, "<i8", d, at + d)
        self.doc_ids = [int(i) if v else None for i, v in zip(ids, valid)]
        self.lengths = np.frombuffer(body, "<i8", d, at + 9 * d)
        self.chunks = np.frombuffer(body, "<i8", 2 * c, at + 17 * d).reshape(-1, 2)
        self.starts = np.concatenate([[0], np.cumsum(self.lengths)])

    def read_chunk(self, k: int) -> np.ndarray:
        at, n = map(int, self.chunks[k])
        planes = 32 if self.bits else 4
        self.f.seek(at)
        head = self.f.read(4 + 4 * planes)
        sizes = struct.unpack(f"<{planes}I", head[4:])
        z = zstandard.ZstdDecompressor()
        ids = join_planes([z.decompress(self.f.read(s), max_output_size=n) for s in sizes], n, self.bits)
        if zlib.crc32(ids.tobytes()) != struct.unpack("<I", head[:4])[0]:
            raise ValueError(f"chunk {k} is damaged")
        return ids

    def document(self, k: int) -> np.ndarray:
        """Ids of the k-th document, from the chunks it spans alone."""
        a, b = int(self.starts[k]), int(self.starts[k + 1])
        parts = [self.read_chunk(c) for c in range(a // self.chunk, -(-b // self.chunk))]
        return np.concatenate(parts or [np.zeros(0, np.uint32)])[a % self.chunk :][: b - a]

    def __iter__(self) -> Iterator[tuple[int | None, np.ndarray]]:
        """Documents in order; every chunk is read once."""
        held, first, k = np.zeros(0, np.uint32), 0, 0
        for d, doc_id in enumerate(self.doc_ids):
            a, b = int(self.starts[d]), int(self.starts[d + 1])
            parts = [held[a - first :]]
            have = first + len(held)
            while have < b:
                parts.append(self.read_chunk(k))
                have += len(parts[-1])
                k += 1
            held, first = np.concatenate(parts) if len(parts) > 1 else parts[0], a
            yield doc_id, held[: b - a]


class Encoder:
    """Whole texts to ids; the pieces between safe cuts are looked up or given to the tokenizer, many in one text.

    Equal to encoding the whole text at once. Only a byte-level vocabulary with the usual pattern (`splits_at_blanks`)
    is handled by pieces, for there no token crosses a safe cut, and the bytes of each id tell where a piece ends; with
    any other, and where a text has blanks that pre-tokens could cross or what may be a special token, whole texts go
    to the tokenizer. Pieces found are kept, `most` of them at most.
    """

    def __init__(self, path: str, most: int = 1_200_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.t, self.most = Tokenizer.from_file(path), most
        self.special = [a.content for a in self.t.get_added_tokens_decoder().values()]
        self.by_pieces = len(self.special) <= 16 and splits_at_blanks(json.loads(self.t.to_str()))
        if self.by_pieces:
            vocab = self.t.get_vocab()
            self.n_bytes = np.zeros(max(vocab.values()) + 1, np.int64)
            self.n_bytes[list(vocab.values())] = list(map(len, vocab))  # the alphabet has a sign for each byte
        self._forget()

    def _forget(self) -> None:
        self.known: dict[bytes, int] = {}  # a piece's place in begin; ids[begin[k]:begin[k + 1]] are its ids
        self.begin, self.ids = np.zeros(1 << 16, np.int64), np.zeros(1 << 18, np.uint32)

    def _whole(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        own = [np.array(e.ids, np.uint32) for e in self.t.encode_batch_fast(texts, add_special_tokens=False)]
        return np.concatenate([np.zeros(0, np.uint32), *own]), np.array([len(x) for x in own], np.int64)

    def _joined(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of pieces end to end and how many each has; pre-tokens cross no edge where all are `joinable`."""
        ids = np.array(self.t.encode_batch_fast([b"".join(pieces).decode()], add_special_tokens=False)[0].ids, np.uint32)
        ends, at = np.cumsum(np.fromiter(map(len, pieces), np.int64, len(pieces))), np.cumsum(self.n_bytes[ids])
        upto = np.searchsorted(at, ends) + 1
        if len(at) and upto[-1] == len(at) and np.array_equal(at[upto - 1], ends):
            return ids, np.diff(upto, prepend=0)
        return self._whole([p.decode() for p in pieces])  # some byte has no id

    def _learn(self, new: list[bytes]) -> None:
        fits = joinable(new)
        joint, rest = list(compress(new, fits)), list(compress(new, ~fits))
        found = [(self._joined(some), some) for some in (joint[k : k + 16384] for k in range(0, len(joint), 16384))]
        found.append((self._whole([p.decode() for p in rest]), rest))
        for (ids, sizes), some in found:
            n, at = len(self.known), int(self.begin[len(self.known)])
            while len(self.begin) <= n + len(some):
                self.begin = np.concatenate([self.begin, np.zeros_like(self.begin)])
            while len(self.ids) < at + len(ids):
                self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
            self.begin[n + 1 : n + 1 + len(some)] = at + np.cumsum(sizes)
            self.ids[at : at + len(ids)] = ids
            self.known.update(zip(some, range(n, n + len(some))))

    def _places(self, pieces: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.known.get, pieces, repeat(-1)), np.int64, len(pieces))

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids end to end, and the number of each text's."""
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        if not self.by_pieces:
            return self._whole(texts.to_pylist())
        odd = pc.match_substring_regex(texts, UNSAFE)
        for name in self.special:
            odd = pc.or_(odd, pc.match_substring(texts, name))
        odd = odd.to_numpy(zero_copy_only=False)
        if not odd.any():
            return self._by_pieces(texts)
        parts = [(odd, *self._whole(texts.filter(pa.array(odd)).to_pylist())), (~odd, *self._by_pieces(texts.filter(pa.array(~odd))))]
        sizes = np.zeros(len(texts), np.int64)
        for some, _, own in parts:
            sizes[some] = own
        ids, which = np.zeros(sizes.sum(), np.uint32), np.repeat(odd, sizes)
        for (_, own, _), there in zip(parts, (which, ~which)):
            ids[there] = own
        return ids, sizes

    def _by_pieces(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        text, at = text_bytes(texts)
        starts = np.flatnonzero(safe_cuts(text, at))
        offsets = np.concatenate([starts, [len(text)]]) if len(text) else np.zeros(1, np.int64)
        coded = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(offsets), pa.py_buffer(text)]).dictionary_encode()
        if len(self.known) > self.most:
            self._forget()
        pieces = coded.dictionary.to_numpy(zero_copy_only=False).tolist()
        place = self._places(pieces)
        if len(lacking := np.flatnonzero(place < 0)):
            new = list(map(pieces.__getitem__, lacking))
            self._learn(new)
            place[lacking] = self._places(new)
        table = pa.LargeListArray.from_arrays(self.begin[: len(self.known) + 1], self.ids)
        found = table.take(pa.array(place).take(coded.indices))
        upto = found.offsets.to_numpy()
        return found.flatten().to_numpy(), np.diff(upto[np.searchsorted(starts, at)] - upto[0])


def text_bytes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a large_string array without nulls, end to end, and where each text begins (and the last ends)."""
    _, offsets, data = texts.buffers()
    at = np.frombuffer(offsets, np.int64, len(texts) + 1, 8 * texts.offset) if len(texts) else np.zeros(1, np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[at[0] : at[-1]], at - at[0]


def safe_cuts(text: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Where pieces begin: texts (at), blanks, a line's end after a sign that isn't white, and the end of a run of letters (ASCII alone)."""
    kind = KIND[text]
    cut = kind == 1
    cut[1:] |= ((kind[1:] & 2) != 0) & ((kind[:-1] & 4) != 0)  # a letter, then another ASCII sign
    cut[1:] |= (text[1:] == 10) & ((kind[:-1] & 8) != 0)
    cut[at[:-1][at[:-1] < len(text)]] = True
    return cut


def joinable(pieces: list[bytes]) -> np.ndarray:
    """Whether each begins with a blank or a line's end, no white after it, and doesn't end in white: in a text of such
    pieces pre-tokens cross no edge."""
    size, text = np.fromiter(map(len, pieces), np.int64, len(pieces)), np.frombuffer(b"".join(pieces) + b" ", np.uint8)
    first = np.cumsum(size) - size
    last, solid = first + size - 1, KIND[text] & 8 != 0
    ends = solid[last] | (text[last] >= 0x80) & (text[last] < 0xC0) & (text[last - 1] >= 0xC3) & (text[last - 1] < 0xE0)
    return (size > 1) & ((text[first] == 32) | (text[first] == 10)) & solid[first + 1] & ends


def splits_at_blanks(spec: dict) -> bool:
    """Whether a tokenizer (its JSON) is byte-level with the usual pattern, where no token crosses a safe blank."""
    before, model = spec.get("pre_tokenizer") or {}, spec.get("model") or {}
    plain = not any(spec.get(k) for k in ("normalizer", "truncation", "padding"))
    byte_level = before.get("type") == "ByteLevel" and before.get("use_regex", True) and not before.get("add_prefix_space")
    fixed = model.get("type") == "BPE" and not any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback"))
    return bool(plain and byte_level and fixed)


_ENCODERS: dict[str, Encoder] = {}


def encoder_for(path: str) -> Encoder:
    """One encoder a worker and vocabulary: the pieces it knows outlive a task."""
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


def by_bytes(batch: pa.RecordBatch, column: str, most: int) -> Iterator[pa.RecordBatch]:
    """Slices of whole rows with at most `most` bytes in a column; a longer row is a slice of its own."""
    size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    first = 0
    while first < batch.num_rows:
        last = int(np.searchsorted(size, (size[first - 1] if first else 0) + most, "right"))
        last = max(last, first + 1)
        yield batch.slice(first, last - first)
        first = last


FILES = "part int, file string, n_docs long, n_tokens long"


def write_tokens(docs: DataFrame, folder: str, tokenizer: str, end_id: int = 0, id_col: str = "doc_id", text: str = "text", parts: int | None = None, bits: bool = False, chunk: int = CHUNK) -> DataFrame:
    """Writes every text's ids and end_id, in ascending id order, to plane files; their (part, file, n_docs, n_tokens).

    The order runs through the files by part: rows are range-partitioned by id and each slice is one file.
    Null texts are empty, null ids come first, and repeated rows are written each time (ties in any order); an empty table gives files
    without documents or none. tokenizer is the path of a vocabulary file on every executor.
    """
    spark = docs.sparkSession

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, encoder = TaskContext.get().partitionId(), encoder_for(tokenizer)
        at = f"{folder}/tokens-{part:06d}.planes"
        with written_once(at) as out:
            w = PlaneWriter(out, chunk, bits)
            for b in batches:
                for some in by_bytes(b, "text", SLICE):
                    ids, sizes = encoder.encode(some.column("text"))
                    w.add_all(some.column("id").to_pylist(), np.insert(ids, np.cumsum(sizes), end_id), (sizes + 1).tolist())
            w.close()
        yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "file": [at], "n_docs": pa.array([len(w.docs)], pa.int64()), "n_tokens": pa.array([w.n], pa.int64())})

    read = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text).alias("text"))
    parts = parts or n_partitions(spark)
    read.repartitionByRange(parts, "id").sortWithinPartitions("id").mapInArrow(run, FILES).write.parquet(f"{folder}/files.parquet")
    return spark.read.schema(FILES).parquet(f"{folder}/files.parquet")


def read_digests(files: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, start, n_tokens, ids_crc32) of every document in the files; start counts all ids before it.

    Only the list of files, a row each, passes through one window.
    """
    spark = files.sparkSession
    bases = files.select("file", F.coalesce(F.sum("n_tokens").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("base"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at, base in zip(b.column("file").to_pylist(), b.column("base").to_pylist()):
                with open_input(at) as f:
                    r = PlaneReader(f)
                    crc = [zlib.crc32(ids.astype("<u4").tobytes()) for _, ids in r]
                    yield pa.RecordBatch.from_pydict({"doc_id": pa.array(r.doc_ids, pa.int64()), "start": pa.array(base + r.starts[:-1], pa.int64()), "n_tokens": pa.array(r.lengths, pa.int64()), "ids_crc32": pa.array(crc, pa.int64())})

    read = bases.repartition(2 * n_partitions(spark), "file").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")
    return read.withColumnRenamed("doc_id", id_col)


def token_digests(docs: DataFrame, tokenizer: str, folder: str | None = None, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Writes and reads back; see write_tokens and read_digests."""
    folder = folder or fresh_dir(docs.sparkSession, "tokens")
    return read_digests(write_tokens(docs, folder, tokenizer, id_col=id_col, text=text), id_col)
