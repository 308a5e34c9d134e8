"""WARC archives: deduplicating writer, monolithic-gzip normaliser with a sidecar index, and reader.

The writer makes one gzip stream a partition (the monolithic form many crawls have). The normaliser inflates
such a stream once, front to back, writes every record again as a gzip member of its own, and puts the
members' offsets in a sidecar file; the reader then fetches any record by one seek.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh_dir, n_partitions, open_input, written_once

MIN_REVISIT = 1000
END = b"\r\n\r\n"
FILES = "archive string, n_records long"


def decisions(pages: DataFrame, id_col: str = "page_id", body: str = "html", min_bytes: int = MIN_REVISIT) -> DataFrame:
    """pages' (id, url, body) with digest, record_type and refers_to; the body itself moves once, by id.

    Equal bodies of min_bytes or more: those with the largest id are responses, the rest revisit it. Only
    digests are grouped, so a group of copies of any size is one partial sum a task.
    """
    p = pages.select(F.col(id_col).alias("id"), F.col("url"), F.coalesce(F.col(body), F.lit("")).alias("body")).withColumn("digest", F.sha1("body"))
    narrow = p.where(F.octet_length("body") >= min_bytes).select("id", "digest")
    leaders = narrow.groupBy("digest").agg(F.max("id").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
    revisits = narrow.join(leaders, "digest").where("not (id <=> first)").distinct()
    on = F.col("p.id").eqNullSafe(F.col("r.id")) & (F.col("p.digest") == F.col("r.digest"))
    return p.alias("p").join(revisits.alias("r"), on, "left").select("p.id", "p.url", "p.body", "p.digest", F.when(F.col("r.digest").isNull(), "response").otherwise("revisit").alias("record_type"), F.col("r.first").alias("refers_to"))


def one_line(value: str | None) -> str:
    """A header value: controls, blanks and per cents are percent-coded, so that any url comes back whole."""
    return re.sub(r"[\x00-\x20%\x7f]", lambda m: f"%{ord(m[0]):02X}", value or "")


def record(id_, url, body: bytes, digest: str, kind: str, refers) -> bytes:
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(body)}\r\n\r\n".encode()
    block = http + (body if kind == "response" else b"")
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{'' if id_ is None else id_}>", "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Target-URI: {one_line(url)}", f"WARC-Payload-Digest: sha1:{digest}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}",
    ]
    if kind == "revisit":
        head += [f"WARC-Refers-To: <urn:page:{refers}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    return "\r\n".join(head).encode() + END + block + END


def write_monolithic(decided: DataFrame, folder: str) -> DataFrame:
    """One gzip stream a partition; (archive, n_records). The files are written when the result is read."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, n = f"{folder}/whole-{TaskContext.get().partitionId():06d}.warc.gz", 0
        with written_once(at) as out:
            z = zlib.compressobj(1, zlib.DEFLATED, 31)
            for b in batches:
                cols = [b.column(c).to_pylist() for c in ("id", "url")] + [b.column("body").cast(pa.binary()).to_pylist()] + [b.column(c).to_pylist() for c in ("digest", "record_type", "refers_to")]
                for row in zip(*cols):
                    out.write(z.compress(record(*row)))
                    n += 1
            out.write(z.flush())
        yield pa.RecordBatch.from_pydict({"archive": [at], "n_records": pa.array([n], pa.int64())})

    return decided.mapInArrow(run, FILES)


def records_in(stream, size: int = 1 << 20) -> Iterator[bytes]:
    """The records of an inflated stream, in order; holds one record and one chunk at a time."""
    z, held = zlib.decompressobj(31), bytearray()
    need = None
    while True:
        while True:
            if need is None and (k := held.find(END)) >= 0:
                m = re.search(rb"(?im)^content-length:\s*(\d+)", bytes(held[:k]))
                if not held.startswith(b"WARC/") or not m:
                    raise ValueError("not a WARC record")
                need = k + 4 + int(m[1]) + 4
            if need is None or len(held) < need:
                break
            yield bytes(held[:need])
            del held[:need]
            need = None
        chunk = stream.read(size)
        if not chunk:
            break
        while chunk:
            held += z.decompress(chunk)
            chunk = z.unused_data  # further members of a file that has some
            if z.eof:
                z = zlib.decompressobj(31)
    if held:
        raise ValueError("the archive ends within a record")


def normalise(files: DataFrame, folder: str, level: int = 6) -> DataFrame:
    """Every archive again with a member for each record, and its sidecar `.idx`; (archive, n_records)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for source, n in zip(b.column("archive").to_pylist(), b.column("n_records").to_pylist()):
                at = f"{folder}/{source.rsplit('/', 1)[-1].replace('whole-', 'members-')}"
                index, offset = [], 0
                with written_once(at) as out, open_input(source) as stream:
                    for r in records_in(stream):
                        z = zlib.compressobj(level, zlib.DEFLATED, 31)
                        member = z.compress(r) + z.flush()
                        out.write(member)
                        index.append((offset, len(member)))
                        offset += len(member)
                if len(index) != n:
                    raise ValueError(f"{source}: {len(index)} records, {n} written")
                with written_once(f"{at}.idx") as out:
                    out.write("".join(f"{o} {s}\n" for o, s in index).encode())
                yield pa.RecordBatch.from_pydict({"archive": [at], "n_records": pa.array([n], pa.int64())})

    return files.mapInArrow(run, FILES)


READ = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary, payload_checked boolean"


def parse(raw: bytes) -> dict:
    head, _, block = raw.partition(END)
    h = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in head.decode().split("\r\n")[1:])}
    block = block[: int(h["content-length"])]
    http, _, payload = block.partition(END)
    number = lambda x: int(m[1]) if (m := re.fullmatch(r"<urn:page:(-?\d+)>", x or "")) else None
    digest = h["warc-payload-digest"].partition(":")[2]
    size = int(re.search(rb"(?i)content-length:\s*(\d+)", http)[1])
    whole = h["warc-type"] == "response"
    url = re.sub(r"%([0-9A-F]{2})", lambda m: chr(int(m[1], 16)), h["warc-target-uri"])
    return {"page_id": number(h["warc-record-id"]), "url": url, "payload_bytes": size, "payload_digest": digest, "record_type": h["warc-type"], "refers_to": number(h.get("warc-refers-to")), "payload": payload if whole else None, "payload_checked": not whole or (len(payload) == size and hashlib.sha1(payload).hexdigest() == digest)}


def read_archives(files: DataFrame, columns: list[str] | None = None) -> DataFrame:
    """Rows of READ from normalised archives, each record found by its offset in the sidecar.

    A response's payload is hashed again; a difference ends the job. columns: those to return.
    """
    kept = [c for c in READ.replace(",", "").split()[::2] if columns is None or c in columns]
    kinds = dict(zip(READ.replace(",", "").split()[::2], READ.replace(",", "").split()[1::2]))
    arrow = {"long": pa.int64(), "string": pa.string(), "binary": pa.binary(), "boolean": pa.bool_()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in b.column("archive").to_pylist():
                with open_input(f"{at}.idx") as f:
                    index = [tuple(map(int, x.split())) for x in f.read().decode().splitlines()]
                with open_input(at) as f:
                    for k in range(0, len(index), 256):
                        rows = []
                        for offset, size in index[k : k + 256]:
                            f.seek(offset)
                            rows.append(parse(zlib.decompress(f.read(size), 31)))
                        if not all(r["payload_checked"] for r in rows):
                            raise ValueError(f"{at}: a payload differs from its digest")
                        yield pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], arrow[kinds[c]]) for c in kept], kept)

    return files.mapInArrow(run, ", ".join(f"{c} {kinds[c]}" for c in kept))


def archive_pages(pages: DataFrame, folder: str | None = None, id_col: str = "page_id", body: str = "html") -> DataFrame:
    """Writes pages' records, normalises the archives and gives the files' (archive, n_records), on disk.

    Null bodies are empty payloads, null urls empty; of repeated rows each gets its record, and all of the
    leading id are responses. An empty table gives archives without records. Other columns are not read.
    """
    spark = pages.sparkSession
    folder = folder or fresh_dir(spark, "warc")
    whole = write_monolithic(decisions(pages, id_col, body), folder)
    whole.write.parquet(f"{folder}/whole.parquet")
    files = spark.read.schema(FILES).parquet(f"{folder}/whole.parquet").repartition(max(n_partitions(spark), 2), "archive")
    normalise(files, folder).write.parquet(f"{folder}/members.parquet")
    return spark.read.schema(FILES).parquet(f"{folder}/members.parquet")


def archive_digest(pages: DataFrame, folder: str | None = None) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to) of every record, read back."""
    files = archive_pages(pages, folder)
    return read_archives(files.repartition(n_partitions(pages.sparkSession), "archive"), ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])
