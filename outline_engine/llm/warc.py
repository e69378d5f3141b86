"""WARC archives of web pages: index-first writing, byte-range reading.

Writing: the record type of every page is settled first on slim rows (id, digest, size), so page
bodies cross the network once.  Each task then writes one archive of gzip members and returns an
index row per record: file, offset, length, URL and digest.  The index is a Parquet table.

Reading: selected index rows are dealt by file and block of the file, sorted by offset, and near
ranges are merged into one read.

Archives are opened with ``pyarrow.fs`` by URI, so any store that it knows will do.  An archive is
written under an attempt's name and then moved to its final name, so a task that runs again
replaces the same file with the same bytes.

Defined cases: null html is an empty payload; null ids are kept and are always responses; equal
rows are all written, those of the smallest id as responses; an empty table gives an empty index.
Line breaks in URLs are percent-encoded in the header, as WARC has no way to fold them.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from urllib.parse import quote, unquote

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from outline_engine.llm.storage import scratch, table

#: Smaller payloads are never revisits: a revisit record would not be smaller.
LEAST_REVISIT = 100
DATE = "2024-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: Ranges no further apart than GAP are read at once, up to about READ bytes.
GAP, READ, BLOCK = 1 << 16, 8 << 20, 64 << 20
INDEX = "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, file string, offset long, length long"
RECORD = "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, payload binary"


def _urn(page) -> str:
    return f"<urn:x-page:{'none' if page is None else page}>"


def _page(urn: str):
    value = urn[len("<urn:x-page:") : -1]
    return None if value == "none" else int(value)


def record(page, url: str, payload: bytes, digest: str, refers_to) -> bytes:
    """An uncompressed WARC record; a revisit has the response's HTTP header but no payload."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    lines = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {_urn(page)}", f"WARC-Date: {DATE}"]
    if url is not None:
        lines.append("WARC-Target-URI: " + quote(url, safe="".join(map(chr, range(33, 127))).replace("%", "")))
    lines.append(f"WARC-Payload-Digest: sha256:{digest}")
    if refers_to is not None:
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {_urn(refers_to)}"]
    lines += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse(data: bytes) -> dict:
    """The fields of a record that ``record`` made; size and digest are those of the full payload."""
    head, _, rest = data.partition(b"\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    sizes = [int(line.split(b": ")[1]) for line in http.split(b"\r\n") if line.lower().startswith(b"content-length: ")]
    known = fields["WARC-Payload-Digest"].removeprefix("sha256:")
    revisit = fields["WARC-Type"] == "revisit"
    if not revisit and (hashlib.sha256(payload).hexdigest() != known or len(payload) != sizes[0]):
        raise ValueError(f"damaged record {fields['WARC-Record-ID']}")
    url = fields.get("WARC-Target-URI")
    return {
        "page_id": _page(fields["WARC-Record-ID"]),
        "url": None if url is None else unquote(url),
        "record_type": fields["WARC-Type"],
        "refers_to": _page(fields["WARC-Refers-To"]) if revisit else None,
        "payload_bytes": sizes[0],
        "payload_digest": known,
        "payload": None if revisit else payload,
    }


def _gzip(data: bytes) -> bytes:
    press = zlib.compressobj(1, zlib.DEFLATED, 31)
    return press.compress(data) + press.flush()


def write(pages: DataFrame, root: str) -> DataFrame:
    """Write ``pages`` (page_id, url, html) as archives under ``root``; return the stored index."""
    spark = pages.sparkSession
    bodies = pages.select(
        F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).cast("binary").alias("body")
    ).withColumn("digest", F.sha2("body", 256))
    slim = bodies.where(F.octet_length("body") >= LEAST_REVISIT).select("page_id", "digest").where("page_id IS NOT NULL")
    repeated = slim.groupBy("digest").agg(F.min("page_id").alias("first_id"), F.max("page_id").alias("last_id")).where("first_id < last_id").select("digest", "first_id")
    revisits = slim.join(repeated, "digest").where("page_id > first_id").select("page_id", "digest", "first_id").distinct()
    settled = bodies.join(revisits, ["page_id", "digest"], "left").sortWithinPartitions("page_id", "digest", "url")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        task = TaskContext.get()
        store, base = fs.FileSystem.from_uri(root)
        store.create_dir(base, recursive=True)
        name = f"pages-{task.partitionId():06d}.warc.gz"
        part = f"{base}/.{name}.{task.taskAttemptId()}"
        offset, out = 0, None
        for one in batches:
            index = []
            for page, digest, url, body, first in zip(*(one.column(c).to_pylist() for c in ("page_id", "digest", "url", "body", "first_id")), strict=True):
                member = _gzip(record(page, url, body, digest, first))
                out = out or store.open_output_stream(part)
                out.write(member)
                index.append((page, url, "response" if first is None else "revisit", first, len(body), digest, name, offset, len(member)))
                offset += len(member)
            if index:
                yield pa.RecordBatch.from_arrays([pa.array(c, type=t) for c, t in zip(zip(*index, strict=True), kinds, strict=True)], names=names)
        if out:
            out.close()
            store.move(part, f"{base}/{name}")

    names = [f.split()[0] for f in INDEX.split(", ")]
    kinds = [pa.int64() if f.endswith("long") else pa.string() for f in INDEX.split(", ")]
    path = f"{root}/index"
    settled.mapInArrow(run, INDEX).write.parquet(path)
    return spark.read.schema(INDEX).parquet(path)


def ranges(rows: list[tuple[int, int]]) -> list[tuple[int, int, int, int]]:
    """Merge sorted (offset, length) pairs: (first row, past the last row, begin, end) of each read."""
    merged: list[tuple[int, int, int, int]] = []
    for i, (offset, length) in enumerate(rows):
        if merged:
            first, _, begin, end = merged[-1]
            if offset - end <= GAP and offset + length - begin <= READ:
                merged[-1] = (first, i + 1, begin, max(end, offset + length))
                continue
        merged.append((i, i + 1, offset, offset + length))
    return merged


def read(selected: DataFrame, root: str, *, payloads: bool = True) -> DataFrame:
    """The records of the ``selected`` index rows, read from the archives under ``root``."""
    wanted = selected.select("file", "offset", "length").where("file IS NOT NULL")
    # Index rows are small and what they stand for is large, so their number of tasks is not left to their size.
    parts = int(selected.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = wanted.repartition(parts, "file", F.floor(F.col("offset") / BLOCK)).sortWithinPartitions("file", "offset")
    schema = RECORD if payloads else RECORD.rpartition(", ")[0]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyarrow import fs

        store, base = fs.FileSystem.from_uri(root)
        kinds = {"page_id": pa.int64(), "url": pa.string(), "record_type": pa.string(), "refers_to": pa.int64(), "payload_bytes": pa.int64(), "payload_digest": pa.string(), "payload": pa.binary()}
        shown = [f.split()[0] for f in schema.split(", ")]
        opened, handle = None, None
        for one in batches:
            rows = list(zip(*(one.column(c).to_pylist() for c in ("file", "offset", "length")), strict=True))
            at = 0
            while at < len(rows):
                name = rows[at][0]
                end = next((i for i in range(at, len(rows)) if rows[i][0] != name), len(rows))
                own, at = [r[1:] for r in rows[at:end]], end
                if opened != name:
                    if handle:
                        handle.close()
                    opened, handle = name, store.open_input_file(f"{base}/{name}")
                for i, j, begin, stop in ranges(own):
                    block = memoryview(handle.read_at(stop - begin, begin))
                    found = [parse(zlib.decompress(block[o - begin : o - begin + n], 31)) for o, n in own[i:j]]
                    yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in found], type=kinds[k]) for k in shown], names=shown)
        if handle:
            handle.close()

    return dealt.mapInArrow(run, schema)


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    root = scratch(spark, "warc")
    index = write(table(spark, sf_dir, "pages"), root)
    return read(index, root, payloads=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url")


OP8_SQL = """
WITH p AS (
  SELECT page_id, url, coalesce(html, '') AS body, sha256(coalesce(html, '')) AS digest, octet_length(encode(coalesce(html, ''))) AS n FROM pages
), f AS (SELECT digest, min(page_id) AS first_id FROM p GROUP BY digest)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, digest AS payload_digest,
  CASE WHEN n >= 100 AND page_id > first_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN n >= 100 AND page_id > first_id THEN first_id END AS refers_to, url
FROM p JOIN f USING (digest)
"""
