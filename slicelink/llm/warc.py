"""WARC archives: a writer with revisit records, and a splittable reader of gzip-member archives.

Each record is a gzip member of its own. Reading tasks take byte ranges: a task looks for the gzip magic in its range,
checks a candidate by inflating its first bytes to a WARC header and the member to its end, and owns the records that
start in its range, also where they end beyond it. Files are reached through pyarrow.fs, by the URI of the shared
folder, so that executors need no common local disk; a lost task writes its file anew under another name, and only
the files named by finished tasks are read.

Defined results: null html is an empty payload; of equal payloads the smallest page_id is the response (a repeated
page_id is written once for each row); an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib

import pyarrow as pa
from pyspark.sql import functions as F

from .common import as_text, fresh_path, ready, slices, table

SPLIT = 8 << 20
MAGIC = b"\x1f\x8b\x08"
VERSION = b"WARC/1."


def _open(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def record(kind: str, record_id: str, uri: str, payload: bytes, length: int, digest: str, refers_to: str | None = None) -> bytes:
    """One uncompressed record; a revisit has the HTTP head only."""
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {length}\r\n\r\n".encode()
    body = head + payload if kind == "response" else head
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{record_id}>", f"WARC-Target-URI: {re.sub(r'[\x00-\x20\x7f]', lambda m: f'%{ord(m[0]):02X}', uri)}", "WARC-Date: 1970-01-01T00:00:00Z", "Content-Type: application/http; msgtype=response", f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {length}"]
    if refers_to is not None:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    lines.append(f"Content-Length: {len(body)}")
    return ("\r\n".join(lines) + "\r\n\r\n").encode() + body + b"\r\n\r\n"


def write_archives(pages, where: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", level: int = 4, least: int = 0):
    """Write one archive per task under `where`; returns its (path, bytes, records) list, a row for each task.

    Payloads of at least `least` bytes that equal another's become revisits of the one with the smallest id.
    """
    ready(pages.sparkSession)
    rows = pages.select(pages[id_col].cast("long").alias("i"), pages[url_col].alias("u"), F.coalesce(pages[html_col], F.lit("")).alias("h"))
    rows = rows.withColumn("d", F.sha1(F.col("h").cast("binary")))
    long = F.octet_length("h") >= least
    first = rows.where(long).groupBy("d").agg(F.min("i").alias("r"), F.count("*").alias("n")).where("n > 1").select(F.col("d").alias("e"), "r")
    rows = rows.join(first, long & (F.col("d") == F.col("e")), "left").select("i", "u", "h", F.when(F.col("r") < F.col("i"), F.col("r")).alias("r"))

    def run(batches):
        fs, top = _open(where)
        fs.create_dir(top, recursive=True)
        path, size, records = f"{top}/part-{uuid.uuid4().hex}.warc.gz", 0, 0
        with fs.open_output_stream(path, compression=None) as out:
            for part in slices(batches, "h"):
                for i, u, h, r in zip(part.column(0).to_pylist(), as_text(part.column(1)).to_pylist(), part.column(2).to_pylist(), part.column(3).to_pylist(), strict=True):
                    data = h.encode()
                    digest = base64.b32encode(hashlib.sha1(data).digest()).decode()
                    packer = zlib.compressobj(level, zlib.DEFLATED, 31)
                    made = packer.compress(record("response" if r is None else "revisit", str(i), u, data, len(data), digest, None if r is None else str(r))) + packer.flush()
                    out.write(made)
                    size, records = size + len(made), records + 1
        yield pa.RecordBatch.from_pydict({"path": [path], "bytes": [size], "records": [records]})

    return rows.mapInArrow(run, "path string, bytes long, records long").collect()


class Source:
    """Reads a file on, from any place, in blocks."""

    def __init__(self, file, block: int = 1 << 20):
        self.file, self.block, self.data, self.begin, self.size = file, block, b"", 0, file.size()

    def at(self, begin: int, n: int) -> bytes:
        """Up to n bytes from begin; fewer only at the file's end."""
        have = begin - self.begin
        if not 0 <= have <= len(self.data) or len(self.data) - have < n:
            self.file.seek(begin)
            self.data, self.begin, have = self.file.read(max(n, self.block)), begin, 0
        return self.data[have : have + n]


def member(source: Source, at: int, most: int = 1 << 16) -> tuple[bytes, int] | None:
    """The record of the gzip member at a place, and the member's end; None if none is there."""
    unpack, out, pos, seen = zlib.decompressobj(31), [], at, 0
    try:
        while not unpack.eof:
            block = source.at(pos, most)
            if not block:
                return None
            out.append(unpack.decompress(block))
            pos += len(block)
            seen += len(out[-1])
            if seen >= len(VERSION) and not b"".join(out[:2])[: len(VERSION)].startswith(VERSION) and not b"".join(out).startswith(VERSION):
                return None
    except zlib.error:
        return None
    whole = b"".join(out)
    return (whole, pos - len(unpack.unused_data)) if whole.startswith(VERSION) else None


def records(source: Source, begin: int, end: int):
    """(offset, record) of each record that starts in [begin, end)."""
    at, end = begin, min(end, source.size)
    while at < end:
        block = source.at(at, min(1 << 16, end - at) + len(MAGIC) - 1)
        found = block.find(MAGIC)
        if found < 0:
            at += max(1, len(block) - len(MAGIC) + 1)
            continue
        at += found
        if at >= end:
            return
        got = member(source, at)
        if got is None:
            at += 1
            continue
        yield at, got[0]
        at = got[1]


def parse(data: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields (lower-case names) and the payload behind the HTTP head."""
    head, _, rest = data.partition(b"\r\n\r\n")
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in head.decode("utf-8", "replace").split("\r\n")[1:])}
    body = rest[: int(fields.get("content-length", len(rest)))]
    return fields, body.partition(b"\r\n\r\n")[2]


RECORDS = "path string, record_offset long, record_type string, record_id string, refers_to_id string, target_uri string, payload binary, payload_bytes long, payload_digest string"


def read_archives(spark, files: list[tuple[str, int]], root: str, split: int = SPLIT):
    """One row per record (RECORDS) of archives given as (path, bytes); root: a URI of their file system."""
    ready(spark)
    names = spark.createDataFrame([(p, n) for p, n, *_ in files], "path string, bytes long")
    ranges = names.where("bytes > 0").select("path", F.explode(F.sequence(F.lit(0), F.expr("bytes - 1"), F.lit(split))).alias("begin"))

    def run(batches):
        fs, _ = _open(root)
        for batch in batches:
            for path, begin in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows, held = [], 0
                with fs.open_input_file(path) as file:
                    for at, data in records(Source(file), begin, begin + split):
                        f, payload = parse(data)
                        full = f.get("warc-type") != "revisit"
                        digest = base64.b32encode(hashlib.sha1(payload).digest()).decode() if full else f.get("warc-payload-digest", "").removeprefix("sha1:")
                        ids = [f[k].removeprefix("<urn:page:").removesuffix(">") if k in f else None for k in ("warc-record-id", "warc-refers-to")]
                        rows.append((path, at, f.get("warc-type"), *ids, f.get("warc-target-uri"), payload, len(payload) if full else int(f.get("x-payload-length", 0)), digest))
                        held += len(payload)
                        if held > 4 << 20:
                            yield _batch(rows)
                            rows, held = [], 0
                if rows:
                    yield _batch(rows)

    n = max(1, min(4096, sum(x[1] for x in files) // split + 1))
    return ranges.repartition(n).mapInArrow(run, RECORDS)


def _batch(rows):
    kinds = {"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}
    fields = [x.split() for x in RECORDS.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(x, kinds[k]) for x, (_, k) in zip(zip(*rows, strict=True), fields, strict=True)], names=[n for n, _ in fields])


def op5_warc(spark, sf_dir):
    where = fresh_path(spark, "warc")
    where = where if "://" in where else "file://" + where.removeprefix("file:")
    files = write_archives(table(spark, sf_dir, "pages"), where)
    got = read_archives(spark, [(x.path, x.bytes) for x in files], where, SPLIT)
    return got.select(F.col("record_id").cast("long").alias("page_id"), "payload_bytes", "payload_digest", "record_type", F.col("refers_to_id").cast("long").alias("refers_to"))


#: refers_to and record_type by SQL; DuckDB has no base32, so the digest is put together from the SHA-1's bits.
OP5_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
d AS (SELECT page_id, octet_length(encode(h)) AS payload_bytes, sha1(h) AS x, min(page_id) OVER (PARTITION BY h) AS first FROM p),
bits AS (SELECT page_id, list_aggregate(list_transform(range(0, 40), lambda i: ('x' || substr(x, i + 1, 1))::BIT::VARCHAR), 'string_agg', '') AS b FROM d)
SELECT d.page_id, d.payload_bytes,
  list_aggregate(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + (substr(b, 5 * i + 1, 5)::BIT::INT), 1)), 'string_agg', '') AS payload_digest,
  CASE WHEN first = d.page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN first = d.page_id THEN NULL ELSE first END AS refers_to
FROM d JOIN bits USING (page_id)
"""
