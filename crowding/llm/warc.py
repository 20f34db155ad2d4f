"""WARC writing with revisit records, and reading back.

Headers (page_id, digest, length) are shuffled by digest, where the largest page_id of a payload that is
long enough and occurs more than once is found; the joined result says of each page whether its record
holds the payload or points to the response. Archives are written with fresh headers, one gzip member a record, and
indexed by a manifest; reading goes through the archives the manifest names, so what a lost or retried task
left behind is never seen.

Edge cases: a null html is an empty payload; payloads below the minimum length are always responses; a null
page_id is never the largest while another is there, and a group of nulls alone is all responses; rows that
repeat a page_id with the same payload are alike, so the group's largest id may have several responses; an
empty table gives no archive and no rows; columns other than page_id, url and html are ignored.
"""

from __future__ import annotations

import gzip
import hashlib
import io
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowding.llm.common import open_fs, scratch, settle, slices, table, utf8

MIN_BYTES = 1000
#: An archive is closed after so many compressed bytes.
ROLL = 256 << 20
_NONE = "none"


def resolve(pages: DataFrame, min_bytes: int = MIN_BYTES) -> DataFrame:
    """page_id, url, html, digest, n_bytes, refers_to (null: response)."""
    page = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce("html", F.lit("")).alias("html"))
    page = page.withColumns({"digest": F.sha1("html"), "n_bytes": F.octet_length("html").cast("long")})
    heads = page.select("page_id", "digest", "n_bytes").filter(F.col("n_bytes") >= min_bytes)
    kept = heads.groupBy(F.col("digest").alias("of"), F.col("n_bytes").alias("size")).agg(F.max("page_id").alias("original"), F.count(F.lit(1)).alias("n")).filter("n > 1").drop("n")
    revisits = heads.join(kept, (F.col("digest") == F.col("of")) & (F.col("n_bytes") == F.col("size"))).filter("page_id < original")
    revisits = revisits.select(F.col("page_id").alias("pid"), F.col("digest").alias("of"), F.col("original").alias("refers_to")).distinct()
    return page.join(revisits, (F.col("page_id") == F.col("pid")) & (F.col("digest") == F.col("of")), "left").drop("pid", "of")


def _record(page_id, url, payload: bytes, digest: str, size: int, refers_to) -> bytes:
    name = lambda i: f"<urn:page:{_NONE if i is None else i}>"
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % size
    body = http + payload
    head = [
        "WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {name(page_id)}", f"WARC-Target-URI: {(url or '').replace(chr(13), '').replace(chr(10), '')}",
        "WARC-Date: 2024-01-01T00:00:00Z", f"WARC-Payload-Digest: sha1:{digest}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}",
    ]
    if refers_to is not None:
        head += [f"WARC-Refers-To: {name(refers_to)}", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    return ("\r\n".join(head) + "\r\n\r\n").encode() + body + b"\r\n\r\n"


def _member(data: bytes) -> bytes:
    z = zlib.compressobj(1, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def write_archives(resolved: DataFrame, root: str) -> DataFrame:
    """Write the records below a shared path; manifest (path, n_records, n_bytes)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, top = open_fs(root)
        fs.create_dir(top, recursive=True)
        out, path, n, size = None, "", 0, 0

        def done():
            return pa.RecordBatch.from_arrays([pa.array([path]), pa.array([n], pa.int64()), pa.array([size], pa.int64())], names=["path", "n_records", "n_bytes"])

        for b in slices(batches):
            cols = [b.column(c).to_pylist() for c in ("page_id", "url", "digest", "n_bytes", "refers_to")]
            for payload, page_id, url, digest, length, refers in zip(utf8(b, "html"), *cols):
                if out is None:
                    path, n, size = f"{uuid.uuid4().hex}.warc.gz", 0, 0
                    out = fs.open_output_stream(f"{top}/{path}", compression=None)
                data = _member(_record(page_id, url, payload if refers is None else b"", digest, length, refers))
                out.write(data)
                n, size = n + 1, size + len(data)
                if size >= ROLL:
                    out.close()
                    out = None
                    yield done()
        if out is not None:
            out.close()
            yield done()

    cols = resolved.select("page_id", "url", "html", "digest", "n_bytes", "refers_to")
    return cols.mapInArrow(run, "path string, n_records long, n_bytes long")


def read_records(stream) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, body) of the records of an uncompressed WARC stream."""
    while line := stream.readline():
        if not line.strip():
            continue
        if not line.startswith(b"WARC/"):
            raise ValueError("not a WARC record")
        head: dict[str, str] = {}
        while (line := stream.readline()).strip():
            k, _, v = line.decode().partition(":")
            head[k.strip().lower()] = v.strip()
        body = stream.read(int(head["content-length"]))
        yield head, body


def _number(urn: str) -> int | None:
    n = urn.rpartition(":")[2].rstrip(">")
    return None if n == _NONE else int(n)


def read_archives(manifest: DataFrame, root: str) -> DataFrame:
    """page_id, url, payload_bytes, payload_digest, record_type, refers_to, payload (null for a revisit).

    A response's length and digest are computed from its payload; a revisit's are its headers'.
    """
    names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"]
    kinds = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, top = open_fs(root)
        for b in batches:
            for path in b.column("path").to_pylist():
                rows, held = [], 0
                with fs.open_input_stream(f"{top}/{path}", compression=None) as raw, gzip.GzipFile(fileobj=raw) as z:
                    for head, body in read_records(io.BufferedReader(z, 1 << 20)):
                        http, _, payload = body.partition(b"\r\n\r\n")
                        url = head.get("warc-target-uri") or None
                        if head["warc-type"] == "revisit":
                            length = next(int(x.split(b":")[1]) for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:"))
                            rows.append((_number(head["warc-record-id"]), url, length, head["warc-payload-digest"].partition(":")[2], "revisit", _number(head["warc-refers-to"]), None))
                        else:
                            rows.append((_number(head["warc-record-id"]), url, len(payload), hashlib.sha1(payload).hexdigest(), "response", None, payload))
                            held += len(payload)
                        if len(rows) >= 1024 or held > 32 << 20:
                            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(map(list, zip(*rows)), kinds)], names=names)
                            rows, held = [], 0
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(map(list, zip(*rows)), kinds)], names=names)

    schema = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"
    return manifest.select("path").mapInArrow(run, schema)


def op6_warc_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Write all pages as WARC with revisits, and return what the archives hold."""
    root = scratch(spark, "warc")
    manifest = settle(write_archives(resolve(table(spark, sf_dir, "pages")), root), "warc-manifest")
    spread = manifest.repartition(max(1, min(manifest.count(), 4096)))
    return read_archives(spread, root).drop("payload", "url")


SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
m AS (SELECT *, strlen(html) AS n, max(page_id) OVER (PARTITION BY html) AS top FROM p)
SELECT page_id, n AS payload_bytes, sha1(html) AS payload_digest,
       CASE WHEN n >= 1000 AND page_id < top THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 1000 AND page_id < top THEN top END AS refers_to
FROM m
"""
