"""WARC archives: a writer that stores equal payloads once, and a reader that splits archives by byte ranges.

Each record is a gzip member of its own. A reading task owns the members that start inside its byte range: it scans
for the gzip magic, takes a candidate for a member only if it inflates to a WARC header, and reads past its range's
end to finish the last record it owns. Magic bytes inside compressed data fail that test or are never reached,
because a task goes on from the end of each member it has read.

Files are written through the file system of the shared folder's URI under names of their own for each attempt; the
list of files comes from the tasks that succeeded, so a lost or repeated task leaves no file that is read.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh_dir, table

LEAST_SHARED_BYTES = 1000
SPLIT_BYTES = 8 << 20
FILE_BYTES = 64 << 20
MAGIC = b"\x1f\x8b\x08"
WINDOW = 1 << 16
HEADER_END = b"\r\n\r\n"


def file_system(uri: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(uri if "://" in uri else uri.replace("file:", "file://", 1) if uri.startswith("file:") else f"file://{uri}")


def record_bytes(page_id: int | None, url: str | None, payload: bytes, digest: str, original: int | None, original_url: str | None = None) -> bytes:
    """A gzip member with a response record, or a revisit record that refers to the response of page original."""
    name = lambda i: f"<urn:page:{'none' if i is None else i}>"
    lines = [
        "WARC/1.1", f"WARC-Type: {'response' if original is None else 'revisit'}", f"WARC-Record-ID: {name(page_id)}", "WARC-Date: 1970-01-01T00:00:00Z",
        "Content-Type: text/html; charset=utf-8", f"WARC-Payload-Digest: sha1:{digest}", f"WARC-Payload-Length: {len(payload)}",
    ]
    if url is not None:
        lines.append("WARC-Target-URI: " + url.replace("%", "%25").replace("\r", "%0D").replace("\n", "%0A"))
    if original is not None:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {name(original)}"]
    body = payload if original is None else b""
    lines.append(f"Content-Length: {len(body)}")
    z = zlib.compressobj(1, zlib.DEFLATED, 31)
    return z.compress("\r\n".join(lines).encode() + HEADER_END + body + HEADER_END) + z.flush()


def marked(pages: DataFrame, id_col: str = "page_id", payload_col: str = "html") -> DataFrame:
    """pages with sw__payload, sw__digest and sw__original: the page that a revisit refers to, else null.

    Of equal payloads of LEAST_SHARED_BYTES and more, the largest id is the response. Only digests that occur twice
    are joined back. Rows without an id are responses of their own; rows that share the largest id all are responses.
    """
    body = F.coalesce(F.encode(F.col(payload_col), "UTF-8"), F.lit(b""))
    base = pages.withColumn("sw__payload", body).withColumn("sw__digest", F.sha1("sw__payload"))
    large = pages.select(F.col(id_col).cast("bigint").alias("k"), body.alias("b")).where(F.length("b") >= LEAST_SHARED_BYTES).select("k", F.sha1("b").alias("sw__same"))
    groups = large.groupBy("sw__same").agg(F.max("k").alias("sw__last"), F.count("*").alias("n")).where("n > 1").drop("n")
    joined = base.join(groups, base.sw__digest == groups.sw__same, "left")
    return joined.withColumn("sw__original", F.when(F.col("sw__last") > F.col(id_col), F.col("sw__last"))).drop("sw__same", "sw__last")


def write(pages: DataFrame, folder: str, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html") -> DataFrame:
    """Archives with a record for each row, under folder; gives the list of files (uri, bytes, records), stored there too."""
    rows = marked(pages, id_col, payload_col).select(F.col(id_col).cast("bigint"), F.col(url_col).cast("string"), "sw__payload", "sw__digest", "sw__original")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, root = file_system(folder)
        out, uri, size, n = None, "", 0, 0

        def close() -> pa.RecordBatch:
            out.close()
            return pa.RecordBatch.from_pydict({"uri": pa.array([uri]), "bytes": pa.array([size], pa.int64()), "records": pa.array([n], pa.int64())})

        for b in batches:
            for at in range(0, b.num_rows, 256):
                for page, url, payload, digest, original in zip(*(c.to_pylist() for c in b.slice(at, 256).columns), strict=True):
                    if out is None:
                        name = f"part-{uuid.uuid4().hex}.warc.gz"
                        uri, size, n = f"{folder.rstrip('/')}/{name}", 0, 0
                        out = system.open_output_stream(f"{root.rstrip('/')}/{name}", compression=None)
                    got = record_bytes(page, url, payload, digest, original)
                    out.write(got)
                    size, n = size + len(got), n + 1
                    if size >= FILE_BYTES:
                        yield close()
                        out = None
        if out is not None:
            yield close()

    system, root = file_system(folder)
    system.create_dir(root, recursive=True)
    rows.mapInArrow(run, "uri string, bytes bigint, records bigint").write.parquet(f"{folder}/_files")
    return rows.sparkSession.read.parquet(f"{folder}/_files")


class _Window:
    """Bytes of a file from any place on, read as they are needed."""

    def __init__(self, f: pa.NativeFile, at: int) -> None:
        self.f, self.base, self.data = f, at, b""

    def get(self, at: int, n: int) -> bytes:
        if at < self.base or at > self.base + len(self.data):
            self.base, self.data = at, b""
        while len(self.data) < at - self.base + n:
            self.f.seek(self.base + len(self.data))
            more = self.f.read(max(WINDOW, n))
            if not more:
                break
            self.data += more
        cut = at - self.base
        if cut > 8 * WINDOW:
            self.base, self.data, cut = at, self.data[cut:], 0
        return self.data[cut : cut + n]


def _member(w: _Window, at: int) -> tuple[bytes, int] | None:
    """The inflated member that starts there and where it ends; nothing if none with a WARC header does."""
    z, out, place = zlib.decompressobj(31), [], at
    size = 0
    while not z.eof:
        chunk = w.get(place, WINDOW)
        if not chunk:
            return None
        try:
            got = z.decompress(chunk)
        except zlib.error:
            return None
        place += len(chunk)
        out.append(got)
        size += len(got)
        if size >= 5 and not b"".join(out[:8])[:5].startswith(b"WARC/"):
            return None
    data = b"".join(out)
    return (data, place - len(z.unused_data)) if data.startswith(b"WARC/") else None


def records_in(f: pa.NativeFile, start: int, stop: int) -> Iterator[bytes]:
    """Inflated records whose members start in [start, stop)."""
    w, at = _Window(f, start), start
    while at < stop:
        here = w.get(at, WINDOW)
        if len(here) < len(MAGIC):
            return
        found = here.find(MAGIC)
        if found < 0:
            at += len(here) - len(MAGIC) + 1
            continue
        at += found
        if at >= stop:
            return
        got = _member(w, at)
        if got is None:
            at += 1
        else:
            yield got[0]
            at = got[1]


def parse(record: bytes) -> dict[str, str | bytes]:
    """Header fields by lower-case name, and the block under an empty name."""
    end = record.index(HEADER_END)
    out: dict[str, str | bytes] = dict((k.lower(), v) for k, _, v in (x.partition(": ") for x in record[:end].decode().split("\r\n")[1:]))
    out[""] = record[end + 4 : end + 4 + int(out["content-length"])]
    return out


def read(files: DataFrame, payloads: bool = False, split_bytes: int = SPLIT_BYTES) -> DataFrame:
    """Records of the listed archives (uri, bytes), read by byte ranges that are dealt out evenly.

    Gives page_id, url, record_type, payload_bytes, payload_digest, refers_to and, if asked for, payload (null for
    revisits). Digest and length of a response are taken from the bytes read, those of a revisit from its header.
    """
    spark = files.sparkSession
    ranges = files.where("bytes > 0").select("uri", "bytes", F.explode(F.expr(f"sequence(0L, bytes - 1, {split_bytes}L)")).alias("first"))
    ranges = ranges.select("uri", "first", F.least("bytes", F.col("first") + split_bytes).alias("stop"))
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    schema = {"page_id": pa.int64(), "url": pa.string(), "record_type": pa.string(), "payload_bytes": pa.int64(), "payload_digest": pa.string(), "refers_to": pa.int64()} | ({"payload": pa.binary()} if payloads else {})

    def number(name: str) -> int | None:
        got = name.removeprefix("<urn:page:").removesuffix(">")
        return None if got == "none" else int(got)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        size = 0
        flush = lambda: pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(schema.values())], names=list(schema))
        for b in batches:
            for uri, first, stop in zip(*(c.to_pylist() for c in b.columns), strict=True):
                system, path = file_system(uri)
                with system.open_input_file(path) as f:
                    for record in records_in(f, first, stop):
                        h = parse(record)
                        original = h["warc-type"] == "revisit"
                        body, url = h[""], h.get("warc-target-uri")
                        url = url if url is None else url.replace("%0A", "\n").replace("%0D", "\r").replace("%25", "%")
                        row = (number(h["warc-record-id"]), url, h["warc-type"], int(h["warc-payload-length"]) if original else len(body), h["warc-payload-digest"].removeprefix("sha1:") if original else hashlib.sha1(body).hexdigest(), number(h["warc-refers-to"]) if original else None)
                        rows.append((*row, None if original else body) if payloads else row)
                        size += len(body) if payloads else 100
                        if size > 4 << 20:
                            yield flush()
                            rows, size = [], 0
        if rows:
            yield flush()

    kinds = {pa.int64(): "bigint", pa.string(): "string", pa.binary(): "binary"}
    return ranges.repartition(parts, "uri", "first").mapInArrow(run, ", ".join(f"{n} {kinds[t]}" for n, t in schema.items()))


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = fresh_dir(spark, "warc")
    files = write(table(spark, sf_dir, "pages"), folder)
    out = read(files)
    return out.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url")


OP5_SQL = """
WITH p AS (SELECT page_id, url, coalesce(html, '') AS h FROM pages),
d AS (SELECT page_id, url, octet_length(encode(h)) AS payload_bytes, sha1(h) AS payload_digest FROM p),
g AS (SELECT *, CASE WHEN payload_bytes >= 1000 THEN max(page_id) OVER (PARTITION BY payload_digest) ELSE page_id END AS last FROM d)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN last = page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN last <> page_id THEN last END AS refers_to, url FROM g
"""
