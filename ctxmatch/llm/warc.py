r"""WARC archives: written as monolithic gzip, then normalised to one gzip member per record with a sidecar offset index.

Some writers compress an archive as a single stream, which cannot be read from the middle. The normaliser inflates such a stream once,
cuts it into records by their Content-Length, writes every record as a member of its own and notes (record id, offset, length) of
each in an index, with which any record can be read alone.

Records whose payloads are equal and of at least ``least`` bytes are written once: the one with the smallest page id is a
``response``, the others are ``revisit`` records that carry the digest, the length and the id of the response, without the
payload. Archives and sidecars are files in the shared folder, written and read by the tasks through Arrow's file systems (local, HDFS, S3, GCS, Azure);
the tables between the steps hold their names only.

Defined cases: null html is an empty payload; a null url has no target header; null page ids are written as such and never chosen over others
as the response; repeated page ids give a record each, of equal payloads those of the smallest id are all responses; an archive closes at the first record that
brings it to ``archive_bytes``, so a very large page has one of its own; other columns are ignored; an empty table gives no archives.
"""

from __future__ import annotations

import gzip
import hashlib
import io
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_folder, drop_written, shared_dir, text_of, written

_NAMES = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, date: str = "2024-01-01T00:00:00Z") -> bytes:
    """One WARC record, uncompressed. A revisit keeps the HTTP head, and so the payload's length."""
    revisit = refers_to is not None
    head = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    body = head if revisit else head + payload
    lines = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: <urn:page:{page_id}>", f"WARC-Date: {date}"]
    if url is not None:
        lines.append("WARC-Target-URI: " + url.replace("\r", "%0D").replace("\n", "%0A"))
    lines.append(f"WARC-Payload-Digest: sha256:{digest}")
    if revisit:
        lines += [f"WARC-Refers-To: <urn:page:{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def headers_of(head: bytes) -> dict[str, str]:
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    return {k.lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}


def records_in(stream: io.BufferedIOBase) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers, whole record) of an inflated archive, one record in memory at a time."""
    while True:
        line, head = stream.readline(), b""
        while line in (b"\r\n", b"\n"):
            line = stream.readline()
        if not line:
            return
        while line not in (b"\r\n", b"\n", b""):
            head += line
            line = stream.readline()
        found = headers_of(head.rstrip(b"\r\n"))
        length = int(found.get("content-length", -1))
        body = stream.read(max(length, 0))
        if len(body) != length:
            raise ValueError(f"record {found.get('warc-record-id')} is cut short")
        yield found, head + b"\r\n" + body + b"\r\n\r\n"


def member(data: bytes, level: int = 6) -> bytes:
    return gzip.compress(data, level, mtime=0)


def _at(path: str) -> tuple[fs.FileSystem, str]:
    """The file system that a URI (or an absolute local path) names, and the path in it."""
    return fs.FileSystem.from_uri(path)


def normalise_file(source: str, target: str, level: int = 6) -> int:
    """Rewrite a monolithic archive with a member per record; returns the number of records. One record is in memory at a time.

    The index goes to ``target + '.idx'``, a tab-separated line (record id, offset, length) per record. Paths are local ones or URIs of a store that Arrow knows.
    """
    (store, path), (into, out_path), at, n = _at(source), _at(target), 0, 0
    with store.open_input_stream(path, compression=None) as packed, into.open_output_stream(out_path, compression=None) as out, into.open_output_stream(out_path + ".idx", compression=None) as side:
        for found, data in records_in(io.BufferedReader(gzip.GzipFile(fileobj=packed), 1 << 20)):
            one = member(data, level)
            out.write(one)
            side.write(f"{found['warc-record-id']}\t{at}\t{len(one)}\n".encode())
            at, n = at + len(one), n + 1
    return n


def index_of(archive: str) -> list[tuple[str, int, int]]:
    """(record id, offset, length) from the sidecar of a normalised archive."""
    store, path = _at(archive + ".idx")
    with store.open_input_stream(path, compression=None) as side:
        lines = (line.rsplit("\t", 2) for line in side.read().decode().splitlines())
        return [(name, int(at), int(n)) for name, at, n in lines]


def records_at(archive: str, index: list[tuple[str, int, int]]) -> Iterator[bytes]:
    """The members that the index points to, each read alone."""
    store, path = _at(archive)
    with store.open_input_file(path) as data:
        for _, at, n in index:
            data.seek(at)
            yield data.read(n)


def read_record(data: bytes) -> tuple[int | None, int, str, str, int | None]:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of one member; a response's digest is computed from its payload."""
    found, whole = next(records_in(io.BufferedReader(io.BytesIO(zlib.decompress(data, 31)))))
    page = lambda name: None if (x := found.get(name, "<urn:page:None>")[10:-1]) == "None" else int(x)
    body = whole.split(b"\r\n\r\n", 1)[1][:-4]
    head, _, payload = body.partition(b"\r\n\r\n")
    length = int(next(x.split(b":")[1] for x in head.split(b"\r\n") if x.lower().startswith(b"content-length:")))
    digest = found["warc-payload-digest"].removeprefix("sha256:")
    if found["warc-type"] == "response":
        if len(payload) != length or hashlib.sha256(payload).hexdigest() != digest:
            raise ValueError(f"payload of {found['warc-record-id']} does not match its digest")
    return page("warc-record-id"), length, digest, found["warc-type"], page("warc-refers-to")


SALTS = 32


def typed(pages: DataFrame, least: int = 100) -> DataFrame:
    """page_id, url, payload, digest, refers_to: null for a response.

    Digests meet their first page in ``SALTS`` places each, so the payloads of a page with very many copies do not follow its digest into one task.
    """
    payload = text_of("html")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), payload.cast("binary").alias("payload"), F.sha2(payload, 256).alias("digest"))
    large = F.octet_length("payload") >= least
    first = rows.filter(large).groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).filter("n > 1").select("digest", "first", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    rows = rows.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int")).join(first, ["digest", "salt"], "left")
    return rows.select("page_id", "url", "payload", "digest", F.when(~F.col("page_id").eqNullSafe(F.col("first")), F.col("first")).alias("refers_to"))


def write_archives(rows: DataFrame, folder: str, archive_bytes: int = 4 << 20) -> DataFrame:
    """archive: URIs of the monolithic gzip archives below ``folder`` to which the tasks write typed rows, record by record.

    Names differ from attempt to attempt: those of a lost attempt are never listed, and an archive that is listed is whole.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, count, open_one = TaskContext.get().partitionId(), 0, None
        store, path = _at(folder)
        store.create_dir(path, recursive=True)

        def closed() -> pa.RecordBatch:
            name, out, packer, _ = open_one
            out.write(packer.flush())
            out.close()
            return pa.RecordBatch.from_arrays([pa.array([f"{folder}/{name}"])], ["archive"])

        for batch in batches:
            for row in zip(*(batch.column(k) for k in range(5)), strict=True):
                if open_one is None:
                    name = f"pages-{part:06d}-{count:06d}-{uuid.uuid4().hex[:8]}.warc.gz"
                    open_one = [name, store.open_output_stream(f"{path}/{name}", compression=None), zlib.compressobj(6, wbits=31), 0]
                data = record(*(x.as_py() for x in row))
                open_one[1].write(open_one[2].compress(data))
                open_one[3] += len(data)
                if open_one[3] >= archive_bytes:
                    yield closed()
                    count, open_one = count + 1, None
        if open_one is not None:
            yield closed()

    return rows.mapInArrow(run, "archive string")


def normalised(archives: DataFrame, folder: str) -> DataFrame:
    """archive, n_records: the archives rewritten below ``folder``, a member per record, each with its sidecar index beside it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, path = _at(folder)
        store.create_dir(path, recursive=True)
        for batch in batches:
            for source in batch.column(0).to_pylist():
                target = f"{folder}/{uuid.uuid4().hex[:8]}-{source.rsplit('/', 1)[1]}"
                yield pa.RecordBatch.from_arrays([pa.array([target]), pa.array([normalise_file(source, target)], pa.int64())], ["archive", "n_records"])

    return archives.mapInArrow(run, "archive string, n_records long")


def read_archives(archives: DataFrame) -> DataFrame:
    """A row per record of normalised archives, read through their sidecars."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
        for batch in batches:
            for archive in batch.column(0).to_pylist():
                rows = [read_record(data) for data in records_at(archive, index_of(archive))]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], _NAMES)

    return archives.mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def archive_pages(pages: DataFrame, *, least: int = 100, archive_bytes: int = 4 << 20, folder: str | None = None) -> DataFrame:
    """Write all pages, normalise the archives, and read them back: a row per record. The normalised archives stay in ``folder`` (one of the shared folder's own)."""
    folder = folder or f"{shared_dir(pages.sparkSession)}/warc-{uuid.uuid4().hex}"
    whole = written(write_archives(typed(pages, least), f"{folder}/whole", archive_bytes), "warc-whole")
    width = int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    members = written(normalised(whole.repartition(width), f"{folder}/members"), "warc-members")
    drop_written(whole)
    drop_folder(pages.sparkSession, f"{folder}/whole")
    return read_archives(members.select("archive").repartition(width))


ORACLE = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
     d AS (SELECT page_id, CAST(strlen(h) AS BIGINT) AS payload_bytes, sha256(h) AS payload_digest FROM p),
     f AS (SELECT payload_digest, min(page_id) AS first FROM d WHERE payload_bytes >= 100 GROUP BY 1)
SELECT d.page_id, d.payload_bytes, d.payload_digest, CASE WHEN f.first < d.page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN f.first < d.page_id THEN f.first END AS refers_to
FROM d LEFT JOIN f ON d.payload_digest = f.payload_digest AND d.payload_bytes >= 100
"""
