"""WARC archives without repeated payloads: revisit resolution.

Pages are hashed where they lie; only their headers (digest, id, length) are shuffled, by digest, to find
each payload's first page.  Later pages become revisit records that name the original.  Archives are
gzip members, a record each, in files of a bounded size; record headers are made anew.  Reading streams
the archives, recomputes the digest of every stored payload, and joins revisits to their originals.

Defined cases: a null payload is empty; a null url is an empty one; pages with a null id are responses;
of pages with the same id and payload all are responses if that id is the smallest; payloads shorter
than ``least`` bytes are never revisits; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import AtomicFile, new_path, opened, written

#: Fixed values of the format.
VERSION = "WARC/1.1"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n"
FILE_BYTES = 256 << 20
#: A payload that very many pages share is matched in this many parts.
SALTS = 16
HEADERS = "page_id bigint, record_id string, record_type string, payload_digest string, payload_bytes bigint, refers_to_record string"


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page_id: int | None, digest: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}:{digest}')}>"


def record(page_id: int | None, url: str, payload: bytes, original: int | None, date: str) -> bytes:
    """One record as a gzip member; a revisit if there is an ``original``."""
    digest = base32_sha1(payload)
    http = HTTP % len(payload)
    block = http if original is not None else http + payload
    fields = {
        "WARC-Type": "response" if original is None else "revisit",
        "WARC-Record-ID": record_id(page_id, digest),
        "WARC-Date": date,
        "WARC-Target-URI": re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url),
        "WARC-Payload-Digest": f"sha1:{digest}",
        "WARC-Block-Digest": f"sha1:{base32_sha1(block)}",
        "Content-Type": "application/http; msgtype=response",
        "X-Page-ID": "" if page_id is None else str(page_id),
    }
    if original is not None:
        fields |= {"WARC-Profile": PROFILE, "WARC-Refers-To": record_id(original, digest)}
    head = "".join(f"{k}: {v}\r\n" for k, v in (fields | {"Content-Length": len(block)}).items())
    packer = zlib.compressobj(4, zlib.DEFLATED, 31)
    return packer.compress(f"{VERSION}\r\n{head}\r\n".encode() + block + b"\r\n\r\n") + packer.flush()


def records(stream, piece: int = 1 << 20) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and block of each record of a gzipped archive, a member at a time."""
    rest = b""
    while rest or (rest := stream.read(piece)):
        unpacker, parts = zlib.decompressobj(31), []
        while not unpacker.eof:
            if not rest and not (rest := stream.read(piece)):
                raise ValueError("an archive ends within a record")
            parts.append(unpacker.decompress(rest))
            rest = unpacker.unused_data
        data = b"".join(parts)
        head, _, body = data.partition(b"\r\n\r\n")
        lines = head.decode().split("\r\n")
        fields = dict(x.split(": ", 1) for x in lines[1:])
        yield fields, body[: int(fields["Content-Length"])]


def mark_revisits(pages: DataFrame, least: int = 0) -> DataFrame:
    """(page_id, url, html, original): ``original`` is the id of the first page with this payload, null for that page itself."""
    known = pages.select(F.col("page_id").cast("bigint").alias("page_id"), F.coalesce(F.col("url"), F.lit("")).alias("url"), F.coalesce(F.col("html"), F.lit("")).alias("html"))
    known = known.withColumn("_digest", F.sha1("html")).withColumn("_bytes", F.octet_length("html"))
    heads = known.where(F.col("_bytes") >= least).select("page_id", "_digest")
    first = heads.groupBy("_digest").agg(F.min("page_id").alias("original"), F.count("page_id").alias("_n")).where("_n > 1").drop("_n")
    first = first.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    salted = heads.withColumn("_salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)).cast("int"))
    later = salted.join(first, ["_digest", "_salt"]).where(F.col("page_id") > F.col("original")).drop("_salt").dropDuplicates(["page_id", "_digest"])
    return known.join(later, ["page_id", "_digest"], "left").select("page_id", "url", "html", "original")


def write_archives(marked: DataFrame, path: str, date: str = "2000-01-01T00:00:00Z", file_bytes: int = FILE_BYTES) -> DataFrame:
    """Writes the archives; (file, records, bytes) of each.  Only files listed here count: a task that ran twice leaves others."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        made, rows = [], iter(r for b in batches for r in zip(*(b.column(c).to_pylist() for c in ("page_id", "url", "html", "original")), strict=True))
        row = next(rows, None)
        while row is not None:
            name = f"{path}/{task.partitionId():06d}-{len(made):04d}-{task.taskAttemptId()}.warc.gz"
            n = size = 0
            with AtomicFile(name) as out:
                while row is not None and size < file_bytes:
                    page_id, url, html, original = row
                    body = record(page_id, url, html.encode(), original, date)
                    out.write(body)
                    n, size, row = n + 1, size + len(body), next(rows, None)
            made.append((name, n, size))
        if made:
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*made, strict=True)], ["file", "records", "bytes"])

    return written(marked.mapInArrow(write, "file string, records bigint, bytes bigint"), "warc-files")


def read_headers(files: DataFrame) -> DataFrame:
    """Headers of all records in the files; digest and length are those of the payload as stored."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("page_id", pa.int64()), ("record_id", pa.string()), ("record_type", pa.string()), ("payload_digest", pa.string()), ("payload_bytes", pa.int64()), ("refers_to_record", pa.string())])
        for uri in (u for b in batches for u in b.column("file").to_pylist()):
            fs, path = opened(uri)
            with fs.open_input_stream(path, compression=None) as stream:
                rows = []
                for fields, block in records(stream):
                    payload = block.partition(b"\r\n\r\n")[2]
                    digest, n = fields["WARC-Payload-Digest"].removeprefix("sha1:"), None
                    if fields["WARC-Type"] == "response":
                        n = len(payload)
                        if base32_sha1(payload) != digest:
                            raise ValueError(f"{uri}: a payload of {fields['WARC-Record-ID']} doesn't match its digest")
                    page = fields["X-Page-ID"]
                    rows.append((int(page) if page else None, fields["WARC-Record-ID"], fields["WARC-Type"], digest, n, fields.get("WARC-Refers-To")))
                    if len(rows) >= 5000:
                        yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), schema.types, strict=True)], schema=schema)
                        rows = []
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), schema.types, strict=True)], schema=schema)

    spread = files.select("file").repartition(max(1, files.sparkSession.sparkContext.defaultParallelism), "file")
    return spread.mapInArrow(read, HEADERS)


def resolve(headers: DataFrame) -> DataFrame:
    """Revisits joined to their originals: length and page id of what they refer to."""
    columns = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    responses = headers.where("record_type = 'response'")
    originals = responses.select(F.col("record_id").alias("refers_to_record"), F.col("page_id").alias("refers_to"), F.col("payload_bytes").alias("_bytes")).dropDuplicates(["refers_to_record"])
    revisits = headers.where("record_type = 'revisit'").join(originals, "refers_to_record", "left").withColumn("payload_bytes", F.col("_bytes"))
    return responses.withColumn("refers_to", F.lit(None).cast("bigint")).select(columns).unionByName(revisits.select(columns))


def report(pages: DataFrame, least: int = 0) -> DataFrame:
    """Per page: the record written for it, as read back."""
    files = write_archives(mark_revisits(pages, least), new_path(pages.sparkSession, "warc"))
    return resolve(written(read_headers(files), "warc-headers"))
