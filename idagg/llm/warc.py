"""WARC archives compressed record by record with a shared Zstandard dictionary.

The dictionary is trained on a bounded sample of the records and stands, itself compressed, in a skippable frame that leads each
archive; every record is a frame of its own, so any of them can be read alone. Records with equal payloads are stored once: the
one with the largest page id is the response, the others are revisits that refer to it.

An archive is one row (name, content) of at most about ``archive_bytes`` of payload; the rows are a table that Spark writes and reads,
so they can live in any store. ``write_files`` copies them to a folder as .warc.zst files. Payloads that are equal meet only as (digest,
id) rows, aggregated before the shuffle; a payload that a third of all pages share costs no more than others.

Edge cases: null html is an empty payload; empty payloads are deduplicated like others; a null id sorts below all others; rows that repeat
an id and payload are written as often as they occur and all have the same type, the response's where that id is the largest; an empty
table gives no archive.
"""

from __future__ import annotations

import base64
import hashlib
import io
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import zstandard as zstd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import bounded_sample, materialize

SKIPPABLE = 0x184D2A5D  # fixed value of the format: magic number of the frame that holds the dictionary
SAMPLE_ROWS, SAMPLE_BYTES, DICTIONARY_BYTES, LEVEL = 1_000, 8 << 20, 110 << 10, 3
ARCHIVE_BYTES = 16 << 20


def train(pages: DataFrame, sample_rows: int = SAMPLE_ROWS) -> bytes:
    """A dictionary from at most sample_rows payloads (those of the lowest hash) and SAMPLE_BYTES in total."""
    p = pages.select("page_id", F.coalesce("html", F.lit("")).alias("h"))
    rows = bounded_sample(p, ["page_id"], sample_rows).where(F.length("h") < 1 << 20).orderBy("__o", "page_id", "h").toLocalIterator()
    samples, size = [], 0
    for r in rows:
        raw = r.h.encode()
        if size < SAMPLE_BYTES and raw:
            samples.append(raw)
            size += len(raw)
    try:
        return zstd.train_dictionary(min(DICTIONARY_BYTES, max(1024, size // 8)), samples, level=LEVEL).as_bytes()
    except zstd.ZstdError:  # too few or too uniform samples: the raw samples are a valid dictionary too
        return b"".join(samples)[-DICTIONARY_BYTES:]


def dictionary_frame(raw: bytes) -> bytes:
    body = zstd.ZstdCompressor(level=19).compress(raw)
    return struct.pack("<II", SKIPPABLE, len(body)) + body


def record(page_id, url: str, payload: bytes, digest: str, refers_to) -> bytes:
    """One WARC/1.1 record; its content is an HTTP response, without a body where it revisits another."""
    kind = "response" if refers_to is None else "revisit"
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http + (payload if refers_to is None else b"")
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}')}>",
        "WARC-Date: 1970-01-01T00:00:00Z", f"WARC-Target-URI: {(url or 'urn:none').replace(chr(13), '%0D').replace(chr(10), '%0A')}",
        f"WARC-Payload-Digest: sha1:{digest}", f"X-Page-Id: {'' if page_id is None else page_id}", f"X-Payload-Length: {len(payload)}",
    ]
    if refers_to is not None:
        head += [
            f"WARC-Refers-To: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{refers_to}')}>", f"X-Refers-To-Page: {refers_to}",
            "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest",
        ]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}", "", ""]
    return "\r\n".join(head).encode() + block + b"\r\n\r\n"


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and payload of a record; lengths are checked."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if lines[0] != "WARC/1.1":
        raise ValueError("not a WARC record")
    fields = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines[1:])
    size = int(fields["Content-Length"])
    if rest[size:] != b"\r\n\r\n":
        raise ValueError("a record's length is wrong")
    return fields, rest[:size].partition(b"\r\n\r\n")[2]


def with_targets(pages: DataFrame) -> DataFrame:
    """pages with refers_to: the largest page id of an equal payload where that is not the row's own."""
    p = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html")).withColumn("k", F.sha1(F.col("html").cast("binary")))
    ids = p.select("k", "page_id")
    best = ids.groupBy("k").agg(F.max("page_id").alias("best"), F.count("*").alias("n")).where("n > 1 and best is not null")
    revisits = (
        ids.join(best, "k").where("page_id is null or page_id <> best").select("page_id", "k", F.col("best").alias("refers_to")).distinct()
        .withColumnsRenamed({"page_id": "rp", "k": "rk"})
    )
    return p.join(revisits, (F.col("page_id").eqNullSafe(F.col("rp"))) & (F.col("k") == F.col("rk")), "left").select("page_id", "url", "html", "refers_to")


def write(pages: DataFrame, dictionary: bytes | None = None, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """The archives: (name, content). pages: page_id, url, html."""
    raw_dict = train(pages) if dictionary is None else dictionary
    shared = pages.sparkSession.sparkContext.broadcast(raw_dict)  # at most DICTIONARY_BYTES or the given one

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        d = zstd.ZstdCompressionDict(shared.value)
        comp = zstd.ZstdCompressor(level=LEVEL, dict_data=d, write_checksum=True, write_content_size=True)
        lead = dictionary_frame(shared.value)
        out, size = io.BytesIO(), 0

        def done() -> pa.RecordBatch:
            content = out.getvalue()
            return pa.RecordBatch.from_arrays([pa.array([f"{hashlib.sha1(content).hexdigest()}.warc.zst"]), pa.array([content], pa.binary())], ["name", "content"])

        for b in batches:
            for pid, url, html, ref in zip(*(c.to_pylist() for c in b.columns), strict=True):
                payload = html.encode()
                digest = base64.b32encode(hashlib.sha1(payload).digest()).decode()
                if not out.tell():
                    out.write(lead)
                out.write(comp.compress(record(pid, url, payload, digest, ref)))
                size += len(payload) if ref is None else 0
                if size >= archive_bytes:
                    yield done()
                    out, size = io.BytesIO(), 0
        if out.tell():
            yield done()

    return materialize(with_targets(pages).mapInArrow(run, "name string, content binary"), "warc")


def records(content: bytes) -> Iterator[bytes]:
    """The records of an archive, one a frame."""
    magic, size = struct.unpack_from("<II", content)
    if magic != SKIPPABLE:
        raise ValueError("the archive doesn't begin with its dictionary")
    d = zstd.ZstdCompressionDict(zstd.ZstdDecompressor().decompress(content[8 : 8 + size]))
    un = zstd.ZstdDecompressor(dict_data=d)
    at, view = 8 + size, memoryview(content)
    while at < len(content):
        span = frame_span(view, at)
        yield un.decompress(view[at : at + span])
        at += span


def frame_span(view: memoryview, at: int) -> int:
    """Bytes of the Zstandard frame that begins at ``at``, from its block headers."""
    head = zstd.frame_header_size(view[at : at + 18])
    check = zstd.get_frame_parameters(view[at : at + 18]).has_checksum
    p = at + head
    while True:
        h = int.from_bytes(view[p : p + 3], "little")
        p += 3 + (1 if (h >> 1) & 3 == 1 else h >> 3)
        if h & 1:
            return p - at + 4 * check


def read(archives: DataFrame) -> DataFrame:
    """One row a record of the archives; each payload's digest and length are checked against the record's own."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for content in b.column(0):
                ids, urls, sizes, digests, kinds, refs, bodies = [], [], [], [], [], [], []
                for raw in records(content.as_py()):
                    f, body = parse(raw)
                    digest = f["WARC-Payload-Digest"].removeprefix("sha1:")
                    if f["WARC-Type"] == "response" and (base64.b32encode(hashlib.sha1(body).digest()).decode() != digest or len(body) != int(f["X-Payload-Length"])):
                        raise ValueError("a payload doesn't match its digest")
                    ids.append(int(f["X-Page-Id"]) if f["X-Page-Id"] else None)
                    urls.append(f["WARC-Target-URI"])
                    sizes.append(int(f["X-Payload-Length"]))
                    digests.append(digest)
                    kinds.append(f["WARC-Type"])
                    refs.append(int(f["X-Refers-To-Page"]) if "X-Refers-To-Page" in f else None)
                    bodies.append(body.decode() if f["WARC-Type"] == "response" else None)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ids, pa.int64()), pa.array(urls, pa.string()), pa.array(sizes, pa.int64()), pa.array(digests, pa.string()), pa.array(kinds, pa.string()), pa.array(refs, pa.int64()), pa.array(bodies, pa.string())],
                    ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "html"])

    return archives.select("content").mapInArrow(
        run, "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, html string")


def write_files(archives: DataFrame, folder: str) -> None:
    """Copy archives to .warc.zst files through the file system that Spark knows the folder by, one at a time."""
    spark = archives.sparkSession
    jvm = spark._jvm
    base = jvm.org.apache.hadoop.fs.Path(folder)
    fs = base.getFileSystem(spark._jsc.hadoopConfiguration())
    fs.mkdirs(base)
    for r in archives.toLocalIterator():
        out = fs.create(jvm.org.apache.hadoop.fs.Path(base, r.name), True)
        out.write(bytearray(r.content))
        out.close()


def oracle() -> str:
    """What is read back from archives of pages, as DuckDB SQL over the pages themselves; the digest's base 32 comes from its hex, five digits giving
    four characters."""
    letters = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
    return f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages), q AS (SELECT page_id, h, sha1(h) AS x, max(page_id) OVER (PARTITION BY h) AS best FROM p)
SELECT page_id, strlen(h) AS payload_bytes,
       array_to_string([substr('{letters}', 1 + CAST(('0x' || substr(x, 1 + 5 * (k // 4), 5))::BIGINT >> (15 - 5 * (k % 4)) & 31 AS BIGINT), 1) for k in range(32)], '') AS payload_digest,
       CASE WHEN page_id = best THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> best THEN best END AS refers_to FROM q
"""
