"""WARC in seekable Zstandard bundles: records in independent frames, a seek table in the footer, an index of records.

A bundle is one binary value (a row of a Parquet table in the shared folder, so any store that Spark writes will do);
``export`` turns bundles into .warc.zst files. Frames hold about `frame_bytes` of records; after the last frame comes a
skippable frame with (compressed size, uncompressed size) of each frame, in the layout of the seekable format.

Edge cases: null html is an empty payload, null url an empty target, null page_id a record without a page number (it
counts as the smallest); rows that repeat the response's page_id and payload are responses too; an empty table gives no
rows; other columns are ignored. A page larger than a frame gets a frame of its own.
"""

from __future__ import annotations

import hashlib
import re
import struct
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..runtime import scratch_path
from .common import pick

#: Fixed values of the Zstandard seekable format: skippable frame, footer magic.
SKIPPABLE, SEEKABLE = 0x184D2A5E, 0x8F92EAB1
FRAME_BYTES, BUNDLE_BYTES = 256 << 10, 8 << 20
LEAST_REVISIT, SALTS = 1000, 32
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n"
BUNDLE = "bundle binary, records array<struct<page_id:long,frame:int,offset:int,length:int>>"
RECORD = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, target string, payload binary"


def roles(pages: DataFrame, least: int = LEAST_REVISIT) -> DataFrame:
    """pages with payload, digest and refers_to (null: response). Digests are counted before they are shuffled, and
    only those that occur twice are joined back. A third of all pages may be copies of one: the rows of a digest are
    dealt to SALTS parts, and the digest's owner goes to all of them."""
    rows = pick(pages, page_id="long", url="string", html="string").select("page_id", "url", F.coalesce("html", F.lit("")).cast("binary").alias("payload"))
    rows = rows.withColumn("digest", F.sha1("payload"))
    owner = rows.where(F.length("payload") >= least).groupBy("digest").agg(F.max("page_id").alias("owner"), F.count(F.lit(1)).alias("n")).where("n > 1 AND owner IS NOT NULL").select("digest", "owner")
    owner = owner.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    joined = rows.withColumn("salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)).cast("int")).join(owner, ["digest", "salt"], "left")
    return joined.select("page_id", "url", "payload", "digest", F.when(~F.col("owner").eqNullSafe(F.col("page_id")), F.col("owner")).alias("refers_to"))


def _uri(page_id: int | None) -> bytes:
    return b"<urn:page:%s>" % (b"unknown" if page_id is None else b"%d" % page_id)


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One WARC/1.1 record; a revisit carries the payload's digest and size and no payload."""
    target = re.sub(rb"[\x00-\x20\x7f]", lambda m: b"%%%02X" % m[0][0], (url or "").encode())
    head = HTTP % len(payload)
    block = head + (payload if refers_to is None else b"")
    lines = [b"WARC/1.1", b"WARC-Type: " + (b"response" if refers_to is None else b"revisit"), b"WARC-Record-ID: " + _uri(page_id), b"WARC-Date: 1970-01-01T00:00:00Z", b"WARC-Target-URI: " + target, b"Content-Type: application/http; msgtype=response", b"WARC-Payload-Digest: sha1:" + digest.encode()]
    if refers_to is not None:
        lines += [b"WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", b"WARC-Refers-To: " + _uri(refers_to)]
    lines.append(b"Content-Length: %d" % len(block))
    return b"\r\n".join(lines) + b"\r\n\r\n" + block + b"\r\n\r\n"


def seek_table(frames: list[tuple[int, int]]) -> bytes:
    body = b"".join(struct.pack("<II", c, u) for c, u in frames) + struct.pack("<IBI", len(frames), 0, SEEKABLE)
    return struct.pack("<II", SKIPPABLE, len(body)) + body


def read_seek_table(bundle: bytes) -> list[tuple[int, int, int]]:
    """(offset, compressed size, uncompressed size) of each frame, from the footer."""
    n, flags, magic = struct.unpack("<IBI", bundle[-9:])
    if magic != SEEKABLE or flags & 0x7C:
        raise ValueError("no seek table at the end of the bundle")
    width = 12 if flags & 0x80 else 8
    at, out, start = len(bundle) - 9 - n * width, [], 0
    for i in range(n):
        c, u = struct.unpack_from("<II", bundle, at + i * width)
        out.append((start, c, u))
        start += c
    return out


def frame(bundle: bytes, number: int) -> bytes:
    """One frame's records; nothing else of the bundle is decompressed."""
    import zstandard

    start, size, raw = read_seek_table(bundle)[number]
    return zstandard.ZstdDecompressor().decompress(bundle[start : start + size], max_output_size=raw)


def parse_record(data: bytes, at: int = 0) -> tuple[dict[str, str], bytes, int]:
    """(headers, block, end) of the record at this offset."""
    stop = data.index(b"\r\n\r\n", at)
    lines = data[at:stop].decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("no record at this offset")
    head = dict(x.split(": ", 1) for x in lines[1:])
    end = stop + 4 + int(head["Content-Length"])
    return head, data[stop + 4 : end], end + 4


def write_bundles(pages: DataFrame, path: str, frame_bytes: int = FRAME_BYTES, bundle_bytes: int = BUNDLE_BYTES, level: int = 3) -> None:
    """Each task fills bundles from its own rows: no shuffle beyond that of `roles`, memory bounded by one bundle."""

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        squeeze = zstandard.ZstdCompressor(level=level, write_checksum=True, write_content_size=True)
        raw, frames, sizes, where = bytearray(), [], [], []

        def close_frame() -> None:
            if raw:
                frames.append(squeeze.compress(bytes(raw)))
                sizes.append((len(frames[-1]), len(raw)))
                raw.clear()

        def bundle() -> pa.RecordBatch:
            close_frame()
            data = b"".join(frames) + seek_table(sizes)
            row = pa.RecordBatch.from_pylist([{"bundle": data, "records": [dict(zip(("page_id", "frame", "offset", "length"), w)) for w in where]}], schema=pa.schema([("bundle", pa.binary()), ("records", pa.list_(pa.struct([("page_id", pa.int64()), ("frame", pa.int32()), ("offset", pa.int32()), ("length", pa.int32())])))]))
            frames.clear(), sizes.clear(), where.clear()
            return row

        for batch in it:
            for values in zip(*(c.to_pylist() for c in batch.columns)):
                one = record(*values)
                if raw and len(raw) + len(one) > frame_bytes:
                    close_frame()
                    if sum(c for c, _ in sizes) >= bundle_bytes:
                        yield bundle()
                where.append((values[0], len(sizes), len(raw), len(one)))
                raw += one
        if where:
            yield bundle()

    roles(pages).mapInArrow(kernel, BUNDLE).write.option("compression", "uncompressed").parquet(path)


def record_index(bundles: DataFrame) -> DataFrame:
    """(bundle_id, page_id, frame, offset, length): where each record lies; bundle_id is the SHA-1 of the bundle."""
    return bundles.select(F.sha1("bundle").alias("bundle_id"), F.explode("records").alias("r")).select("bundle_id", "r.*")


def read_records(bundles: DataFrame, payloads: bool = True) -> DataFrame:
    """RECORD rows parsed from the bundles' own bytes. Digests and sizes of responses are computed from the payload
    read back and held against the header; a revisit has those of the record it refers to, from its headers."""

    def kernel(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        schema = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("target", pa.string()), ("payload", pa.binary())])
        number = lambda uri: None if uri is None or uri == "<urn:page:unknown>" else int(uri[10:-1])
        open_ = zstandard.ZstdDecompressor()
        for batch in it:
            for bundle in batch.column(0).to_pylist():
                for start, size, raw in read_seek_table(bundle):
                    data, at, rows = open_.decompress(bundle[start : start + size], max_output_size=raw), 0, []
                    while at < len(data):
                        head, block, at = parse_record(data, at)
                        http, _, payload = block.partition(b"\r\n\r\n")
                        n = int(re.search(rb"Content-Length: (\d+)", http)[1])
                        digest = head["WARC-Payload-Digest"].removeprefix("sha1:")
                        if head["WARC-Type"] == "response":
                            n, found = len(payload), hashlib.sha1(payload).hexdigest()
                            if found != digest:
                                raise ValueError(f"payload digest of {head['WARC-Record-ID']} differs")
                        rows.append((number(head["WARC-Record-ID"]), n, digest, head["WARC-Type"], number(head.get("WARC-Refers-To")), head["WARC-Target-URI"], payload if payloads else None))
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], schema=schema)

    return bundles.select("bundle").mapInArrow(kernel, RECORD)


def archive(pages: DataFrame, path: str | None = None) -> DataFrame:
    """Write all pages to bundles under `path` (default: the shared folder) and give the table of bundles read back."""
    spark = pages.sparkSession
    path = path or scratch_path(spark, "warc")
    write_bundles(pages, path)
    return spark.read.schema(BUNDLE).parquet(path)
