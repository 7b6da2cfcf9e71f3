"""Web archives in ZIP packages: a writer, and a reader that range-reads records in place."""

from __future__ import annotations

import base64
import hashlib
import json
import struct
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trainscape.llm._common import checkpointed, shared_dir, table, text_chunks
from trainscape.llm._storage import RangeReader, join, remove_tree, write_whole

#: Payload bytes after which a package is closed; a task holds one package at a time.
PACKAGE_BYTES = 32_000_000
RECORDS, INDEX = "archive/data.warc.gz", "indexes/index.cdxj"
RECORD_SCHEMA = "page_id long, url string, record_type string, payload binary, payload_bytes long, payload_digest string, refers_to long"
#: Fixed values of the ZIP format.
_LOCAL, _CENTRAL, _END, _END64, _LOCATOR = b"PK\x03\x04", b"PK\x01\x02", b"PK\x05\x06", b"PK\x06\x06", b"PK\x06\x07"
_MAX32, _MAX16 = 0xFFFFFFFF, 0xFFFF


@dataclass(frozen=True)
class Member:
    name: str
    method: int
    size: int
    stored: int
    header: int


def zip_bytes(members: list[tuple[str, bytes]], always64: bool = False) -> bytes:
    """A ZIP package of stored members; ZIP64 records where sizes need them, or always."""
    out, central = bytearray(), bytearray()
    for name, data in members:
        label, crc, at = name.encode(), zlib.crc32(data), len(out)
        large = always64 or max(len(data), at) >= _MAX32
        size = _MAX32 if large else len(data)
        extra = struct.pack("<HHQQ", 1, 16, len(data), len(data)) if large else b""
        out += _LOCAL + struct.pack("<HHHHHIIIHH", 45 if large else 20, 0x800, 0, 0, 0x21, crc, size, size, len(label), len(extra)) + label + extra + data
        extra = struct.pack("<HHQQQ", 1, 24, len(data), len(data), at) if large else b""
        central += _CENTRAL + struct.pack("<HHHHHHIIIHHHHHII", 45, 45 if large else 20, 0x800, 0, 0, 0x21, crc, size, size, len(label), len(extra), 0, 0, 0, 0, _MAX32 if large else at) + label + extra
    start, count = len(out), len(members)
    out += central
    large = always64 or count >= _MAX16 or start >= _MAX32 or len(central) >= _MAX32
    if large:
        end = len(out)
        out += _END64 + struct.pack("<QHHIIQQQQ", 44, 45, 45, 0, 0, count, count, len(central), start) + _LOCATOR + struct.pack("<IQI", 0, end, 1)
    out += _END + struct.pack("<HHHHIIH", 0, 0, *([_MAX16] * 2 if large else [count] * 2), *([_MAX32] * 2 if large else [len(central), start]), 0)
    return bytes(out)


def zip_members(source: RangeReader) -> dict[str, Member]:
    """The members of a package, from its central directory alone."""
    tail_at = max(0, source.size - 22 - _MAX16)
    tail = source.read(tail_at, source.size - tail_at)
    end = tail.rfind(_END)
    if end < 0:
        raise ValueError("no end of central directory: not a ZIP package")
    count, length, start = struct.unpack("<HII", tail[end + 10 : end + 20])
    if (count == _MAX16 or length == _MAX32 or start == _MAX32) and tail_at + end >= 20:
        locator = source.read(tail_at + end - 20, 20)
        if locator[:4] == _LOCATOR:
            record = source.read(struct.unpack("<Q", locator[8:16])[0], 56)
            if record[:4] != _END64:
                raise ValueError("the ZIP64 locator points at no directory")
            count, length, start = struct.unpack("<QQQ", record[32:56])
    directory, at, found = source.read(start, length), 0, {}
    for _ in range(count):
        if directory[at : at + 4] != _CENTRAL:
            raise ValueError("broken central directory")
        (method,) = struct.unpack("<H", directory[at + 10 : at + 12])
        packed, size, n_name, n_extra, n_note = struct.unpack("<IIHHH", directory[at + 20 : at + 34])
        (header,) = struct.unpack("<I", directory[at + 42 : at + 46])
        name = directory[at + 46 : at + 46 + n_name].decode("utf-8", "replace")
        extra = directory[at + 46 + n_name : at + 46 + n_name + n_extra]
        while len(extra) >= 4:
            tag, n = struct.unpack("<HH", extra[:4])
            if tag == 1:
                wide = iter(struct.unpack(f"<{n // 8}Q", extra[4 : 4 + n // 8 * 8]))
                size = next(wide) if size == _MAX32 else size
                packed = next(wide) if packed == _MAX32 else packed
                header = next(wide) if header == _MAX32 else header
            extra = extra[4 + n :]
        found[name] = Member(name, method, size, packed, header)
        at += 46 + n_name + n_extra + n_note
    return found


def data_offset(source: RangeReader, member: Member) -> int:
    """Where a stored member's bytes begin; other methods cannot be read in place."""
    if member.method:
        raise ValueError(f"{member.name} is compressed by method {member.method}; only stored members can be range-read")
    local = source.read(member.header, 30)
    if local[:4] != _LOCAL:
        raise ValueError(f"no local header of {member.name}")
    return member.header + 30 + sum(struct.unpack("<HH", local[26:30]))


def base32_sha1(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_bytes(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, revisit: bool) -> bytes:
    """One record, compressed alone. A revisit keeps the HTTP head with the payload's length, not the payload."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if revisit else http + payload
    target = "".join(c if c.isprintable() and c != " " else "".join(f"%{b:02X}" for b in c.encode("utf-8", "surrogatepass")) for c in url or "about:blank")
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: <urn:page:{page_id}>", f"WARC-Target-URI: {target}", "WARC-Date: 1970-01-01T00:00:00Z", f"WARC-Payload-Digest: sha1:{digest}", "Content-Type: application/http;msgtype=response", f"Content-Length: {len(block)}"]
    if revisit:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    packer = zlib.compressobj(3, zlib.DEFLATED, 31)
    return packer.compress("\r\n".join(head).encode("utf-8", "surrogatepass") + b"\r\n\r\n" + block + b"\r\n\r\n") + packer.flush()


def parse_record(data: bytes) -> dict:
    """A record's headers, payload (None for a revisit) and its full payload's length; checks the digest of a payload that is there."""
    head, _, rest = zlib.decompress(data, 31).partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "surrogatepass").split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = dict(x.split(": ", 1) for x in lines[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    length = int(next(x for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:")).split(b":")[1])
    digest, kind = fields["WARC-Payload-Digest"].removeprefix("sha1:"), fields["WARC-Type"]
    if kind == "response" and (len(payload) != length or base32_sha1(payload) != digest):
        raise ValueError(f"the payload of {fields['WARC-Record-ID']} does not match its digest")
    number = lambda x: None if x is None or x.endswith(":None>") else int(x[len("<urn:page:") : -1])
    return {"page_id": number(fields["WARC-Record-ID"]), "record_type": kind, "payload": payload if kind == "response" else None, "payload_bytes": length, "payload_digest": digest, "refers_to": number(fields.get("WARC-Refers-To"))}


def _write(folder: str, package_bytes: int, always64: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, made = TaskContext.get(), 0
        name = f"part-{task.partitionId():06d}-{task.taskAttemptId()}"  # attempts may hold rows in other orders; only one attempt's names are returned
        records, index, held = bytearray(), [], 0

        def close() -> pa.RecordBatch:
            nonlocal made, held
            uri = join(folder, f"{name}-{made:06d}.wacz")
            write_whole(uri, zip_bytes([(RECORDS, bytes(records)), (INDEX, "".join(index).encode("utf-8", "surrogatepass"))], always64))
            row = pa.RecordBatch.from_arrays([pa.array([uri]), pa.array([len(index)], pa.int64())], ["uri", "records"])
            made, held = made + 1, 0
            records.clear()
            index.clear()
            return row

        for whole in batches:
            for batch in text_chunks(whole, "html"):
                for row in batch.to_pylist():
                    payload = row["html"].encode("utf-8", "surrogatepass")
                    digest = base64.b32encode(bytes.fromhex(row["sha"])).decode()
                    data = record_bytes(row["page_id"], row["url"], payload, digest, row["head"], row["revisit"])
                    index.append(json.dumps({"url": row["url"], "digest": digest, "offset": len(records), "length": len(data)}) + "\n")
                    records += data
                    held += len(payload) + 512
                    if held >= package_bytes:
                        yield close()
        if index:
            yield close()

    return run


def write_archives(pages: DataFrame, folder: str, revisit_bytes: int = 0, package_bytes: int = PACKAGE_BYTES, always64: bool = False) -> DataFrame:
    """Writes (page_id, url, html) rows as packages into a folder; returns (uri, records) of each.

    Of the rows with equal payloads of revisit_bytes bytes or more, those with
    the smallest page_id become response records, the others revisit it. Null
    html is an empty payload, a null url about:blank (the index keeps the null).
    Rows without page_id are written too; they revisit an equal page that has
    one. Which payloads are equal follows from digests alone; a digest shared by
    very many pages is pre-aggregated, and its join can be split.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    rows = rows.withColumn("sha", F.sha1(F.col("html").cast("binary")))
    heads = rows.where(F.octet_length("html") >= revisit_bytes).groupBy("sha").agg(F.min("page_id").alias("head"))
    marked = rows.join(heads, "sha", "left").withColumn("revisit", F.col("head").isNotNull() & ~F.col("head").eqNullSafe(F.col("page_id")))
    return checkpointed(marked.select("page_id", "url", "html", "sha", "head", "revisit").mapInArrow(_write(folder, package_bytes, always64), "uri string, records long"))


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("record_type", pa.string()), ("payload", pa.binary()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("refers_to", pa.int64())])
    for batch in batches:
        for uri in batch.column("uri").to_pylist():
            with RangeReader(uri) as source:
                members = zip_members(source)
                index_at, records_at = data_offset(source, members[INDEX]), data_offset(source, members[RECORDS])
                rows, held = [], 0
                for line in source.read(index_at, members[INDEX].size).decode("utf-8", "surrogatepass").split("\n")[:-1]:
                    entry = json.loads(line)
                    rows.append({"url": entry["url"], **parse_record(source.read(records_at + entry["offset"], entry["length"]))})
                    held += len(rows[-1]["payload"] or b"")
                    if held > 4_000_000 or len(rows) >= 2000:
                        yield pa.RecordBatch.from_pylist(rows, schema)
                        rows, held = [], 0
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, schema)


def read_archives(packages: DataFrame) -> DataFrame:
    """The records of the packages at `uri`: RECORD_SCHEMA; the payload of a revisit is null.

    Nothing is extracted: the directory and the index are read from a package's
    end, then each record by its byte range. A broken package or a payload that
    does not match its digest raises an error.
    """
    return packages.select("uri").repartition(max(1, min(packages.count(), 4096)), "uri").mapInArrow(_read, RECORD_SCHEMA)


def op5_warc_packages(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = join(shared_dir(spark), f"warc-{uuid.uuid4().hex}")
    packages = write_archives(table(spark, sf_dir, "pages"), folder)
    found = checkpointed(read_archives(packages).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"))
    remove_tree(folder)
    return found
