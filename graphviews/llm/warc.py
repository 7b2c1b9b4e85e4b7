"""Legacy archive converter: ARC volumes to WARC records, written and read as archives.

An ARC volume opens with a version block; version 1 header lines have five fields,
version 2 lines ten, and either ends with the length of the block that follows.
Each document becomes a WARC record: ``response`` when its block is an HTTP
answer, ``resource`` otherwise, with a record id and a date made from the line and
SHA-1 digests of block and payload.  Of responses with equal payloads of at least
``least_bytes``, that with the largest id stays, the others become ``revisit``
records that name it and keep the HTTP head only.

Archives are files of one volume each, gzip-compressed, written by Spark's own
writer (committed per task, any file system) and read back as binary files whose
records are cut by their declared lengths.  A volume holds about ``volume_bytes``,
so what a task holds is bounded by that and by its longest record.

Heads and bodies are bytes of any kind, kept as they are; a body sent in chunks stays so in
its record, its payload, whose length and digest are given, is what the chunks hold.

Defined results: null html is the empty payload; a null id is written without its
head field and never counts as the largest; rows repeated with one id are each a
response if theirs is the largest; a declared length beyond the volume gives the
rest of it, marked truncated; a header line of another form is an error; of other
archives, a digest that is missing counts as right, a length that is nowhere is null.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphviews.llm.common import scratch_path, table

VOLUME_BYTES = 8 << 20
#: The fields of ARC header lines by version.
ARC_FIELDS = {
    1: ("url", "ip", "date", "mime", "length"),
    2: ("url", "ip", "date", "mime", "result", "checksum", "location", "offset", "file", "length"),
}
ARC_TITLES = {
    1: "URL IP-address Archive-date Content-type Archive-length",
    2: "URL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length",
}
PAGE_FIELD = "X-Page-Id"
#: A field of our own: the payload's length, which a revisit cannot tell by its block.
LENGTH_FIELD = "X-Payload-Length"


class ArchiveError(ValueError):
    """A header line or record that is not of its format."""


def base32_sha1(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def arc_url(url: str | None) -> str:
    """A URL without blanks or controls, as a header line needs."""
    return re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url or "") or "unknown:"


def arc_line(version: int, **fields) -> bytes:
    return " ".join(str(fields.get(f, "-")) for f in ARC_FIELDS[version]).encode() + b"\n"


def arc_volume(version: int, name: str, date: str, documents: list[tuple[str, str, bytes]]) -> bytes:
    """A volume of (url, mime, block) documents."""
    about = f"{version} 0 -\n{ARC_TITLES[version]}\n".encode()
    parts, at = [], 0

    def add(url: str, mime: str, block: bytes, result: str):
        nonlocal at
        line = arc_line(version, url=url, ip="0.0.0.0", date=date, mime=mime, result=result, offset=at, file=name, length=len(block))
        parts.extend((line, block, b"\n"))
        at += len(line) + len(block) + 1

    add(f"filedesc://{name}", "text/plain", about, "200")
    for url, mime, block in documents:
        add(url, mime, block, "200")
    return b"".join(parts)


@dataclass
class ArcDocument:
    fields: dict[str, str]
    block: bytes
    truncated: bool = False


def read_arc(data: bytes) -> Iterator[ArcDocument]:
    """The documents of a volume, without its version block; the block's first line tells the version."""
    at, version = 0, 0
    while at < len(data):
        if data[at : at + 1] == b"\n":
            at += 1
            continue
        end = data.find(b"\n", at)
        if end < 0:
            raise ArchiveError(f"header line without an end at byte {at}")
        values = data[at:end].decode("utf-8", "replace").rstrip("\r").split(" ")
        known = version or {len(f): v for v, f in ARC_FIELDS.items()}.get(len(values), 0)
        if not known or len(values) != len(ARC_FIELDS[known]) or not values[-1].isdigit():
            raise ArchiveError(f"no version {version or '1 or 2'} header line at byte {at}: {values[:3]}")
        fields = dict(zip(ARC_FIELDS[known], values))
        length = int(values[-1])
        block = data[end + 1 : end + 1 + length]
        at = end + 1 + length
        if not version:
            if not fields["url"].startswith("filedesc:"):
                raise ArchiveError("a volume opens with its version block")
            version = int(block.split(b" ", 1)[0])
            if version not in ARC_FIELDS:
                raise ArchiveError(f"unknown version {version}")
            continue
        yield ArcDocument(fields, block, len(block) < length)


def warc_date(stamp: str) -> str:
    """14 digits, or fewer from the left, as an ISO date."""
    if not stamp.isdigit() or len(stamp) < 4:
        raise ArchiveError(f"no date: {stamp}")
    s = (stamp + "0101000000"[len(stamp) - 4 :])[:14] if len(stamp) < 14 else stamp[:14]
    return f"{s[:4]}-{s[4:6]}-{s[6:8]}T{s[8:10]}:{s[10:12]}:{s[12:14]}Z"


def split_http(block: bytes) -> tuple[bytes, bytes]:
    head, mark, body = block.partition(b"\r\n\r\n")
    return (head + mark, body) if block.startswith(b"HTTP/") and mark else (b"", block)


def payload_of(head: bytes, body: bytes) -> bytes:
    """The body, or what its chunks hold where the head says that it is chunked and it is, to its end."""
    if not re.search(rb"(?mi)^Transfer-Encoding:[ \t]*chunked[ \t]*\r$", head):
        return body
    out, at = [], 0
    while size := re.compile(rb"([0-9A-Fa-f]{1,15})[^\r\n]*\r\n").match(body, at):
        length = int(size[1], 16)
        if length == 0:
            return b"".join(out)
        at = size.end() + length
        if body[at : at + 2] != b"\r\n":
            break
        out.append(body[size.end() : at])
        at += 2
    return body


def converted(doc: ArcDocument) -> dict:
    """What a WARC record says of an ARC document."""
    head, body = split_http(doc.block)
    payload = payload_of(head, body)
    digest = base32_sha1(payload)
    page = re.search(rb"(?mi)^" + PAGE_FIELD.encode() + rb": (-?\d+)\r$", head)
    name = f"{doc.fields['url']} {doc.fields['date']} {page[1].decode() if page else ''} {digest}"
    return {
        "record_id": f"urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, name)}", "url": doc.fields["url"], "date": warc_date(doc.fields["date"]),
        "ip": doc.fields["ip"], "mime": doc.fields["mime"], "type": "response" if head else "resource", "head": head,
        "body": body, "payload_bytes": len(payload), "payload_digest": digest, "truncated": doc.truncated, "page_id": int(page[1]) if page else None,
    }


def warc_record(r: dict) -> bytes:
    """The record's bytes up to the two line ends that close it."""
    block = r["head"] if r["type"] == "revisit" else r["head"] + r["body"]
    lines = ["WARC/1.1", f"WARC-Type: {r['type']}", f"WARC-Record-ID: <{r['record_id']}>", f"WARC-Date: {r['date']}", f"WARC-Target-URI: {r['url']}"]
    if r["ip"] not in (None, "-", "0.0.0.0"):
        lines.append(f"WARC-IP-Address: {r['ip']}")
    if r["truncated"]:
        lines.append("WARC-Truncated: length")
    if r["type"] == "revisit":
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest",
                  f"WARC-Refers-To: <{r['refers_id']}>", f"WARC-Refers-To-Target-URI: {r['refers_url']}", f"WARC-Refers-To-Date: {r['refers_date']}"]
    kind = r["mime"] if r["type"] == "resource" else "application/http;msgtype=response"
    lines.append(f"{LENGTH_FIELD}: {r['payload_bytes']}")
    lines += [f"WARC-Block-Digest: sha1:{base32_sha1(block)}", f"WARC-Payload-Digest: sha1:{r['payload_digest']}", f"Content-Type: {kind}", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def read_warc(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields (lower-cased names) and block of each record of a volume."""
    at = 0
    while at < len(data):
        if data[at : at + 2] == b"\r\n":
            at += 2
            continue
        end = data.find(b"\r\n\r\n", at)
        if not data.startswith(b"WARC/", at) or end < 0:
            raise ArchiveError(f"no record at byte {at}")
        fields, name = {}, None
        for line in data[at:end].decode("utf-8", "replace").split("\r\n")[1:]:
            if line[:1] in (" ", "\t") and name:  # a value goes on in the next line
                fields[name] += f" {line.strip()}"
            elif ":" in line:
                name, value = line.split(":", 1)
                name = name.strip().lower()
                fields[name] = value.strip()
        if not fields.get("content-length", "").isdigit():
            raise ArchiveError(f"no length of the record at byte {at}")
        length = int(fields["content-length"])
        yield fields, data[end + 4 : end + 4 + length]
        at = end + 4 + length


RECORDS = (
    "record_id string, url string, date string, ip string, mime string, type string, head binary, body binary, "
    "payload_bytes long, payload_digest string, truncated boolean, page_id long"
)


def _arrow(rows: list[dict], like: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_pylist(rows, like)


_RECORD_SCHEMA = pa.schema([
    ("record_id", pa.string()), ("url", pa.string()), ("date", pa.string()), ("ip", pa.string()), ("mime", pa.string()), ("type", pa.string()), ("head", pa.binary()),
    ("body", pa.binary()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("truncated", pa.bool_()), ("page_id", pa.int64()),
])


def pages_to_arc(pages: DataFrame, *, page_id: str = "page_id", url: str = "url", html: str = "html", date: str = "20240101000000", volume_bytes: int = VOLUME_BYTES) -> DataFrame:
    """Pages as legacy volumes of one binary column; even partitions write version 1, odd ones version 2."""
    rows = pages.select(F.col(page_id).cast("long").alias("id"), F.col(url).alias("url"), F.coalesce(F.col(html), F.lit("")).cast("binary").alias("body"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        version, held, size, made = 1 + part % 2, [], 0, 0

        def volume():
            nonlocal held, size, made
            data = arc_volume(version, f"part-{part}-{made}.arc", date, held)
            held, size, made = [], 0, made + 1
            return pa.RecordBatch.from_arrays([pa.array([data], pa.binary())], ["volume"])

        for batch in batches:
            for at in range(len(batch)):
                page, where, body = (batch.column(k)[at].as_py() for k in range(3))
                named = f"{PAGE_FIELD}: {page}\r\n" if page is not None else ""
                head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n{named}Content-Length: {len(body)}\r\n\r\n"
                held.append((arc_url(where), "text/html", head.encode() + body))
                size += len(body)
                if size >= volume_bytes:
                    yield volume()
        if held:
            yield volume()

    return rows.mapInArrow(run, "volume binary")


def arc_to_records(volumes: DataFrame, *, volume: str = "volume") -> DataFrame:
    """The documents of ARC volumes (a binary column, as the binary file source has it) as WARC records."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(len(batch)):
                rows, size = [], 0
                for doc in read_arc(_plain(batch.column(0)[at].as_py())):
                    rows.append(converted(doc))
                    size += len(doc.block)
                    if size >= 1 << 20:
                        yield _arrow(rows, _RECORD_SCHEMA)
                        rows, size = [], 0
                if rows:
                    yield _arrow(rows, _RECORD_SCHEMA)

    return volumes.select(F.col(volume)).mapInArrow(run, RECORDS)


def _plain(data: bytes) -> bytes:
    """Unpack gzip, of one member or a member a record; other bytes stay."""
    out = []
    while data[:2] == b"\x1f\x8b":
        unpack = zlib.decompressobj(31)
        out.append(unpack.decompress(data))
        data = unpack.unused_data
    return b"".join(out) if out else data


def with_revisits(records: DataFrame, *, least_bytes: int = 0) -> DataFrame:
    """Responses of equal payloads but the one of the largest page id become revisits of it."""
    same = ["payload_digest", "payload_bytes"]
    kept = (
        records.where((F.col("type") == "response") & (F.col("payload_bytes") >= least_bytes)).groupBy(*same)
        .agg(F.max(F.struct("page_id", "record_id", "url", "date")).alias("kept"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    )
    again = F.col("kept").isNotNull() & (F.col("type") == "response") & ~F.col("page_id").eqNullSafe(F.col("kept.page_id"))
    return records.join(kept.hint("shuffle_hash"), same, "left").select(
        *[c for c in records.columns if c not in ("type", "body")],
        F.when(again, "revisit").otherwise(F.col("type")).alias("type"),
        F.when(again, F.lit(b"")).otherwise(F.col("body")).alias("body"),
        F.when(again, F.col("kept.record_id")).alias("refers_id"), F.when(again, F.col("kept.url")).alias("refers_url"), F.when(again, F.col("kept.date")).alias("refers_date"),
    )


def write_warc(records: DataFrame, path: str, *, volume_bytes: int = VOLUME_BYTES) -> None:
    """Write the records as WARC archives, one volume a file; the text writer takes bytes of any kind as they are."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            for at in range(len(batch)):
                record = warc_record({n: batch.column(n)[at].as_py() for n in batch.schema.names})
                held.append(record)
                size += len(record)
                if size >= volume_bytes:
                    yield pa.RecordBatch.from_arrays([pa.array([b"".join(held)[:-2]], pa.binary())], ["value"])
                    held, size = [], 0
        if held:
            yield pa.RecordBatch.from_arrays([pa.array([b"".join(held)[:-2]], pa.binary())], ["value"])

    volumes = records.mapInArrow(run, "value binary").select(F.col("value").cast("string").alias("value"))
    volumes.write.option("lineSep", "\r\n").option("compression", "gzip").option("maxRecordsPerFile", 1).text(path)


def read_warc_files(spark, path: str) -> DataFrame:
    """Type, ids, page id, payload length and digest of all records under path; digests of payloads are recomputed."""
    fields = "record_id string, type string, page_id long, payload_bytes long, payload_digest string, refers_id string, intact boolean"
    schema = pa.schema([("record_id", pa.string()), ("type", pa.string()), ("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("refers_id", pa.string()), ("intact", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(len(batch)):
                rows = []
                for f, block in read_warc(_plain(batch.column(0)[at].as_py())):
                    head, body = split_http(block)
                    page = re.search(rb"(?mi)^" + PAGE_FIELD.encode() + rb": (-?\d+)\r$", head)
                    said = f.get("warc-payload-digest", "").removeprefix("sha1:") or None
                    if f.get("warc-type") == "revisit":
                        stated = re.search(rb"(?mi)^Content-Length:[ \t]*(\d+)[ \t]*\r$", head)
                        own = f.get(LENGTH_FIELD.lower(), "")
                        size, digest = int(own) if own.isdigit() else int(stated[1]) if stated else None, said
                    else:
                        payload = payload_of(head, body)
                        size, digest = len(payload), base32_sha1(payload)
                    rows.append({
                        "record_id": f.get("warc-record-id", "").strip("<>") or None, "type": f.get("warc-type"), "page_id": int(page[1]) if page else None, "payload_bytes": size,
                        "payload_digest": digest, "refers_id": f.get("warc-refers-to", "").strip("<>") or None,
                        "intact": said in (None, digest) and f.get("warc-block-digest") in (None, f"sha1:{base32_sha1(block)}"),
                    })
                yield _arrow(rows, schema)

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, fields)


def op5_warc_convert(spark, sf_dir):
    path = scratch_path(spark, "warc")
    write_warc(with_revisits(arc_to_records(pages_to_arc(table(spark, sf_dir, "pages")))), path)
    back = read_warc_files(spark, path)
    kept = back.where("type = 'response'").groupBy(F.col("record_id").alias("refers_id")).agg(F.max("page_id").alias("refers_to"))
    return back.join(kept, "refers_id", "left").select(
        "page_id", "payload_bytes", "payload_digest", F.col("type").alias("record_type"), "refers_to", "intact"
    )


#: base32 of 160 bits: 32 letters, each from five bits of the hexadecimal digest.
OP5_SQL = r"""
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
h AS (SELECT page_id, strlen(html)::BIGINT AS n, sha1(html) AS hex FROM p),
bits AS (SELECT page_id, n, hex, array_to_string([right(bin(('0x' || c)::INT + 16), 4) FOR c IN string_split(hex, '')], '') AS b FROM h),
d AS (SELECT page_id, n, hex, array_to_string([substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
  (16 * substr(b, 5 * i + 1, 1)::INT + 8 * substr(b, 5 * i + 2, 1)::INT + 4 * substr(b, 5 * i + 3, 1)::INT + 2 * substr(b, 5 * i + 4, 1)::INT + substr(b, 5 * i + 5, 1)::INT) + 1, 1)
  FOR i IN range(32)], '') AS digest FROM bits),
m AS (SELECT *, max(page_id) OVER (PARTITION BY hex, n) AS top FROM d)
SELECT page_id, n AS payload_bytes, digest AS payload_digest, CASE WHEN page_id = top THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id <> top THEN top END AS refers_to, true AS intact FROM m
"""
