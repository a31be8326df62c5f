"""Legacy archive converter: ARC files in, equivalent WARC files out, and readers of both.

``write_arc`` builds version 1 and version 2 archives of pages (the legacy input); ``parse_arc`` reads their header
lines, which have five fields in version 1 and ten in version 2, and takes each record by its declared length;
``convert`` synthesises WARC record identifiers, timestamps, types and digests; ``read_warc`` reads the result.
Archives are rows (archive name, bytes) of tables in the shared folder, as only Spark's writers reach every store;
each is a run of gzip members, one for each record, and never larger than ``ARCHIVE_BYTES`` plus one record.

Edge cases: a null html is an empty payload, a null url is ``about:blank``; a null page_id is kept; repeated rows are
records of their own; equal payloads of at least ``min_dedup`` bytes revisit the record with the largest page_id (among
rows of equal page_id the last in archive order is the response); an empty table gives no archive and no row.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import binary_column, materialise

ARCHIVE_BYTES = 4 << 20
BROADCAST_REVISITS = 200_000  # about 40 MB
ARC_DATE = "20240101000000"
V1_FIELDS = "URL IP-address Archive-date Content-type Archive-length"
V2_FIELDS = "URL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length"


def _http(page_id: int | None, payload: bytes) -> bytes:
    name = b"" if page_id is None else b"X-Page-Id: %d\r\n" % page_id
    return b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n" + name + b"Content-Length: %d\r\n\r\n" % len(payload) + payload


def arc_record(version: int, url: str, page_id: int | None, payload: bytes, archive: str, offset: int) -> bytes:
    body = _http(page_id, payload)
    head = [quote(url, safe="!#$&'()*+,/:;=?@[]~%") or "about:blank", "0.0.0.0", ARC_DATE, "text/html"]
    if version == 2:
        head += ["200", hashlib.md5(body).hexdigest(), "-", str(offset), archive]
    return " ".join([*head, str(len(body))]).encode() + b"\n" + body + b"\n"


def arc_head(version: int, archive: str) -> bytes:
    body = f"{version} {'0' if version == 1 else '1'} orbitgraph\n{V1_FIELDS if version == 1 else V2_FIELDS}\n".encode()
    fields = [f"filedesc://{archive}", "0.0.0.0", ARC_DATE, "text/plain"] + (["200", "-", "-", "0", archive] if version == 2 else [])
    return " ".join([*fields, str(len(body))]).encode() + b"\n" + body + b"\n"


def parse_arc(data: bytes) -> Iterator[dict]:
    """Records of an ARC file (gzip members or plain), by the field list of its version and the declared lengths."""
    at, end, fields = 0, len(data), None
    while at < end:
        if data[at : at + 1] == b"\n":  # records end with a line feed
            at += 1
            continue
        stop = data.index(b"\n", at)
        parts = data[at:stop].decode("utf-8", "replace").split(" ")
        length = int(parts[-1])
        body = data[stop + 1 : stop + 1 + length]
        if len(body) < length:
            raise ValueError(f"truncated ARC record at byte {at}: {len(body)} of {length} bytes")
        at = stop + 1 + length
        if parts[0].startswith("filedesc:"):
            lines = body.decode("utf-8", "replace").split("\n")
            version, fields = int(lines[0].split(" ")[0]), lines[1].split(" ")
            if len(fields) != (5 if version == 1 else 10):
                raise ValueError(f"unknown ARC field list: {lines[1]}")
            continue
        if fields is None or len(parts) != len(fields):
            raise ValueError("ARC record does not have the declared fields")
        yield dict(zip(fields, parts, strict=True)) | {"body": body}


def gunzip_members(data: bytes, step: int = 1 << 15) -> bytes:
    """All members of a gzip file, fed in small steps: what is left over after each member is never the whole rest."""
    out, at, view = [], 0, memoryview(data)
    while at < len(data):
        engine = zlib.decompressobj(31)
        while not engine.eof:
            piece = view[at : at + step]
            if not len(piece):
                raise ValueError("truncated gzip member")
            out.append(engine.decompress(piece))
            at += len(piece) - len(engine.unused_data)
    return b"".join(out)


def split_http(body: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields (lower case) and payload of an HTTP response."""
    head, _, payload = body.partition(b"\r\n\r\n")
    fields = (line.split(":", 1) for line in head.decode("latin-1").split("\r\n")[1:] if ":" in line)
    return {k.strip().lower(): v.strip() for k, v in fields}, payload


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def warc_date(arc_date: str) -> str:
    d = (arc_date + "00000000000000")[:14]
    return f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"


def warc_id(*parts: object) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, '|'.join(map(str, parts)))}>"


def warc_record(kind: str, fields: list[tuple[str, str]], block: bytes) -> bytes:
    lines = [f"WARC-Type: {kind}", *(f"{k}: {v}" for k, v in fields), f"Content-Length: {len(block)}"]
    return ("WARC/1.1\r\n" + "\r\n".join(lines) + "\r\n\r\n").encode() + block + b"\r\n\r\n"


def parse_warc(data: bytes) -> Iterator[dict]:
    """Records of a WARC file: header fields by name, and the block as ``body``."""
    at = 0
    while at < len(data):
        stop = data.index(b"\r\n\r\n", at)
        lines = data[at:stop].decode("utf-8", "replace").split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"no WARC record at byte {at}")
        fields = dict(x.split(": ", 1) for x in lines[1:])
        length = int(fields["Content-Length"])
        if len(data) < stop + 8 + length:
            raise ValueError(f"truncated WARC record at byte {at}")
        yield fields | {"body": data[stop + 4 : stop + 4 + length]}
        at = stop + 4 + length + 4


def _member(data: bytes) -> bytes:
    return gzip.compress(data, 1, mtime=0)


def _archive_batch(name: str, parts: list[bytes]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([b"".join(parts)], pa.large_binary()).cast(pa.binary())], names=["archive", "content"])


ARCHIVES = T.StructType([T.StructField("archive", T.StringType()), T.StructField("content", T.BinaryType())])


def write_arc(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """ARC archives of the pages (versions 1 and 2 in turn), materialised in the shared folder."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number, held, size = TaskContext.get().partitionId(), 0, [], 0
        name, version = "", 1
        for batch in batches:
            ids, urls = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for page, url, html in zip(ids, urls, binary_column(batch, "html").to_pylist(), strict=True):
                if not held:
                    name, version = f"legacy-{part:06d}-{number:06d}.arc.gz", 1 + (part + number) % 2
                    held.append(_member(arc_head(version, name)))
                held.append(_member(arc_record(version, url or "about:blank", page, html or b"", name, size)))
                size += len(held[-1])
                if size >= ARCHIVE_BYTES:
                    yield _archive_batch(name, held)
                    number, held, size = number + 1, [], 0
        if held:
            yield _archive_batch(name, held)

    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).alias("html"))
    return materialise(rows.mapInArrow(run, ARCHIVES), "arc")


RECORDS = "archive string, number int, page_id long, url string, arc_date string, payload_bytes long, digest string"


def read_arc(archives: DataFrame) -> DataFrame:
    """One thin row for each ARC record, with the bare base-32 SHA-1 of its payload; payloads stay in the archives."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, content in zip(batch.column(0).to_pylist(), binary_column(batch, "content").to_pylist(), strict=True):
                rows = []
                for i, r in enumerate(parse_arc(gunzip_members(content))):
                    head, payload = split_http(r["body"])
                    page = head.get("x-page-id")
                    rows.append((name, i, None if page is None else int(page), r["URL"], r["Archive-date"], len(payload), base32_sha1(payload)))
                if rows:
                    kinds = (pa.string(), pa.int32(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string())
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=re.findall(r"(\w+) \w+", RECORDS))

    return archives.mapInArrow(run, RECORDS)


def revisits(archives: DataFrame, min_dedup: int = 0) -> DataFrame:
    """One row for each archive: the numbers of its records that revisit another, and that other record.

    The largest record of a payload is an aggregate that combines within each task, so a payload that a third of all
    pages share is no hot group; its join back is a plain shuffle join of thin rows, whose skewed side Spark splits."""
    records = materialise(read_arc(archives), "arc-records")
    lowest = F.lit(-(1 << 62))
    order = F.struct(F.coalesce("page_id", lowest).alias("p"), F.col("archive").alias("a"), F.col("number").alias("n"), F.col("url").alias("u"), F.col("arc_date").alias("d"))
    firsts = records.groupBy("digest", "payload_bytes").agg(F.max(order).alias("m"))
    joined = records.where(F.col("payload_bytes") >= min_dedup).join(firsts, ["digest", "payload_bytes"])
    again = joined.where((F.col("archive") != F.col("m.a")) | (F.col("number") != F.col("m.n")))
    page = F.when(F.col("m.p") > lowest, F.col("m.p"))
    entry = F.struct("number", page.alias("page"), F.col("m.a").alias("archive"), F.col("m.n").alias("first"), F.col("m.u").alias("url"), F.col("m.d").alias("date"))
    return again.groupBy("archive").agg(F.collect_list(entry).alias("again"))


def convert(archives: DataFrame, min_dedup: int = 0) -> DataFrame:
    """WARC archives equivalent to the ARC ones; repeated payloads become revisits of the largest page_id's record."""
    again = materialise(revisits(archives, min_dedup), "revisits")
    few = (again.agg(F.sum(F.size("again"))).first()[0] or 0) <= BROADCAST_REVISITS  # else both sides shuffle by archive
    marked = archives.join(F.broadcast(again) if few else again, "archive", "left").select("archive", "content", "again")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks = batch.column(2).to_pylist()
            for legacy, content, again in zip(batch.column(0).to_pylist(), binary_column(batch, "content").to_pylist(), marks, strict=True):
                first_of = {m["number"]: m for m in again or ()}
                name = re.sub(r"\.arc\.gz$", "", legacy) + ".warc.gz"
                info = b"software: orbitgraph legacy archive converter\r\nformat: WARC File Format 1.1\r\n"
                held = []
                for i, r in enumerate(parse_arc(gunzip_members(content))):
                    date = warc_date(r["Archive-date"])
                    if not held:
                        held.append(_member(warc_record("warcinfo", [("WARC-Record-ID", warc_id(name)), ("WARC-Date", date), ("WARC-Filename", name), ("Content-Type", "application/warc-fields")], info)))
                    block, first = r["body"], first_of.get(i)
                    fields = [("WARC-Record-ID", warc_id(legacy, i)), ("WARC-Date", date), ("WARC-Target-URI", r["URL"]), ("WARC-Payload-Digest", f"sha1:{base32_sha1(split_http(block)[1])}")]
                    if first:
                        block = block.partition(b"\r\n\r\n")[0] + b"\r\n\r\n"
                        fields += [("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("WARC-Refers-To", warc_id(first["archive"], first["first"])), ("WARC-Refers-To-Target-URI", first["url"]), ("WARC-Refers-To-Date", warc_date(first["date"]))]
                        if first["page"] is not None:
                            fields.append(("X-Refers-To-Page", str(first["page"])))
                    fields += [("WARC-Block-Digest", f"sha1:{base32_sha1(block)}"), ("Content-Type", "application/http; msgtype=response")]
                    held.append(_member(warc_record("revisit" if first else "response", fields, block)))
                if held:
                    yield _archive_batch(name, held)

    return materialise(marked.mapInArrow(run, ARCHIVES), "warc")


def read_warc(archives: DataFrame) -> DataFrame:
    """Responses and revisits of WARC archives: page_id, payload length and digest, type, page referred to, url, date, id."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in binary_column(batch, "content").to_pylist():
                rows = []
                for r in parse_warc(gunzip_members(content)):
                    if r["WARC-Type"] not in ("response", "revisit"):
                        continue
                    head, payload = split_http(r["body"])
                    page, first = head.get("x-page-id"), r.get("X-Refers-To-Page")
                    digest = r["WARC-Payload-Digest"].removeprefix("sha1:")
                    if r["WARC-Type"] == "response" and base32_sha1(payload) != digest:
                        raise ValueError(f"payload digest of {r['WARC-Record-ID']} does not hold")
                    rows.append((None if page is None else int(page), int(head["content-length"]), digest, r["WARC-Type"], None if first is None else int(first), r["WARC-Target-URI"], r["WARC-Date"], r["WARC-Record-ID"]))
                if rows:
                    kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.string())
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", "warc_date", "record_id"])

    return archives.mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string, warc_date string, record_id string")
