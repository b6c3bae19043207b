"""Operator 8: WARC archives, written by Spark's text sink and read in byte ranges.

Writing: every record is a gzip member. The text sink ends each row with a separator; the separator here is the
NUL byte, which is also the last byte of a member whose record is under 16 MiB (the top byte of its length), so
the file is the plain concatenation of members. Longer records are followed by an empty member, which ends alike.

Reading: the text source splits files into byte ranges and cuts them at the gzip magic, so a task gets exactly the
candidate members that start inside its range. A candidate counts only if its gzip header decodes and its content
starts a WARC record. Magic bytes inside compressed data give false candidates; those are glued back to the member
they belong to. Where such a member runs over the end of a range, its pieces are joined in a second, small step.

Names: Hadoop would decompress ``*.gz`` as one stream, so archives must carry another suffix to be splittable.

Defined cases: a null page has an empty payload; a null ``page_id`` or ``url`` leaves out the header; of rows with
equal payloads, all that have the smallest ``page_id`` are responses; a null id never is another's original;
truncated or damaged members are skipped and reading goes on at the next record; an empty table writes no record.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import scratch_path
from .text import rows_of

MAGIC = b"\x1f\x8b\x08"
LEAST_REVISIT = 100
LEVEL = 4
_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def gzip_member(data: bytes, level: int = LEVEL) -> bytes:
    """A gzip member that ends in a NUL byte."""
    packer = zlib.compressobj(level, zlib.DEFLATED, 31)
    member = packer.compress(data) + packer.flush()
    if member[-1]:
        packer = zlib.compressobj(level, zlib.DEFLATED, 31)
        member += packer.compress(b"") + packer.flush()
    return member


def build_record(page_id, url: str | None, payload: bytes, digest: str, original, date: str) -> bytes:
    """One WARC record; ``original`` is the page that a revisit refers to."""
    revisit = original is not None
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if revisit else http + payload
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}"]
    if page_id is not None:
        head.append(f"WARC-Record-ID: <urn:page:{page_id}>")
    if url is not None:
        head.append(f"WARC-Target-URI: {' '.join(url.split())}")
    head += [f"WARC-Date: {date}", f"WARC-Payload-Digest: sha256:{digest}"]
    if revisit:
        head += [f"WARC-Refers-To: <urn:page:{original}>", f"WARC-Profile: {_PROFILE}"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_record(data: bytes) -> dict | None:
    """Headers and payload of a record; None if it is damaged."""
    head, sep, rest = data.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "replace").split("\r\n")
    if not sep or not lines[0].startswith("WARC/"):
        return None
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    size = fields.get("content-length", "")
    if not size.isdigit() or len(rest) < int(size):
        return None
    block = rest[: int(size)]
    http, sep, payload = block.partition(b"\r\n\r\n") if block.startswith(b"HTTP/") else (b"", b"", block)
    stated = next((x.partition(b":")[2].strip() for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:")), b"")
    return {"fields": fields, "payload": payload, "stated": int(stated) if stated.isdigit() else None}


class Members:
    """Turns the candidates of one byte range, in order, into records and fragments."""

    def __init__(self):
        self.raw: list[bytes] = []
        self.unpacker = None
        self.out: list[bytes] = []
        self.leading = True

    @staticmethod
    def starts_record(candidate: bytes) -> bool:
        """The header decodes, and what follows begins a WARC record."""
        if len(candidate) < 10 or candidate[3] & 0xE0:
            return False
        try:
            return zlib.decompressobj(31).decompress(candidate, 5) == b"WARC/"
        except zlib.error:
            return False

    @staticmethod
    def is_filler(candidate: bytes) -> bool:
        try:
            d = zlib.decompressobj(31)
            return d.decompress(candidate, 1) == b"" and d.eof
        except zlib.error:
            return False

    def feed(self, candidate: bytes) -> tuple[str, bytes] | None:
        """('record', its bytes), ('orphan', raw bytes before the first record of the range) or nothing yet."""
        if self.starts_record(candidate):
            self.raw, self.out, self.unpacker = [], [], zlib.decompressobj(31)
            self.leading = False
        elif self.unpacker is None:
            return ("orphan", candidate) if self.leading and not self.is_filler(candidate) else None
        self.raw.append(candidate)
        try:
            self.out.append(self.unpacker.decompress(candidate))
        except zlib.error:
            self.raw, self.unpacker = [], None
            return None
        if self.unpacker.eof:
            whole, self.raw, self.unpacker = b"".join(self.out), [], None
            return "record", whole
        return None

    def rest(self) -> bytes | None:
        return b"".join(self.raw) if self.unpacker is not None else None


RECORD = "page_id string, url string, record_type string, refers_to string, stated_digest string, stated_bytes bigint, payload binary"
_NAMES = ["kind", "file", "block", "seq", "raw", "page_id", "url", "record_type", "refers_to", "stated_digest", "stated_bytes", "payload"]
_TYPES = [pa.string(), pa.string(), pa.int64(), pa.int64(), pa.binary(), pa.string(), pa.string(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.binary()]


def _page(urn: str | None) -> str | None:
    return urn.strip("<>").removeprefix("urn:page:") if urn else None


def _fields(data: bytes) -> tuple | None:
    found = parse_record(data)
    if found is None:
        return None
    f = found["fields"]
    return (_page(f.get("warc-record-id")), f.get("warc-target-uri"), f.get("warc-type"), _page(f.get("warc-refers-to")), f.get("warc-payload-digest", "").removeprefix("sha256:") or None, found["stated"], found["payload"])


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    at, members, seq, size = None, Members(), 0, 0
    rows: list[tuple] = []

    def table() -> pa.RecordBatch:
        columns = list(zip(*rows, strict=True)) or [()] * len(_NAMES)
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, _TYPES, strict=True)], _NAMES)

    def close() -> None:
        if at is not None and (rest := members.rest()) is not None:
            rows.append(("open", *at, seq, rest, *(None,) * 7))

    for batch in batches:
        for file, block, candidate in zip(rows_of(batch, "file").to_pylist(), rows_of(batch, "block").to_pylist(), rows_of(batch, "candidate"), strict=True):
            if at != (file, block):
                close()
                at, members, seq = (file, block), Members(), 0
            candidate = candidate.as_py()
            if seq == 0 and block == 0 and not candidate:
                seq += 1  # what stands before the file's first magic
                continue
            seq += 1
            found = members.feed(MAGIC + candidate)
            if found and found[0] == "orphan":
                rows.append(("orphan", *at, seq, found[1], *(None,) * 7))
            elif found and (fields := _fields(found[1])):
                rows.append(("record", *at, seq, None, *fields))
                size += len(fields[-1])
            if len(rows) >= 2000 or size > 8 << 20:
                yield table()
                rows, size = [], 0
    close()
    if rows:
        yield table()


def _glue(pieces: pd.DataFrame) -> pd.DataFrame:
    """Records whose members lie across ranges of one file."""
    out, pending = [], None
    for row in pieces.sort_values(["block", "seq"]).itertuples():
        if row.kind == "open":
            pending = bytes(row.raw)
        elif pending is not None:
            pending += bytes(row.raw)
        if pending is None:
            continue
        d = zlib.decompressobj(31)
        try:
            whole = d.decompress(pending)
        except zlib.error:
            pending = None
            continue
        if d.eof:
            fields = _fields(whole)
            if fields:
                out.append(fields)
            pending = None
    return pd.DataFrame(out, columns=_NAMES[5:])


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """One row per record: page_id, url, record_type, refers_to, stated_digest, stated_bytes, payload."""
    candidates = (
        spark.read.option("encoding", "ISO-8859-1").option("lineSep", MAGIC.decode("latin-1")).text(path)
        .select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("block"), F.col("value").cast("binary").alias("candidate"))
    )
    found = candidates.mapInArrow(_scan, f"kind string, file string, block bigint, seq bigint, raw binary, {RECORD}")
    names = _NAMES[5:]
    across = found.where("kind <> 'record'").select(*_NAMES[:5]).groupBy("file").applyInPandas(_glue, RECORD)
    return found.where("kind = 'record'").select(*names).unionByName(across)


def write_warc(pages: DataFrame, path: str, date: str = "2024-01-01T00:00:00Z", least: int = LEAST_REVISIT) -> None:
    """Write a record per row of (page_id, url, html) into a folder of archives."""
    rows = pages.select("page_id", "url", F.coalesce(F.col("html"), F.lit("")).alias("html")).withColumn("digest", F.sha2(F.col("html").cast("binary"), 256))
    long = pages.select("page_id", F.coalesce(F.col("html"), F.lit("")).alias("html")).where(F.octet_length("html") >= least)
    copies = long.select("page_id", F.sha2(F.col("html").cast("binary"), 256).alias("digest")).groupBy("digest").agg(F.min("page_id").alias("original"), F.count("*").alias("n")).where("n > 1").drop("n")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = [rows_of(batch, c) for c in ("page_id", "url", "html", "digest", "original")]
            for i in range(0, batch.num_rows, 500):
                members = []
                for page_id, url, html, digest, original in zip(*(c.slice(i, 500).to_pylist() for c in columns), strict=True):
                    other = None if original is None or original == page_id else original
                    members.append(gzip_member(build_record(page_id, url, html.encode(), digest, other, date))[:-1])
                yield pa.RecordBatch.from_arrays([pa.array(members, pa.binary())], ["member"])

    packed = rows.join(copies, "digest", "left").select("page_id", "url", "html", "digest", "original").mapInArrow(pack, "member binary")
    packed.select(F.col("member").cast("string").alias("value")).write.option("lineSep", "\0").text(path)


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch_path(spark, "warc")
    write_warc(spark.read.parquet(f"{sf_dir}/pages.parquet"), path)
    records = read_warc(spark, path)
    revisit = F.col("record_type") == "revisit"
    return records.select(
        F.col("page_id").cast("long").alias("page_id"),
        F.when(revisit, F.col("stated_bytes")).otherwise(F.octet_length("payload")).cast("long").alias("payload_bytes"),
        F.when(revisit, F.col("stated_digest")).otherwise(F.sha2("payload", 256)).alias("payload_digest"),
        "record_type",
        F.col("refers_to").cast("long").alias("refers_to"),
    )


ORACLE = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html, sha256(coalesce(html, '')) AS digest, strlen(coalesce(html, ''))::BIGINT AS n FROM pages),
     o AS (SELECT digest, min(page_id) AS original FROM p WHERE n >= 100 GROUP BY digest)
SELECT p.page_id, p.n AS payload_bytes, p.digest AS payload_digest,
       CASE WHEN o.original IS NULL OR o.original = p.page_id THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN o.original <> p.page_id THEN o.original END AS refers_to
FROM p LEFT JOIN o USING (digest)
"""
