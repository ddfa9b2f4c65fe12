"""Web archives: writing records, normalising whole-file gzip streams to a member a record, and reading through an index.

An archive is a row (archive, content), as ``binaryFile`` gives it. ``write_archives`` puts all records of an archive
into a single gzip stream, the monolithic form that allows no access to one record. ``normalise`` inflates such a stream
once, piece by piece, writes each record as a gzip member of its own, and adds the sidecar index (record id, type,
offset, length). Archives close at a bounded size, so no task holds more than one of them.
"""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from uncertainseq.llm.common import materialise

REVISIT_BYTES, ROLL, SALTS = 1000, 4 << 20, 32
ARCHIVES = "archive string, content binary"
INDEX = "array<struct<record: string, type: string, offset: bigint, length: bigint>>"
INDEX_TYPE = pa.list_(pa.struct([("record", pa.string()), ("type", pa.string()), ("offset", pa.int64()), ("length", pa.int64())]))
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """One WARC record: a response, or a revisit of the page ``refers_to`` whose block has the HTTP head alone."""
    digest = base64.b32encode(hashlib.sha1(payload).digest()).decode()
    head = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = head if refers_to is not None else head + payload
    fields = [f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", "WARC-Date: 2024-01-01T00:00:00Z", f"WARC-Payload-Digest: sha1:{digest}"]
    if url is not None:
        fields.append("WARC-Target-URI: " + url.replace("\r", "%0D").replace("\n", "%0A"))
    if refers_to is not None:
        fields += [f"WARC-Refers-To: <urn:page:{refers_to}>", f"WARC-Profile: {PROFILE}"]
    fields += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return ("WARC/1.0\r\n" + "\r\n".join(fields) + "\r\n\r\n").encode() + block + b"\r\n\r\n"


def fields_of(head: bytes) -> dict[str, str]:
    """Header fields, names in lower case."""
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in head.decode("utf-8", "replace").split("\r\n")[1:]) if k}


def records_of(pieces: Iterator[bytes]) -> Iterator[bytes]:
    """Cut a stream of bytes into whole records."""
    held, at = bytearray(), 0
    for piece in pieces:
        held += piece
        while (end := held.find(b"\r\n\r\n", at)) >= 0:
            length = int(fields_of(bytes(held[:end]))["content-length"])
            total = end + 4 + length + 4
            if len(held) < total:
                at = end
                break
            yield bytes(held[:total])
            del held[:total]
            at = 0
    if held.strip():
        raise ValueError("the archive ends within a record")


def inflated(content: bytes, step: int = 1 << 16) -> Iterator[bytes]:
    """The bytes of a gzip file of one or more members, each inflated once."""
    at, inflate = 0, zlib.decompressobj(31)
    while at < len(content):
        piece = content[at : at + step]
        at += len(piece)
        while piece:
            yield inflate.decompress(piece)
            piece = inflate.unused_data
            if inflate.eof:
                inflate = zlib.decompressobj(31) if piece or at < len(content) else inflate


def per_record(content: bytes) -> tuple[bytes, list[dict]]:
    """The same records, each a gzip member of its own, and their index."""
    out, index, offset = [], [], 0
    for raw in records_of(inflated(content)):
        fields = fields_of(raw[: raw.index(b"\r\n\r\n")])
        squeeze = zlib.compressobj(6, zlib.DEFLATED, 31)
        member = squeeze.compress(raw) + squeeze.flush()
        index.append({"record": fields["warc-record-id"], "type": fields["warc-type"], "offset": offset, "length": len(member)})
        out.append(member)
        offset += len(member)
    return b"".join(out), index


def read_record(member: bytes) -> tuple[int | None, int, str, str, int | None]:
    """(page_id, payload bytes, SHA-1 of the payload, type, page referred to) of a member; a response's payload is measured, a revisit's is told."""
    raw = zlib.decompress(member, 31)
    cut = raw.index(b"\r\n\r\n")
    fields = fields_of(raw[:cut])
    block = raw[cut + 4 : -4]
    number = lambda x: int(x.removeprefix("<urn:page:").rstrip(">")) if x and x != "<urn:page:>" else None
    inner = block.index(b"\r\n\r\n") + 4
    told = base64.b32decode(fields["warc-payload-digest"].removeprefix("sha1:")).hex()
    if fields["warc-type"] == "revisit":
        return number(fields["warc-record-id"]), int(fields_of(block[: inner - 4])["content-length"]), told, "revisit", number(fields["warc-refers-to"])
    payload = block[inner:]
    digest = hashlib.sha1(payload).hexdigest()
    if digest != told:
        raise ValueError("a payload differs from its digest")
    return number(fields["warc-record-id"]), len(payload), digest, fields["warc-type"], None


def with_revisits(pages: DataFrame, least: int = REVISIT_BYTES) -> DataFrame:
    """(page_id, url, html, keep): keep is the page whose record holds the payload, null where it is the row's own.

    Digests are summed before they meet, and the joined rows are salted, so a payload that many pages share is no hot key.
    """
    html = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    rows = pages.select("page_id", "url", html.alias("html"), F.sha1(html).alias("digest"), F.octet_length(html).alias("bytes"))
    shared = rows.filter(F.col("bytes") >= least).groupBy("digest", "bytes").agg(F.max("page_id").alias("keep"), F.count("*").alias("n")).filter("n > 1").drop("n")
    spread = shared.withColumn("salt", F.explode(F.array(*[F.lit(i) for i in range(SALTS)])))
    salted = rows.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int"))
    joined = salted.join(spread, ["digest", "bytes", "salt"], "left")
    return joined.select("page_id", "url", "html", F.when(F.col("keep") != F.coalesce("page_id", F.col("keep") - 1), F.col("keep")).alias("keep"))


def write_archives(rows: DataFrame, roll: int = ROLL) -> DataFrame:
    """(archive, content) with whole-file gzip streams of the records of (page_id, url, html, keep)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, number, raw = TaskContext.get().partitionId(), 0, 0
        squeeze, parts = zlib.compressobj(6, zlib.DEFLATED, 31), []

        def close() -> pa.RecordBatch:
            name = f"pages-{task:06d}-{number:05d}.warc.gz"
            return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([b"".join([*parts, squeeze.flush()])], pa.binary())], names=["archive", "content"])

        for batch in batches:
            for page, url, html, keep in zip(*(batch.column(k) for k in range(4)), strict=True):
                x = record(page.as_py(), url.as_py(), html.as_py(), keep.as_py())
                parts.append(squeeze.compress(x))
                raw += len(x)
                if raw >= roll:
                    yield close()
                    squeeze, parts, raw, number = zlib.compressobj(6, zlib.DEFLATED, 31), [], 0, number + 1
        if raw:
            yield close()

    return rows.select("page_id", "url", "html", "keep").mapInArrow(run, ARCHIVES)


def normalise(archives: DataFrame) -> DataFrame:
    """(archive, content, index) with a gzip member a record. Content that is normal already comes out as it is; null content is empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, content in zip(batch.column(0), batch.column(1), strict=True):
                members, index = per_record(content.as_py() or b"")
                yield pa.RecordBatch.from_arrays([pa.array([name.as_py()], pa.string()), pa.array([members], pa.binary()), pa.array([index], INDEX_TYPE)], names=["archive", "content", "index"])

    return archives.select("archive", "content").mapInArrow(run, f"{ARCHIVES}, index {INDEX}")


def read_archives(archives: DataFrame) -> DataFrame:
    """A row per record, each cut out of its archive by the index and inflated alone."""
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content, index in zip(batch.column(0), batch.column(1), strict=True):
                whole = memoryview(content.as_buffer())
                rows = [read_record(whole[x["offset"] : x["offset"] + x["length"]]) for x in index.as_py()]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    return archives.select("content", "index").mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def archive_pages(pages: DataFrame, least: int = REVISIT_BYTES) -> DataFrame:
    """The normalised archives of all pages, written to the shared folder: (archive, content, index).

    Null html is empty. Of pages with equal payloads of ``least`` bytes or more the largest page_id holds the payload, the
    others revisit it; rows of one page_id and payload all hold it. A null page_id revisits a known one, and holds its own
    payload where no copy has an id. No rows give no archives; other columns are ignored.
    """
    return materialise(normalise(write_archives(with_revisits(pages, least))), "archives")


def page_records(pages: DataFrame) -> DataFrame:
    """Records of all pages as read back from their archives."""
    return read_archives(archive_pages(pages))


ORACLE = """
with p as (select page_id, coalesce(html, '') h from pages),
d as (select page_id, octet_length(encode(h)) n, sha1(encode(h)) s from p),
k as (select *, max(page_id) over (partition by s, n) keep from d)
select page_id, cast(n as bigint) payload_bytes, s payload_digest, case when n >= 1000 and keep <> page_id then 'revisit' else 'response' end record_type,
  case when n >= 1000 and keep <> page_id then keep end refers_to from k"""
