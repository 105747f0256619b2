"""WARC archives as chunked record tables.

``write_archives`` turns pages into WARC/1.1 records and stores them as rows (archive, record,
chunk_no, body) of at most ``CHUNK`` bytes, in Parquet in the shared folder. ``chunk_table`` streams
such rows back: a record is parsed as its chunks pass, so no task ever holds a whole record; each
row carries the running SHA-256 and length of the payload up to and including it, and the last row
of a record its header fields and final digest. Records of one chunk are parsed where they lie;
only the chunks of oversized records are brought together (by record) and put in order.

Of records with equal payloads of at least ``MIN_REVISIT`` bytes the one with the smallest page_id
is the response; the others are revisit records without a payload that name it, its digest and its
length. Digest groups are found from slim rows (id, digest, place) with partial sums; what a page is to
become goes to where its payload is stored (``common.beside``), so payloads are never shuffled, at any
size, and a digest shared by a third of all pages crowds no task.

Edge cases: a null html is an empty payload; a null url is left out; control characters in a url
are escaped; rows with the same page_id and payload are all responses; an empty table gives an
empty result; extra columns are ignored. A response whose payload does not match its digest raises.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

CHUNK, MIN_REVISIT = 1 << 20, 100
#: Fixed value: the profile of revisit records with equal payloads.
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
ARCHIVE_SCHEMA = "archive int, record string, chunk_no int, last boolean, body binary"
CHUNK_SCHEMA = "record string, chunk_no int, last boolean, payload binary, payload_bytes long, payload_digest string, fields map<string,string>"
_CONTROL = re.compile(r"[\x00-\x20\x7f]")


def record_head(kind: str, record: str, length: int, fields: dict[str, str]) -> bytes:
    lines = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <{record}>", *(f"{k}: {v}" for k, v in fields.items()), f"Content-Length: {length}", "", ""]
    return "\r\n".join(lines).encode()


def page_urn(page_id) -> str:
    return f"urn:page:{page_id}"


def _write(chunk: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        archive, no = TaskContext.get().partitionId(), 0
        for batch in batches:
            rows: list[tuple] = []
            held = 0
            for page_id, url, digest, size, first, payload in zip(*[batch.column(i) for i in range(6)], strict=True):
                page_id, url, first = page_id.as_py(), url.as_py(), first.as_py()
                no += 1
                fields = {"WARC-Date": "1970-01-01T00:00:00Z"} | ({"WARC-Target-URI": _CONTROL.sub(lambda m: f"%{ord(m[0]):02X}", url)} if url is not None else {})
                fields["WARC-Payload-Digest"] = f"sha256:{digest.as_py()}"
                body = memoryview(payload.as_py() or b"")
                if first is not None and first != page_id:
                    fields |= {"WARC-Profile": PROFILE, "WARC-Refers-To": f"<{page_urn(first)}>", "WARC-Refers-To-Payload-Length": str(size.as_py())}
                    head, body = record_head("revisit", page_urn(page_id), 0, fields), memoryview(b"")
                else:
                    head = record_head("response", page_urn(page_id), len(body), fields)
                record = f"{archive}/{no}"
                cuts = [0, *range(max(0, chunk - len(head)), len(body), chunk), len(body)] if len(head) + len(body) + 4 > chunk else [0, len(body)]
                last = len(cuts) - 2
                for k in range(last + 1):
                    piece = (head if k == 0 else b"") + bytes(body[cuts[k] : cuts[k + 1]]) + (b"\r\n\r\n" if k == last else b"")
                    rows.append((archive, record, k, k == last, piece))
                    held += len(piece)
                if held > 8 * chunk:
                    yield _rows(rows, ARCHIVE_SCHEMA)
                    rows, held = [], 0
            yield _rows(rows, ARCHIVE_SCHEMA)

    return run


_ARROW = {"int": pa.int32(), "long": pa.int64(), "string": pa.string(), "boolean": pa.bool_(), "binary": pa.binary(), "map<string,string>": pa.map_(pa.string(), pa.string())}


def _rows(rows: list[tuple], schema: str) -> pa.RecordBatch:
    names, kinds = zip(*(c.split(" ") for c in schema.split(", ")), strict=True)
    columns = list(zip(*rows, strict=True)) or [[]] * len(names)
    return pa.RecordBatch.from_arrays([pa.array(list(c), _ARROW[k]) for c, k in zip(columns, kinds, strict=True)], names=list(names))


def write_archives(pages: DataFrame, chunk: int = CHUNK, least: int = MIN_REVISIT) -> DataFrame:
    """Writes a record for each row of (page_id, url, html) to the shared folder; the stored chunk rows."""
    payload = F.coalesce(F.col("html").cast("binary"), F.lit(b""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.sha2(payload, 256).alias("digest"), F.octet_length(payload).cast("long").alias("size"), payload.alias("payload"))
    stored, slots = C.stored_by_task(rows, "pages")
    large = stored.select("_slot", "_row", "page_id", "size", F.when(F.col("size") >= least, F.col("digest")).alias("digest"))
    slim = C.materialize(large, "page-digests")
    digests = slim.filter("digest is not null")
    groups = C.materialize(digests.groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("_n")), "digests")
    first = C.join_hot(digests, groups, "digest", digests.count()).select("_slot", "_row", "first")
    first = first.union(slim.filter("digest is null").select("_slot", "_row", F.lit(None).cast("long")))
    side = first.groupBy("_slot").agg(F.sort_array(F.collect_list(F.struct("_row", "first"))).alias("all")).select("_slot", F.col("all.first").alias("firsts"))
    marked = C.beside(stored, slots, side).select("page_id", "url", "digest", "size", F.get("firsts", F.col("_row").cast("int")).alias("first"), "payload")
    return C.materialize(marked.mapInArrow(_write(chunk), ARCHIVE_SCHEMA), "warc")


class RecordStream:
    """Parser of one record whose bytes come in pieces."""

    def __init__(self) -> None:
        self.head, self.fields, self.left, self.size, self.sha = b"", None, 0, 0, hashlib.sha256()

    def feed(self, data: bytes) -> bytes:
        """The payload bytes among ``data``."""
        if self.fields is None:
            self.head += data
            end = self.head.find(b"\r\n\r\n")
            if end < 0:
                return b""
            lines = self.head[:end].decode().split("\r\n")
            if not lines[0].startswith("WARC/1."):
                raise ValueError(f"not a WARC record: {lines[0][:40]!r}")
            self.fields = dict(x.split(": ", 1) for x in lines[1:])
            self.left, data, self.head = int(self.fields["Content-Length"]), self.head[end + 4 :], b""
        own = data[: self.left]
        self.left -= len(own)
        self.size += len(own)
        self.sha.update(own)
        return own

    def close(self) -> dict[str, str]:
        if self.fields is None or self.left:
            raise ValueError("a WARC record ends early")
        stated = self.fields.get("WARC-Payload-Digest")
        if self.fields["WARC-Type"] == "response" and stated not in (None, f"sha256:{self.sha.hexdigest()}"):
            raise ValueError(f"payload of {self.fields['WARC-Record-ID']} does not match its digest")
        return self.fields


def _read(keep: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stream, record = RecordStream(), None
        for batch in batches:
            rows = []
            for name, no, last, body in zip(*[batch.column(i) for i in range(4)], strict=True):
                name, no, last = name.as_py(), no.as_py(), last.as_py()
                if no == 0:
                    stream, record = RecordStream(), name
                elif name != record:
                    raise ValueError(f"chunks of {name} are out of order")
                own = stream.feed(body.as_py())
                fields = stream.close() if last else None
                rows.append((name, no, last, own if keep else None, stream.size, stream.sha.hexdigest(), list(fields.items()) if last else None))
            yield _rows(rows, CHUNK_SCHEMA)

    return run


def chunk_table(archives: DataFrame, keep_payload: bool = True) -> DataFrame:
    """(record, chunk_no, last, payload, payload_bytes, payload_digest, fields); length and digest are those so far, fields come with the last chunk."""
    columns = ["record", "chunk_no", "last", "body"]
    whole = archives.filter("chunk_no = 0 and last").select(*columns)
    parts = archives.filter("not (chunk_no = 0 and last)").select(*columns).repartition("record").sortWithinPartitions("record", "chunk_no")
    return whole.mapInArrow(_read(keep_payload), CHUNK_SCHEMA).union(parts.mapInArrow(_read(keep_payload), CHUNK_SCHEMA))


def page_records(archives: DataFrame) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to) of every record, from its chunks and header."""
    field = lambda k: F.element_at("fields", k)
    number = lambda c: F.regexp_extract(c, "^<urn:page:(-?[0-9]+)>$", 1)
    as_id = lambda c: F.when(number(c) != "", number(c)).cast("long")
    revisit = field("WARC-Type") == "revisit"
    return chunk_table(archives, False).filter("last").select(
        as_id(field("WARC-Record-ID")).alias("page_id"),
        F.when(revisit, field("WARC-Refers-To-Payload-Length").cast("long")).otherwise(F.col("payload_bytes")).alias("payload_bytes"),
        F.when(revisit, F.substring(field("WARC-Payload-Digest"), 8, 64)).otherwise(F.col("payload_digest")).alias("payload_digest"),
        field("WARC-Type").alias("record_type"),
        as_id(field("WARC-Refers-To")).alias("refers_to"),
    )


def op6_warc_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page written as a WARC record and read back."""
    return page_records(write_archives(C.table(spark, sf_dir, "pages")))


def oracle() -> str:
    return f"""
    with p as (select page_id, strlen(coalesce(html, '')) n, sha256(coalesce(html, '')) d from pages),
    g as (select d, min(page_id) first from p where n >= {MIN_REVISIT} group by d)
    select page_id, n::BIGINT payload_bytes, p.d payload_digest, case when first is null or first = page_id then 'response' else 'revisit' end record_type,
      case when first <> page_id then first end refers_to from p left join g on p.d = g.d and n >= {MIN_REVISIT}"""
