"""WARC archives: one gzip member a record, written through Spark's own sink and read back sequentially.

A record is a header block, a payload framed by content-length, and a SHA-1 digest. Equal payloads of a thousand bytes or
more are stored once: the record with the largest id is the response, the others are revisit records that refer to it. The
reader verifies the digest, the stated lengths, and that every member holds one record whole.

Archives go through Spark's text sink, so any store that Spark reaches will do, commits are atomic and a lost task is
written anew. That sink ends each row by a separator; the separator is the zero byte in which a gzip member below
16 MiB ends (the high byte of its length), which is taken off the member first. Larger records are followed by an empty
member, which ends in a zero byte as well and which readers skip. Reading streams each archive through zlib in small
pieces; archives are bounded by ``archive_bytes`` (and one payload), rows repeated under one id included.

Defined cases: null payloads are empty; repeated rows are written as they are, all rows that share the largest id are
responses; null ids are written as the empty string and lose to any other id (rows that all lack one are all responses); an
empty table writes no archive and reads as an empty result; other columns are not archived.
"""

from __future__ import annotations

import hashlib
import io
import uuid
import zlib
from collections.abc import Iterator
from datetime import UTC, datetime

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from shardweave.staging import fresh_path, stage

LEAST = 1000
#: Fixed value: the profile of revisits whose payload is known by its digest.
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
ARCHIVE_BYTES = 32 << 20
PIECE = 64 << 10
END = b"\r\n\r\n"

RECORD = "page_id long, url string, payload binary, payload_bytes long, payload_digest string, record_type string, refers_to long"
#: An empty gzip member: its last four bytes, the length, are zero.
NOTHING = zlib.compressobj(6, zlib.DEFLATED, 31).flush()


def plan_records(df: DataFrame, id_col: str, url: str | None, payload: str, least: int = LEAST, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """id, url, payload bytes, digest, and which record another one stands for. Equal payloads are equal digests and lengths."""
    body = F.coalesce(F.col(payload).cast("binary"), F.lit(b""))
    rows = df.select(F.col(id_col).alias("page_id"), (F.col(url) if url else F.lit(None)).cast("string").alias("url"), body.alias("payload"))
    rows = rows.withColumns({"payload_digest": F.sha1("payload"), "payload_bytes": F.octet_length("payload").cast("long"), "key": F.coalesce(F.col("page_id").cast("string"), F.lit(""))})
    same = ["payload_digest", "payload_bytes"]
    groups = stage(rows.groupBy("page_id", "key", *same).agg(F.count("*").alias("n")), "warc-groups")
    large = groups.where(F.col("payload_bytes") >= least)
    keep = large.groupBy(*same).agg(F.max("page_id").alias("refers_to"), F.count("*").alias("kinds")).where("kinds > 1 and refers_to is not null").drop("kinds")
    again = large.join(keep, same).where(~F.col("page_id").eqNullSafe(F.col("refers_to"))).select(F.col("key").alias("of"), F.col("payload_digest").alias("with"), "refers_to")
    facts = groups.agg(F.sum(F.col("n") * F.col("payload_bytes")).alias("all"), F.max(F.col("n") * F.col("payload_bytes")).alias("most")).first()
    # Payloads move once: dealt by id and digest, which spreads equal payloads and serves the join, and rows of one id and
    # payload that outgrow an archive by a salt as well.
    salts = max(1, -(-(facts["most"] or 0) // archive_bytes))
    salt = F.pmod(F.monotonically_increasing_id(), F.lit(salts)).cast("int")
    dealt = rows.withColumn("salt", salt).repartition(max(2, -(-(facts["all"] or 0) // archive_bytes)), "key", "payload_digest", "salt")
    every = again.withColumn("grain", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    met = dealt.join(every, (dealt["key"] == every["of"]) & (dealt["payload_digest"] == every["with"]) & (dealt["salt"] == every["grain"]), "left")
    return met.drop("key", "salt", "of", "with", "grain")


def record_id(page_id, digest: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{page_id}|{digest}')}>"


def record(page_id, url, payload: bytes, digest: str, refers_to, date: str = "1970-01-01T00:00:00Z") -> bytes:
    """One record before compression."""
    kind = "response" if refers_to is None else "revisit"
    body = payload if refers_to is None else b""
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {record_id(page_id, digest)}", f"WARC-Date: {date}", f"WARC-Target-URI: {(url or '').translate(BREAKS)}",
        f"X-Page-ID: {'' if page_id is None else page_id}", f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {len(payload)}",
        "Content-Type: text/html; charset=utf-8", f"Content-Length: {len(body)}",
    ]
    if refers_to is not None:
        head += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {record_id(refers_to, digest)}", f"X-Refers-To-Page-ID: {refers_to}"]
    return "\r\n".join(head).encode() + END + body + END


BREAKS = {10: "%0A", 13: "%0D"}


def member(raw: bytes) -> bytes:
    """A gzip member without its last byte, a zero, which the sink puts back."""
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    out = packer.compress(raw) + packer.flush()
    if out[-1]:
        out += NOTHING
    return out[:-1]


def write(
    df: DataFrame, path: str, id_col: str = "page_id", url: str | None = "url", payload: str = "html", least: int = LEAST, archive_bytes: int = ARCHIVE_BYTES, date: str | None = None
) -> None:
    """Archives of ``df`` in the folder ``path``. Rows are dealt out anew so that one archive holds about ``archive_bytes`` of
    payload. ``date``: when the pages were captured, in the form of ISO 8601; by default now, the same for all records."""
    when = date or datetime.now(UTC).strftime("%Y-%m-%dT%H:%M:%SZ")

    def members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = zip(*(batch.column(n).to_pylist() for n in ("page_id", "url", "payload", "payload_digest", "refers_to")), strict=True)
            yield pa.RecordBatch.from_arrays([pa.array([member(record(*r, when)) for r in rows], pa.binary())], names=["member"])

    made = plan_records(df, id_col, url, payload, least, archive_bytes).mapInArrow(members, "member binary")
    made.select(F.col("member").cast("string").alias("value")).write.option("lineSep", "\0").option("compression", "none").mode("errorifexists").text(path)


class Member(io.RawIOBase):
    """The bytes of the gzip member that begins at ``at``, inflated piece by piece; ``at`` ends behind it."""

    def __init__(self, packed: memoryview, at: int):
        self.packed, self.at, self.zip, self.ready = packed, at, zlib.decompressobj(31), b""

    def readable(self) -> bool:
        return True

    def readinto(self, into) -> int:
        while not self.ready:
            if self.zip.eof:
                return 0
            more = self.zip.unconsumed_tail
            if not more:
                more = self.packed[self.at : self.at + PIECE]
                self.at += len(more)
                if not len(more):
                    raise ValueError("an archive ends inside a gzip member")
            self.ready = self.zip.decompress(more, PIECE)
            if self.zip.eof:
                self.at -= len(self.zip.unused_data)
        n = min(len(into), len(self.ready))
        into[:n] = self.ready[:n]
        self.ready = self.ready[n:]
        return n


def records(packed: bytes) -> Iterator[dict]:
    """Records of an archive in order; a payload that doesn't match its digest or length, or a member that isn't one record, is an error."""
    view, at = memoryview(packed), 0
    while at < len(view):
        raw = Member(view, at)
        stream = io.BufferedReader(raw, PIECE)
        line = stream.readline()
        if line:
            yield _record(line, stream)
            if stream.read(1):
                raise ValueError("a gzip member holds more than one record")
        at = raw.at


def _record(line: bytes, stream: io.BufferedReader) -> dict:
    if line.strip() != b"WARC/1.1":
        raise ValueError(f"no record begins at {line[:40]!r}")
    head: dict[str, str] = {}
    while line := stream.readline().rstrip(b"\r\n"):
        name, _, value = line.decode().partition(":")
        head[name.lower()] = value.strip()
    named = head.get("warc-record-id")
    lacking = [k for k in ("warc-record-id", "warc-date", "warc-type", "content-length", "warc-payload-digest", "x-payload-length") if k not in head]
    if lacking:
        raise ValueError(f"record {named} lacks {lacking}")
    size = int(head["content-length"])
    body = stream.read(size)
    if len(body) != size or stream.read(len(END)) != END:
        raise ValueError(f"record {named} is cut short")
    digest, stated, kind = head["warc-payload-digest"].removeprefix("sha1:"), int(head["x-payload-length"]), head["warc-type"]
    number = lambda k: int(head[k]) if head.get(k) else None
    if kind == "response" and (hashlib.sha1(body).hexdigest() != digest or stated != size):
        raise ValueError(f"record {named} doesn't match its digest or length")
    if kind == "revisit" and (size or number("x-refers-to-page-id") is None):
        raise ValueError(f"record {named} is no revisit without a payload")
    return {
        "page_id": number("x-page-id"), "url": head.get("warc-target-uri") or None, "payload": body, "payload_bytes": stated,
        "payload_digest": digest, "record_type": kind, "refers_to": number("x-refers-to-page-id"),
    }


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("payload", pa.binary()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())])
    for batch in batches:
        for packed in batch.column("content"):
            held, size = [], 0
            for r in records(packed.as_py()):
                held.append(r)
                size += len(r["payload"])
                if len(held) >= 1000 or size > 4 << 20:
                    yield pa.RecordBatch.from_pylist(held, names)
                    held, size = [], 0
            if held:
                yield pa.RecordBatch.from_pylist(held, names)


def read(spark: SparkSession, path: str) -> DataFrame:
    """Records of all archives in the folder ``path``."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")
    return files.mapInArrow(_read, RECORD)


def round_trip(df: DataFrame, **how) -> DataFrame:
    """``df`` written to archives in the shared folder and read back."""
    path = fresh_path(df.sparkSession, "warc")
    write(df, path, **how)
    return read(df.sparkSession, path)


def digest(df: DataFrame) -> DataFrame:
    columns: list[str | Column] = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    return df.select(*columns)
