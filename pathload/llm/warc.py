"""WARC archives: writing, normalising one whole-file gzip stream into members, and reading by offset.

write_archives puts records into archives that are one gzip stream each, the form
that many tools produce and that can't be read from the middle. normalise inflates
such a stream once, piece by piece, writes each record as a gzip member of its own,
and makes a sidecar row (archive, record, offset, length) for it. read_records
opens members by those rows. Archives travel as rows of a Parquet table in the
shared folder; export_files and import_files turn them into .warc.gz and .cdxj files.

Of records with equal payloads the one with the largest id is a response and the
others are revisits of it, found by digest before any payload moves. A task starts a
new archive whenever one has its payload bytes, so no archive holds more than those
and one record, and how many tasks there are follows from the payloads' counted size.

Contracts: a null payload is empty; a page with a null id is a response of its own
and keeps the null; equal rows give equal records; rows of equal id and different
payloads are judged each; an empty table gives no archives; other columns are
ignored. A stream that ends inside a record or a member raises an error.
"""

from __future__ import annotations

import base64
import hashlib
import json
import zlib
from collections.abc import Iterator
from pathlib import Path

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.llm.common import shuffle_parts, staged, table

#: Payload bytes after which an archive ends, and payload bytes of a task, about.
ARCHIVE_BYTES, TASK_BYTES = 16 << 20, 64 << 20
_EPOCH = "2024-01-01T00:00:00Z"  # records carry a fixed date, so that archives are the same after a retry
LEVEL = 3


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_bytes(page: int | None, url: str, payload: bytes, digest: str, refers: int | None, refers_url: str | None) -> bytes:
    """One WARC/1.1 record. A revisit carries no payload, only its digest, size and the record it refers to."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http + (payload if refers is None else b"")
    head = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers is None else 'revisit'}",
        f"WARC-Record-ID: <urn:page:{'none' if page is None else page}>",
        f"WARC-Target-URI: {_clean(url)}",
        f"WARC-Date: {_EPOCH}",
        f"WARC-Payload-Digest: sha1:{digest}",
        f"WARC-Block-Digest: sha1:{base32_sha1(block)}",
        "Content-Type: application/http; msgtype=response",
    ]
    if refers is not None:
        head += [
            "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest",
            f"WARC-Refers-To: <urn:page:{refers}>",
            f"WARC-Refers-To-Target-URI: {_clean(refers_url)}",
        ]
    return "\r\n".join([*head, f"Content-Length: {len(block)}", "", ""]).encode() + block + b"\r\n\r\n"


def _clean(url: str | None) -> str:
    return "".join(c for c in url or "" if c > " ")


class RecordCutter:
    """Cuts a growing stream of bytes into records by their headers' Content-Length."""

    def __init__(self):
        self.held = bytearray()

    def feed(self, data: bytes) -> Iterator[bytes]:
        self.held += data
        at = 0
        while (head := self.held.find(b"\r\n\r\n", at)) >= 0:
            size = next(int(x.split(b":", 1)[1]) for x in bytes(self.held[at:head]).split(b"\r\n") if x.lower().startswith(b"content-length:"))
            end = head + 4 + size + 4
            if end > len(self.held):
                break
            yield bytes(self.held[at:end])
            at = end
        del self.held[:at]


def parse_record(raw: bytes) -> dict:
    """Headers, and the payload behind the HTTP head."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    fields = {k.lower().decode(): v.strip().decode() for k, _, v in (x.partition(b":") for x in head.split(b"\r\n")[1:])}
    http, _, payload = rest[: int(fields["content-length"])].partition(b"\r\n\r\n")
    size = next((int(x.split(b":", 1)[1]) for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:")), len(payload))
    urn = lambda s: None if s is None or s.endswith(":none>") else int(s.strip("<>").rsplit(":", 1)[1])
    return {
        "page_id": urn(fields["warc-record-id"]),
        "url": fields.get("warc-target-uri", ""),
        "record_type": fields["warc-type"],
        "payload_digest": fields["warc-payload-digest"].removeprefix("sha1:"),
        "payload_bytes": size,
        "refers_to": urn(fields.get("warc-refers-to")),
        "payload": payload,
    }


def choose_records(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """(page_id, url, body, refers_to, refers_url): revisits by equal digest, settled on ids and digests alone. body: the payload, deflated for the way."""

    def press(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw = [(x.as_py() or "").encode() for x in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([hashlib.sha1(r).hexdigest() for r in raw]), pa.array([zlib.compress(r, 1) for r in raw], pa.binary())], ["page_id", "url", "hex", "body"])

    pages = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html"))
    light = pages.select("page_id", "url", F.sha1(F.encode("html", "UTF-8")).alias("hex"), F.octet_length("html").alias("size")).where(F.col("page_id").isNotNull() & (F.col("size") >= least_bytes))
    best = light.groupBy("hex").agg(F.max(F.struct("page_id", "url")).alias("top"), F.count(F.lit(1)).alias("n")).where("n > 1")
    revisit = light.join(best, "hex").where(F.col("page_id") < F.col("top.page_id"))
    revisit = revisit.groupBy("page_id", "hex").agg(F.max("top.page_id").alias("refers_to"), F.max("top.url").alias("refers_url"))
    total = pages.agg(F.sum(F.octet_length("html"))).first()[0] or 0
    tasks = max(shuffle_parts(pages.sparkSession), -(-total // TASK_BYTES))
    dealt = pages.select(F.col("page_id").cast("long"), "url", "html").mapInArrow(press, "page_id bigint, url string, hex string, body binary").repartition(tasks, "page_id")
    return dealt.join(revisit, ["page_id", "hex"], "left").drop("hex")


def write_archives(records: DataFrame, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """(archive, content): whole-file gzip streams of the records as tasks get them. archive: the task's number above twenty bits of its own count."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        archive, held, out, stream = TaskContext.get().partitionId() << 20, 0, [], None

        def done() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([archive], pa.int64()), pa.array([b"".join([*out, stream.flush()])], pa.binary())], ["archive", "content"])

        for b in batches:
            for page, url, body, refers, refers_url in zip(*b.columns, strict=True):
                if stream is None:
                    held, out, stream = 0, [], zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
                payload = zlib.decompress(body.as_py())
                out.append(stream.compress(record_bytes(page.as_py(), url.as_py(), payload, base32_sha1(payload), refers.as_py(), refers_url.as_py())))
                held += len(payload)
                if held >= archive_bytes:
                    yield done()
                    archive, stream = archive + 1, None
        if stream is not None:
            yield done()

    return records.select("page_id", "url", "body", "refers_to", "refers_url").mapInArrow(write, "archive bigint, content binary")


def normalise_stream(content: bytes, step: int = 1 << 20) -> tuple[bytes, list[tuple[int, int]]]:
    """A gzip file rewritten with a member for each record, and each member's offset and length.

    The stream is inflated once in steps; files of several members are accepted too.
    """
    cutter, inflate = RecordCutter(), zlib.decompressobj(31)
    out, index, at = [], [], 0
    data, inside = content, False
    while data or inside:
        piece = inflate.decompress(data, step)
        for raw in cutter.feed(piece):
            member = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
            packed = member.compress(raw) + member.flush()
            out.append(packed)
            index.append((at, len(packed)))
            at += len(packed)
        if inflate.eof:
            data, inside, inflate = inflate.unused_data, False, zlib.decompressobj(31)
        elif not piece and not inflate.unconsumed_tail:
            raise ValueError("the gzip stream ends inside a member")
        else:
            data, inside = inflate.unconsumed_tail, True
    if cutter.held:
        raise ValueError(f"{len(cutter.held)} bytes after the last whole record")
    return b"".join(out), index


def normalise(archives: DataFrame) -> DataFrame:
    """(archive, content, offsets, lengths): member-wise archives with their sidecar."""

    def rewrite(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for archive, content in zip(b.column(0), b.column(1), strict=True):
                new, index = normalise_stream(content.as_py())
                yield pa.RecordBatch.from_arrays(
                    [pa.array([archive.as_py()], pa.int64()), pa.array([new], pa.binary()), pa.array([[i[0] for i in index]], pa.list_(pa.int64())), pa.array([[i[1] for i in index]], pa.list_(pa.int64()))],
                    ["archive", "content", "offsets", "lengths"],
                )

    return archives.select("archive", "content").mapInArrow(rewrite, "archive bigint, content binary, offsets array<bigint>, lengths array<bigint>")


def sidecar(normal: DataFrame) -> DataFrame:
    """(archive, record, offset, length), one row for each record."""
    zipped = normal.select("archive", F.posexplode(F.arrays_zip("offsets", "lengths")).alias("record", "place"))
    return zipped.select("archive", "record", F.col("place.offsets").alias("offset"), F.col("place.lengths").alias("length"))


def read_records(normal: DataFrame, with_payload: bool = True) -> DataFrame:
    """One row for each record, each member opened by its own offset and length."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for archive, content, offsets, lengths in zip(*(b.column(i) for i in range(4)), strict=True):
                data = memoryview(content.as_buffer())
                places = list(zip(offsets.as_py(), lengths.as_py(), strict=True))
                for k in range(0, len(places), 256):
                    got = [parse_record(zlib.decompress(data[o : o + n], 31)) for o, n in places[k : k + 256]]
                    col = lambda name, kind: pa.array([g[name] for g in got], kind)  # noqa: B023, E731
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([archive.as_py()] * len(got), pa.int64()), col("page_id", pa.int64()), col("url", pa.string()), col("record_type", pa.string()), col("payload_digest", pa.string()),
                         col("payload_bytes", pa.int64()), col("refers_to", pa.int64()), col("payload", pa.binary()) if with_payload else pa.array([None] * len(got), pa.binary())],
                        ["archive", "page_id", "url", "record_type", "payload_digest", "payload_bytes", "refers_to", "payload"],
                    )

    return normal.select("archive", "content", "offsets", "lengths").mapInArrow(
        read, "archive bigint, page_id bigint, url string, record_type string, payload_digest string, payload_bytes bigint, refers_to bigint, payload binary"
    )


def export_files(normal: DataFrame, folder: str) -> None:
    """Writes .warc.gz files and JSON-lines sidecars into a folder that all executors mount."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for archive, content, offsets, lengths in zip(*(b.column(i) for i in range(4)), strict=True):
                to = Path(folder, f"part-{archive.as_py():012d}.warc.gz")
                for path, data in ((to, content.as_py()), (to.with_suffix(".cdxj"), "".join(json.dumps({"offset": o, "length": n}) + "\n" for o, n in zip(offsets.as_py(), lengths.as_py(), strict=True)).encode())):
                    part = path.with_name(f"{path.name}.{id(b)}.part")
                    part.write_bytes(data)
                    part.replace(path)  # whole or not at all, also after a retry
            yield pa.RecordBatch.from_arrays([b.column(0)], ["archive"])

    Path(folder).mkdir(parents=True, exist_ok=True)
    normal.select("archive", "content", "offsets", "lengths").mapInArrow(write, "archive bigint").write.format("noop").mode("overwrite").save()


def import_files(spark: SparkSession, folder: str) -> DataFrame:
    """(archive, content) of the gzip files of a folder, whole-file streams or members alike."""
    found = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.gz").load(folder)
    return found.select(F.xxhash64("path").alias("archive"), "content")


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    # A task's whole-file streams are normalised where they are made; only the member-wise archives are kept.
    normal = staged(normalise(write_archives(choose_records(table(spark, sf_dir, "pages")))))
    return read_records(normal, with_payload=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


_ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
_DIGIT = "substr('%s', ((('0x' || substr(hex, %d, 5))::INTEGER >> %d) & 31) + 1, 1)"
ORACLE = (
    "WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS n, sha1(coalesce(html, '')) AS hex FROM pages), "
    "d AS (SELECT page_id, n, " + " || ".join(_DIGIT % (_ALPHABET, 5 * i + 1, shift) for i in range(8) for shift in (15, 10, 5, 0)) + " AS digest, max(page_id) OVER (PARTITION BY hex) AS top FROM p) "
    "SELECT page_id, n::BIGINT AS payload_bytes, digest AS payload_digest, CASE WHEN page_id = top THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id = top THEN NULL ELSE top END AS refers_to FROM d"
)
