"""WARC archives: one gzip member per record, written and read in sequence.

An archive is a row (volume, data) of a table in the shared folder, about ``VOLUME`` bytes of
records each, so that any store Spark can write holds archives; ``data`` is a complete ``.warc.gz``
file. ``read_files`` reads such files from a folder with Spark's binary source.

Pages with equal payloads of at least ``least`` bytes are written once, as the response of the
largest id; the others become revisit records without payload that refer to it. Defined results:
a null payload is empty; a null id is written without an id and is the least; rows that repeat an id and
a payload are all responses if that id is the largest; a damaged record ends the reading of its
archive with a row whose status says why. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksolve.llm.common import heaviest, materialize

VOLUME = 4 << 20
RECORDS = "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, payload binary, status string"
_END = b"\r\n"


def _member(head: list[tuple[str, str]], block: bytes, level: int) -> bytes:
    lines = ["WARC/1.1", *(f"{k}: {v}" for k, v in head), f"Content-Length: {len(block)}", "", ""]
    c = zlib.compressobj(level, zlib.DEFLATED, 31)
    return c.compress("\r\n".join(lines).encode() + block + _END * 2) + c.flush()


def _sha1(data: bytes) -> str:
    return "sha1:" + base64.b32encode(hashlib.sha1(data).digest()).decode()


def _uri(url: str | None) -> str:
    return "".join(c if c.isprintable() and c != " " else "".join(f"%{b:02X}" for b in c.encode()) for c in url or "about:blank")


def _records(page_id: int | None, url: str | None, payload: bytes, refers: int | None, date: str, level: int) -> bytes:
    head = [("WARC-Type", "response" if refers is None else "revisit"), ("WARC-Record-ID", f"<urn:page:{'none' if page_id is None else page_id}>"), ("WARC-Date", date), ("WARC-Target-URI", _uri(url))]
    head += [("WARC-Payload-Digest", _sha1(payload)), ("X-Payload-Length", str(len(payload)))]
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    if refers is not None:
        head += [("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("WARC-Refers-To", f"<urn:page:{refers}>")]
        block = http
    else:
        block = http + payload
    head += [("WARC-Block-Digest", _sha1(block)), ("Content-Type", "application/http; msgtype=response")]
    return _member(head, block, level)


def plan_revisits(pages: DataFrame, page_id: str = "page_id", url: str = "url", payload: str = "html", least: int = 1000) -> DataFrame:
    """page_id, url, payload (binary), refers_to. A hot digest is one row after the partial aggregate, and the pages of the heaviest
    digests stay where they are when they learn their response; the others move once, by digest."""
    rows = pages.select(F.col(page_id).cast("long").alias("page_id"), F.col(url).cast("string").alias("url"), F.coalesce(F.encode(payload, "UTF-8"), F.lit(b"")).alias("payload"))
    named = rows.withColumn("digest", F.when(F.octet_length("payload") >= least, F.sha1("payload")))
    first = named.where("digest IS NOT NULL").groupBy("digest").agg(F.max("page_id").alias("first"), F.count("*").alias("n")).where("n > 1")
    first = materialize(first, "first-pages")
    hot = heaviest(first, "n").drop("n")
    near = named.join(F.broadcast(hot), "digest")
    far = named.join(F.broadcast(hot.select("digest")), "digest", "left_anti")
    # small payloads get a key of their own, so that they do not pile up under null
    far = far.withColumn("digest", F.coalesce("digest", F.concat(F.lit("of page "), F.coalesce(F.col("page_id").cast("string"), F.lit("none")), F.lit("/"), F.length("payload").cast("string"))))
    both = near.unionByName(far.join(first.drop("n"), "digest", "left"))
    return both.select("page_id", "url", "payload", F.when(~F.col("page_id").eqNullSafe(F.col("first")), F.col("first")).alias("refers_to"))


def write_archives(planned: DataFrame, date: str = "2024-01-01T00:00:00Z", level: int = 3) -> DataFrame:
    """volume, records, data: archives in the shared folder."""

    def volumes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n, info = [], 0, _member([("WARC-Type", "warcinfo"), ("WARC-Record-ID", "<urn:page:info>"), ("WARC-Date", date), ("Content-Type", "application/warc-fields")], b"format: WARC File Format 1.1\r\n", level)
        size = 0

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_pydict({"records": pa.array([n], pa.int64()), "data": pa.array([info + b"".join(held)], pa.binary())})

        for batch in batches:
            for i in range(batch.num_rows):
                row = [batch.column(c)[i] for c in range(4)]
                held.append(_records(row[0].as_py(), row[1].as_py(), row[2].as_py(), row[3].as_py(), date, level))
                n, size = n + 1, size + len(held[-1])
                if size >= VOLUME:
                    yield out()
                    held, n, size = [], 0, 0
        if held:
            yield out()

    made = planned.select("page_id", "url", "payload", "refers_to").mapInArrow(volumes, "records long, data binary")
    return materialize(made.select(F.monotonically_increasing_id().alias("volume"), "records", "data"), "warc")


def members(data: bytes, step: int = 1 << 16) -> Iterator[bytes]:
    """The gzip members of an archive, decompressed one after the other in steps of ``step`` bytes."""
    at = 0
    while at < len(data):
        d, parts = zlib.decompressobj(31), []
        while not d.eof:
            if at >= len(data):
                raise ValueError("truncated member")
            parts.append(d.decompress(data[at : at + step]))
            at += min(step, len(data) - at)
        at -= len(d.unused_data)
        yield b"".join(parts)


def parse(record: bytes) -> tuple[dict[str, str], bytes]:
    """Named fields (lower case) and the block, framed by its content length."""
    head, mark, rest = record.partition(_END * 2)
    lines = head.decode("utf-8", "replace").split("\r\n")
    if not mark or not lines[0].startswith("WARC/"):
        raise ValueError("no WARC header")
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    n = int(fields["content-length"])
    if rest[n:] != _END * 2:
        raise ValueError("content length and record differ")
    return fields, rest[:n]


def _page(name: str | None) -> int | None:
    found = (name or "").removeprefix("<urn:page:").rstrip(">")
    return int(found) if found.lstrip("-").isdigit() else None


def _read(data: bytes, payloads: bool) -> Iterator[tuple]:
    try:
        for record in members(data):
            f, block = parse(record)
            kind = f.get("warc-type", "")
            if kind not in ("response", "revisit"):
                continue
            payload, status = block.partition(_END * 2)[2], "ok"
            if "warc-block-digest" in f and f["warc-block-digest"] != _sha1(block):
                status = "block digest differs"
            digest = f.get("warc-payload-digest", "")
            if kind == "response" and digest and digest != _sha1(payload):
                status = "payload digest differs"
            plain = base64.b32decode(digest.removeprefix("sha1:")).hex() if digest.startswith("sha1:") else None
            size = len(payload) if kind == "response" else int(f["x-payload-length"]) if "x-payload-length" in f else None
            yield _page(f.get("warc-record-id")), f.get("warc-target-uri"), kind, _page(f.get("warc-refers-to")), size, plain, payload if payloads and kind == "response" else None, status
    except (ValueError, KeyError, zlib.error) as e:
        yield None, None, None, None, None, None, None, f"unreadable: {e}"


def read_archives(archives: DataFrame, data: str = "data", payloads: bool = True) -> DataFrame:
    """The records of every archive with verified digests: page_id, url, record_type, refers_to, payload_bytes, payload_digest, payload, status."""
    kinds = [pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary(), pa.string()]
    names = ["page_id", "url", "record_type", "refers_to", "payload_bytes", "payload_digest", "payload", "status"]

    def table(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    def records(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for value in batch.column(0):
                rows, size = [], 0
                for row in _read(value.as_py() or b"", payloads):
                    rows.append(row)
                    size += len(row[6] or b"")
                    if len(rows) == 4096 or size >= 1 << 24:
                        yield table(rows)
                        rows, size = [], 0
                if rows:
                    yield table(rows)

    return archives.select(data).mapInArrow(records, RECORDS)


def read_files(spark: SparkSession, path: str) -> DataFrame:
    """The records of the ``.warc.gz`` files under ``path``."""
    return read_archives(spark.read.format("binaryFile").load(path), "content")


def resolve(records: DataFrame) -> DataFrame:
    """Revisit records with the payload of the response that they refer to."""
    own = records.where("record_type = 'response'").select(F.col("page_id").alias("refers_to"), F.col("payload").alias("found"))
    return records.join(own, "refers_to", "left").withColumn("payload", F.coalesce("payload", "found")).select(records.columns)


ORACLE = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html, octet_length(encode(coalesce(html, ''))) AS n FROM pages),
d AS (SELECT *, max(page_id) OVER (PARTITION BY html) AS top FROM p)
SELECT page_id, n::BIGINT AS payload_bytes, sha1(html) AS payload_digest,
       CASE WHEN n >= 1000 AND page_id <> top THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 1000 AND page_id <> top THEN top END AS refers_to
FROM d
"""
