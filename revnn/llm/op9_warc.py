"""WARC archives: deduplicated records, a monolithic-gzip normaliser with offset index, and random reads.

A writer task packs records into archives of bounded size as one gzip stream each (what careless crawlers leave).
The normaliser inflates such a stream once, from front to back, rewrites every record as its own gzip member and notes
(offset, length, uri, type) of each in a sidecar index; a record can then be read without what precedes it.
Archives and index rows are a table in the folder that all executors share, so a lost executor loses nothing, and any
store that Spark can write will do. :func:`write_files` puts the same bytes into plain ``.warc.gz`` files.

Equal payloads are found from (SHA-1, length) pairs alone: partial aggregation, then a join over keys salted by the
page, so that one payload on a third of all pages is spread over many tasks.

Defined cases: null html is an empty payload; payloads below 1000 bytes are always responses; repeated page_ids with
equal payloads are alike (all responses, or all revisits); a null page_id refers to the response if there is another
page with this payload, else is one; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from revnn.llm.common import shared_dir, table

#: Payloads below this many bytes are never replaced by a revisit.
LEAST_SHARED = 1000
#: Uncompressed bytes after which a task begins another archive.
ARCHIVE_BYTES = 16 << 20
SALTS = 32
LEVEL = 1
DATE = "2024-01-01T00:00:00Z"
ARCHIVES = "archive string, body binary, offsets array<long>, lengths array<long>, kinds array<string>"
RECORDS = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"


def plan_records(pages: DataFrame) -> DataFrame:
    """page_id, url, html, sha1, n_bytes, refers_to (null for responses)."""
    p = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html"))
    p = p.withColumns({"sha1": F.sha1(F.col("html").cast("binary")), "n_bytes": F.octet_length("html").cast("long")})
    shared = p.where(F.col("n_bytes") >= LEAST_SHARED).groupBy("sha1", "n_bytes").agg(F.max("page_id").alias("first_id"), F.count(F.lit(1)).alias("copies"))
    shared = shared.where("copies > 1 and first_id is not null").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    p = p.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int"))
    p = p.join(shared.drop("copies"), ["sha1", "n_bytes", "salt"], "left")
    other = F.col("first_id").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first_id"))
    # a revisit has no body: the page itself goes no further
    return p.select("page_id", "url", F.when(~other, F.col("html")).alias("html"), "sha1", "n_bytes", F.when(other, F.col("first_id")).alias("refers_to"))


def record(page_id, url: str | None, html: str | None, sha1: str, n_bytes: int, refers_to) -> bytes:
    """One WARC/1.1 record. The payload is the block of a resource-like response; a revisit has an empty block."""
    body = b"" if refers_to is not None else (html or "").encode()
    head = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>",
        f"WARC-Date: {DATE}",
        f"WARC-Payload-Digest: sha1:{base64.b32encode(bytes.fromhex(sha1)).decode()}",
        f"X-Payload-Length: {n_bytes}",
        "Content-Type: text/html; charset=utf-8",
        f"Content-Length: {len(body)}",
    ]
    if url is not None:
        head.insert(3, "WARC-Target-URI: " + url.replace("\r", "%0D").replace("\n", "%0A"))
    if refers_to is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def split_record(data: bytes | memoryview, at: int = 0) -> tuple[dict[str, str], bytes, int] | None:
    """Headers and block of the record that begins at `at`, and where it ends; None if it isn't whole yet."""
    end = data.find(b"\r\n\r\n", at)
    if end < 0:
        return None
    lines = bytes(data[at:end]).decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError(f"not a WARC record: {lines[0][:40]!r}")
    head = {k.lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    stop = end + 4 + int(head["content-length"])
    return (head, bytes(data[end + 4 : stop]), stop + 4) if len(data) >= stop + 4 else None


def normalise(chunks: Iterator[bytes], level: int = LEVEL) -> Iterator[tuple[bytes, dict[str, str], int, int]]:
    """From the bytes of a .warc.gz of any member layout: (own gzip member, headers, offset, length) of every record.

    The stream is inflated once; at most one record and one chunk are held."""
    inflate, held, offset = zlib.decompressobj(31), bytearray(), 0
    for chunk in chunks:
        while chunk:
            held += inflate.decompress(chunk)
            chunk = inflate.unused_data
            if inflate.eof:
                inflate = zlib.decompressobj(31)
        at = 0
        while found := split_record(held, at):
            head, _, stop = found
            pack = zlib.compressobj(level, zlib.DEFLATED, 31)
            member = pack.compress(bytes(held[at:stop])) + pack.flush()
            yield member, head, offset, len(member)
            offset, at = offset + len(member), stop
        del held[:at]
    held += inflate.flush()
    if held:
        raise ValueError("the archive ends inside a record")


def read_member(body: bytes, offset: int, length: int) -> tuple[dict[str, str], bytes]:
    """A record by its place in the index."""
    found = split_record(zlib.decompress(body[offset : offset + length], 31))
    assert found
    return found[0], found[1]


def _write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows as of plan_records -> archives with their index."""

    def close(pack, parts: list[bytes]) -> pa.RecordBatch:
        stream = b"".join([*parts, pack.flush()])
        body, offsets, lengths, kinds = bytearray(), [], [], []
        for member, head, offset, length in normalise(stream[i : i + (1 << 20)] for i in range(0, len(stream), 1 << 20)):
            body += member
            offsets.append(offset)
            lengths.append(length)
            kinds.append(head["warc-type"])
        name = hashlib.sha1(body).hexdigest()
        return pa.RecordBatch.from_pydict(
            {"archive": [name], "body": [bytes(body)], "offsets": [offsets], "lengths": [lengths], "kinds": [kinds]},
            pa.schema([("archive", pa.string()), ("body", pa.binary()), ("offsets", pa.list_(pa.int64())), ("lengths", pa.list_(pa.int64())), ("kinds", pa.list_(pa.string()))]),
        )

    pack, parts, size = zlib.compressobj(LEVEL, zlib.DEFLATED, 31), [], 0
    for batch in batches:
        for row in zip(*(batch.column(c).to_pylist() for c in ("page_id", "url", "html", "sha1", "n_bytes", "refers_to")), strict=True):
            data = record(*row)
            parts.append(pack.compress(data))
            size += len(data)
            if size >= ARCHIVE_BYTES:
                yield close(pack, parts)
                pack, parts, size = zlib.compressobj(LEVEL, zlib.DEFLATED, 31), [], 0
    if size:
        yield close(pack, parts)


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    number = lambda urn: int(n) if (n := urn.removeprefix("<urn:page:").removesuffix(">")) else None
    for batch in batches:
        for body, offsets, lengths in zip(*(batch.column(c).to_pylist() for c in ("body", "offsets", "lengths")), strict=True):
            out = {"page_id": [], "payload_bytes": [], "payload_digest": [], "record_type": [], "refers_to": []}
            for offset, length in zip(offsets, lengths, strict=True):
                head, block = read_member(body, offset, length)
                digest = base64.b32decode(head["warc-payload-digest"].removeprefix("sha1:")).hex()
                if head["warc-type"] == "response" and (len(block) != int(head["x-payload-length"]) or hashlib.sha1(block).hexdigest() != digest):
                    raise ValueError(f"record {head['warc-record-id']} isn't what was written")
                refers = head.get("warc-refers-to")
                for k, v in zip(out, (number(head["warc-record-id"]), int(head["x-payload-length"]), digest, head["warc-type"], refers and number(refers)), strict=True):
                    out[k].append(v)
            types = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())])
            yield pa.RecordBatch.from_pydict(out, types)


def write_archives(pages: DataFrame, folder: str) -> None:
    """Archives and their offset index as a table under `folder`."""
    plan_records(pages).mapInArrow(_write, ARCHIVES).write.mode("overwrite").option("compression", "none").parquet(folder)


def read_archives(spark: SparkSession, folder: str) -> DataFrame:
    """Every record of every archive, each by its offset, with its digest checked."""
    return spark.read.schema(ARCHIVES).parquet(folder).select("body", "offsets", "lengths").mapInArrow(_read, RECORDS)


def write_files(archives: DataFrame, folder: str) -> DataFrame:
    """Sink for a file system that all executors mount: <archive>.warc.gz and <archive>.idx (offset length type)."""

    def put(batches):
        for batch in batches:
            for name, body, offsets, lengths, kinds in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                with open(f"{folder}/{name}.warc.gz", "wb") as f:
                    f.write(body)
                with open(f"{folder}/{name}.idx", "w") as f:
                    f.writelines(f"{o} {n} {k}\n" for o, n, k in zip(offsets, lengths, kinds, strict=True))
                yield pa.RecordBatch.from_pydict({"archive": [name], "records": pa.array([len(offsets)], pa.int64())})

    return archives.mapInArrow(put, "archive string, records long")


def op9_warc_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    import uuid

    folder = f"{shared_dir(spark)}/warc-{uuid.uuid4().hex}"
    write_archives(table(spark, sf_dir, "pages"), folder)
    return read_archives(spark, folder)


ORACLE = """
with p as (select page_id, encode(coalesce(html, '')) as body from pages),
d as (select page_id, octet_length(body)::bigint as payload_bytes, sha1(body) as payload_digest from p),
m as (select *, max(page_id) over (partition by payload_digest, payload_bytes) as first_id from d)
select page_id, payload_bytes, payload_digest,
       case when payload_bytes < 1000 or page_id = first_id then 'response' else 'revisit' end as record_type,
       case when payload_bytes < 1000 or page_id = first_id then null else first_id end as refers_to
from m
"""
QUERIES = {"op9_warc_archive": op9_warc_archive}
ORACLE_SQL = {"op9_warc_archive": ORACLE}
