"""Web archives: writing capture transactions as WARC records, reading them back, and putting transactions together.

A capture is a request, a response (or a revisit of an earlier equal payload) and a metadata record; the first and the
last name the second one through ``WARC-Concurrent-To``, and a revisit names the response that it stands for through
``WARC-Refers-To``. Each record is a gzip member of its own, so that a reader may begin at any record. Members are put
together to chunks of some bytes, and chunks to files, by Spark's committed text writer: what it writes between two chunks is an empty
gzip member, so the archives are plain concatenations of members, lie in any store Spark writes to, and a lost task
leaves no half archive. Archives are read one bounded file at a time, member by member, and cut by ``Content-Length``.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import storage

#: Bytes of a chunk, chunks in a file (a file has their product, or its largest record more), and the smallest payload that a revisit stands for.
CHUNK_BYTES, CHUNKS_PER_FILE, LEAST_REVISIT = 4 << 20, 16, 100
CRLF = "\r\n"
#: Fixed value: a gzip member that holds nothing.
EMPTY_MEMBER = bytes.fromhex("1f8b08000000000000030300") + bytes(8)
LEVEL = 6
#: Fixed value: the date of every record, as the tables have no time of capture.
DATE = "2024-01-01T00:00:00Z"


def revisited(captures: DataFrame, least: int = LEAST_REVISIT) -> DataFrame:
    """(digest, first, first_name): for each payload of at least ``least`` bytes that occurs more than once, its smallest key and that capture's name.

    ``captures`` has (k, digest, n, seq). Partial minima on each task come first, so a payload that a third of all pages
    share sends one row a task. Of repeated keys the smallest ``seq`` responds; null keys come after all others.
    """
    least_row = F.min(F.struct(F.col("k").isNull().alias("none"), "k", "seq"))
    again = captures.where(F.col("n") >= least).groupBy("digest").agg(F.count(F.lit(1)).alias("c"), least_row.alias("r")).where("c > 1")
    return again.select("digest", F.col("r.k").alias("first"), F.col("r.seq").alias("first_seq"))


def _record(kind: Column | str, name: Column, headers: list[Column], body: Column) -> Column:
    """A record as binary; null headers are left out."""
    kind = F.lit(kind) if isinstance(kind, str) else kind
    head = F.concat_ws(CRLF, F.lit("WARC/1.1"), F.concat(F.lit("WARC-Type: "), kind), F.concat(F.lit("WARC-Record-ID: <"), name, F.lit(">")), F.lit(f"WARC-Date: {DATE}"), *headers, F.concat(F.lit("Content-Length: "), F.octet_length(body).cast("string")))
    return F.concat(head.cast("binary"), F.lit(CRLF * 2).cast("binary"), body, F.lit(CRLF * 2).cast("binary"))


def write_archives(pages: DataFrame, path: str, key: str = "page_id", url: str = "url", html: str = "html", least: int = LEAST_REVISIT) -> None:
    """Writes three records a page into gzip-compressed archives below ``path``.

    A null payload is empty, a null url is left out, a null key is written as ``null``. Of equal payloads of at least
    ``least`` bytes the one with the smallest key is the response (of repeated rows of that key, too, all are responses; the
    first of them is referred to), all others are revisits that refer to its record; repeated rows are captures of
    their own. Pages get their numbers once, in a written table, as numbers given on the fly need not be the same twice. The
    table of repeated payloads is written first, so that Spark knows its size: it is broadcast if that is under the session's
    limit and joined by shuffle, with skewed digests split, if not.
    """
    spark = pages.sparkSession
    payload = F.coalesce(F.col(html).cast("binary"), F.lit(b""))
    rows = pages.select(F.col(key).alias("k"), F.regexp_replace(F.col(url), r"[\r\n]+", " ").alias("u"), payload.alias("p"), F.sha2(payload, 256).alias("digest"), F.octet_length(payload).alias("n"), F.monotonically_increasing_id().alias("seq"))
    rows = storage.materialize(rows, "captures")
    again = storage.materialize(revisited(rows, least), "revisited")
    rows = rows.join(again, "digest", "left")
    revisit = F.col("first_seq").isNotNull() & ~F.col("k").eqNullSafe(F.col("first"))
    named = lambda kind, k, seq: F.concat_ws(":", F.lit(f"urn:x-capture:{kind}"), F.coalesce(F.col(k).cast("string"), F.lit("null")), F.substring("digest", 1, 16), F.col(seq).cast("string"))
    name = lambda kind: named(kind, "k", "seq")
    target = F.concat(F.lit("WARC-Target-URI: "), F.col("u"))
    digest = F.concat(F.lit("WARC-Payload-Digest: sha256:"), F.col("digest"))
    to = F.concat(F.lit("WARC-Concurrent-To: <"), name("capture"), F.lit(">"))
    refers = F.when(revisit, F.concat(F.lit("WARC-Refers-To: <"), named("capture", "first", "first_seq"), F.lit(">")))
    text = lambda *lines: F.concat_ws(CRLF, *lines).cast("binary")
    empty = F.lit("")
    ask = text(F.concat(F.lit("GET "), F.coalesce(F.col("u"), F.lit("/")), F.lit(" HTTP/1.1")), F.lit("Accept: text/html"), empty, empty)
    answer = F.concat(text(F.lit("HTTP/1.1 200 OK"), F.lit("Content-Type: text/html; charset=utf-8"), F.concat(F.lit("Content-Length: "), F.octet_length("p").cast("string")), empty, empty), F.when(revisit, F.lit(b"")).otherwise(F.col("p")))
    about = text(F.concat(F.lit("captureKey: "), F.coalesce(F.col("k").cast("string"), F.lit("null"))), F.concat(F.lit("payloadBytes: "), F.octet_length("p").cast("string")), empty)
    three = F.array(
        _record("request", name("request"), [to, target, F.lit("Content-Type: application/http; msgtype=request")], ask),
        _record(F.when(revisit, F.lit("revisit")).otherwise(F.lit("response")), name("capture"), [target, digest, refers, F.when(revisit, F.lit("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")), F.lit("Content-Type: application/http; msgtype=response")], answer),
        _record("metadata", name("metadata"), [to, target, F.lit("Content-Type: application/warc-fields")], about),
    )

    def members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for batch in batches:
            for record in batch.column("record"):
                pack = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
                member = pack.compress(record.as_buffer()) + pack.flush()
                if held and size + len(member) > CHUNK_BYTES:
                    yield pa.RecordBatch.from_arrays([pa.array([b"".join(held)], pa.binary())], names=["chunk"])
                    held, size = [], 0
                held.append(member)
                size += len(member)
        if held:
            yield pa.RecordBatch.from_arrays([pa.array([b"".join(held)], pa.binary())], names=["chunk"])

    chunks = rows.select(F.explode(three).alias("record")).mapInArrow(members, "chunk binary").select(F.col("chunk").cast("string").alias("value"))
    write = chunks.write.option("encoding", "ISO-8859-1").option("lineSep", EMPTY_MEMBER.decode("latin-1")).option("maxRecordsPerFile", CHUNKS_PER_FILE)
    write.text(path)


_LENGTH = re.compile(rb"\r\nContent-Length:[ \t]*(\d+)", re.I)


def members_of(data: bytes) -> Iterator[bytes]:
    """The contents of the gzip members of an archive, one after another; the archive itself, if it is not compressed."""
    if data[:2] != b"\x1f\x8b":
        yield data
        return
    at = memoryview(data)
    while len(at):
        member, out, used, step = zlib.decompressobj(31), [], 0, 1 << 12
        while not member.eof:
            if used >= len(at):
                raise ValueError("the archive ends within a member")
            out.append(member.decompress(at[used : used + step]))
            used, step = used + step, 1 << 18
        at = at[min(used, len(at)) - len(member.unused_data) :]
        yield b"".join(out)


def records_of(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(headers by lower-case name, block) of every record of one archive; a record may be a member, or go over several."""
    rest = b""
    for part in members_of(data):
        rest, at = rest + part if rest else part, 0
        while at < len(rest):
            stop = rest.find(b"\r\n\r\n", at)
            if rest[at : at + 5] not in (b"WARC/", b"WARC/"[: len(rest) - at]):
                raise ValueError("a record does not start where the one before ends")
            if stop < 0:
                break
            head = rest[at:stop]
            size = int(_LENGTH.search(head)[1])
            if len(rest) < stop + 8 + size:
                break
            fields = (line.partition(b":") for line in head.split(b"\r\n")[1:])
            yield {k.decode("utf-8", "replace").lower(): v.decode("utf-8", "replace").strip() for k, _, v in fields}, rest[stop + 4 : stop + 4 + size]
            at = stop + 4 + size
            if rest[at : at + 4] != b"\r\n\r\n":
                raise ValueError("a record does not end after its block")
            at += 4
        rest = rest[at:]
    if rest:
        raise ValueError("the archive ends within a record")


RECORD = "record_id string, record_type string, concurrent_to string, target_uri string, refers_to string, digest string, block_bytes bigint, block binary, payload_sha256 string, payload_bytes bigint"


def read_records(spark: SparkSession, path: str, blocks: bool = False) -> DataFrame:
    """The records of all archives below ``path``; blocks are kept only for metadata records, or for all with ``blocks``.

    ``payload_sha256`` and ``payload_bytes`` are taken from the payload that a response record holds.
    """
    import hashlib

    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("content")

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = [pa.string()] * 6 + [pa.int64(), pa.binary(), pa.string(), pa.int64()]
        names = [c.split()[0] for c in RECORD.split(", ")]
        for batch in batches:
            for value in batch.column("content"):
                rows = []
                for h, block in records_of(value.as_py()):
                    kind, sha, size = h.get("warc-type"), None, None
                    if kind == "response":
                        payload = block[block.find(b"\r\n\r\n") + 4 :]
                        sha, size = hashlib.sha256(payload).hexdigest(), len(payload)
                    rows.append((h["warc-record-id"].strip("<>"), kind, h.get("warc-concurrent-to", "").strip("<>") or None, h.get("warc-target-uri"), h.get("warc-refers-to", "").strip("<>") or None, h.get("warc-payload-digest", "").removeprefix("sha256:") or None, len(block), block if blocks or kind == "metadata" else None, sha, size))
                    if len(rows) == 500:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)
                        rows = []
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)

    return files.mapInArrow(parse, RECORD)


def assemble_transactions(records: DataFrame) -> DataFrame:
    """One nested row per capture: ``capture_id`` and the structs ``request``, ``response`` and ``metadata``.

    Requests and metadata find their capture by their concurrent-to identifier, a response or revisit by its own. A part
    that is missing is null; a record without either kind of identifier is a capture of its own. If a part occurs more
    than once in a transaction, the one with the smallest record id is taken.
    """
    part = F.struct(*[c.split()[0] for c in RECORD.split(", ")])
    kind = F.col("record_type")
    of = lambda *kinds: F.min_by(F.when(kind.isin(*kinds), part), F.when(kind.isin(*kinds), F.col("record_id")))
    return records.groupBy(F.coalesce("concurrent_to", "record_id").alias("capture_id")).agg(of("request").alias("request"), of("response", "revisit").alias("response"), of("metadata").alias("metadata"))


def capture_summary(transactions: DataFrame) -> DataFrame:
    """Digest columns of the captures: key, full payload's bytes and digest, record type, and the key that a revisit refers to."""
    return transactions.select(
        F.expr("try_cast(split_part(capture_id, ':', 4) AS bigint)").alias("page_id"),
        F.coalesce("response.payload_bytes", F.expr("try_cast(regexp_extract(cast(metadata.block AS string), 'payloadBytes: ([0-9]+)', 1) AS bigint)")).alias("payload_bytes"),
        F.coalesce("response.payload_sha256", "response.digest").alias("payload_digest"),
        F.col("response.record_type").alias("record_type"),
        F.expr("try_cast(split_part(response.refers_to, ':', 4) AS bigint)").alias("refers_to"),
    )
