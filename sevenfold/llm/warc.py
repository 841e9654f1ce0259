"""WARC archives: writing, normalising monolithic gzip, offset indexes, reading back.

A monolithic archive is one gzip stream around many records, so no record can be
read alone. The normaliser inflates such a stream once, writes every record as a
gzip member of its own and a sidecar index of offsets. All files go through
Spark's writers and readers, so any store that Spark reaches will do.
"""

from __future__ import annotations

import gzip
import io
import json
import uuid
import zlib
from collections.abc import Iterator

import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sevenfold.llm.common import durable, shared_dir, small_side

#: Payloads shorter than this are never revisited.
LEAST_REVISIT = 1000
#: Bytes of records, before compression, at which an archive is closed.
ARCHIVE_BYTES = 16 << 20
CHUNK = 1 << 16
LEVEL = 6
CRAWLED = "2024-01-01T00:00:00Z"
#: An empty gzip member. Spark's text writer ends each row with a separator; as an
#: empty member it leaves a chain of gzip members valid.
EMPTY_MEMBER = gzip.compress(b"", mtime=0)


# --------------------------------------------------------------------------- records
def _uri(value) -> str:
    return "".join(c if " " < c != "\x7f" else "".join(f"%{b:02X}" for b in c.encode("utf-8", "surrogatepass")) for c in value) if isinstance(value, str) and value else "urn:none"


def record_bytes(page_id, url, payload: bytes, digest: str, revisits=None) -> bytes:
    """One record: the response with its payload, or a revisit without."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    block = http + (b"" if revisits is not None else payload)
    name = lambda page: f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page}:{digest}')}>"
    lines = [
        "WARC/1.1",
        f"WARC-Type: {'response' if revisits is None else 'revisit'}",
        f"WARC-Record-ID: {name(page_id)}",
        f"WARC-Date: {CRAWLED}",
        f"WARC-Target-URI: {_uri(url)}",
        f"WARC-Payload-Digest: sha1:{digest}",
        f"X-Payload-Bytes: {len(payload)}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if page_id is not None:
        lines.append(f"X-Page-Id: {page_id}")
    if revisits is not None:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {name(revisits)}", f"X-Refers-To-Page: {revisits}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_header(head: bytes) -> dict[str, str]:
    """Fields of a record's header, names in lower case."""
    lines = head.decode("utf-8", "replace").split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError(f"not a WARC record: {lines[0][:40]!r}")
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:] if x)}


class RecordReader:
    """Cuts a stream of inflated bytes into records, holding one record at a time."""

    def __init__(self):
        self.buffer, self.need = bytearray(), 0

    def feed(self, data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
        self.buffer += data
        at = 0
        while True:
            if not self.need:
                end = self.buffer.find(b"\r\n\r\n", at)
                if end < 0:
                    break
                self.head = parse_header(bytes(self.buffer[at:end]))
                self.need = end + 4 - at + int(self.head["content-length"]) + 4
            if len(self.buffer) - at < self.need:
                break
            yield self.head, bytes(self.buffer[at : at + self.need])
            at += self.need
            self.need = 0
        del self.buffer[:at]

    def end(self):
        if self.buffer:
            raise ValueError(f"the archive ends inside a record; {len(self.buffer)} bytes are left")


def inflate(data) -> Iterator[tuple[bytes, int, int]]:
    """Inflated chunks of a chain of gzip members, each with the member's offset and its end if it ends there, else -1."""
    view, at = memoryview(data), 0
    while at < len(view):
        begin, inner = at, zlib.decompressobj(31)
        while not inner.eof:
            if at >= len(view):
                raise ValueError("a gzip member is cut off")
            piece = view[at : at + CHUNK]
            out = inner.decompress(piece)
            at += len(piece) - len(inner.unused_data)
            yield out, begin, at if inner.eof else -1


def normalise(data, archive: str) -> tuple[bytes, list[dict]]:
    """One pass over a monolithic stream: the chain of one-record members, and their index."""
    out, index, reader = io.BytesIO(), [], RecordReader()
    for chunk, _, _ in inflate(data):
        for head, record in reader.feed(chunk):
            pack = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
            member = pack.compress(record) + pack.flush()
            index.append({"archive": archive, "offset": out.tell(), "length": len(member), "type": head.get("warc-type"), "uri": head.get("warc-target-uri"), "id": head.get("warc-record-id"), "digest": head.get("warc-payload-digest", "").removeprefix("sha1:")})
            out.write(member)
    reader.end()
    return out.getvalue(), index


def read_record(data, offset: int, length: int) -> tuple[dict[str, str], bytes]:
    """The one record at an index entry, without inflating any other."""
    record = zlib.decompress(memoryview(data)[offset : offset + length], 31)
    end = record.index(b"\r\n\r\n")
    head = parse_header(record[:end])
    return head, record[end + 4 : end + 4 + int(head["content-length"])]


# ------------------------------------------------------------------- writing, reading
def _write_files(rows: DataFrame, path: str, by: list[str]) -> None:
    """One file per row of (data binary, *by), in folders named by the columns ``by``."""
    (
        rows.select(F.col("data").cast("string").alias("value"), *by)
        .write.partitionBy(*by)
        .option("encoding", "ISO-8859-1")
        .option("lineSep", EMPTY_MEMBER.decode("latin-1"))
        .option("maxRecordsPerFile", 1)
        .mode("overwrite")
        .text(path)
    )


def _files(spark, path: str) -> DataFrame:
    return spark.read.format("binaryFile").option("recursiveFileLookup", "false").load(path)


def assign_records(pages: DataFrame) -> DataFrame:
    """page_id, url, payload, payload_digest, payload_bytes, refers_to of every page.

    Of equal payloads of ``LEAST_REVISIT`` bytes or more the largest page_id is
    the response; rows that tie in it are all responses. Payloads are equal when
    their SHA-1, their SHA-256 and their lengths are, so known collisions of SHA-1
    aren't taken for copies. Copies are aggregated before they shuffle.
    """
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    rows = pages.select("page_id", "url", payload.alias("payload"), F.sha1(payload).alias("payload_digest"), F.octet_length(payload).cast("long").alias("payload_bytes"))
    rows = rows.withColumn("second", F.sha2(F.when(F.col("payload_bytes") >= LEAST_REVISIT, F.col("payload")), 256))
    large = rows.where(F.col("payload_bytes") >= LEAST_REVISIT)
    first = large.groupBy(F.col("payload_digest").alias("g_digest"), F.col("second").alias("g_second"), F.col("payload_bytes").alias("g_bytes")).agg(F.max("page_id").alias("first_id"), F.count("*").alias("n")).where("n > 1").drop("n")
    side = small_side(durable(first))
    same = (rows["payload_digest"] == side["g_digest"]) & (rows["second"] == side["g_second"]) & (rows["payload_bytes"] == side["g_bytes"])
    revisits = F.when(F.col("first_id").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first_id")), F.col("first_id"))
    return rows.join(side, same, "left").select("page_id", "url", "payload", "payload_digest", "payload_bytes", revisits.alias("refers_to"))


def write_monolithic(records: DataFrame, path: str, archive_bytes: int = ARCHIVE_BYTES) -> None:
    """Archives of one gzip stream each, of about ``archive_bytes`` of records.

    Ids travel as text: as numbers, a batch that holds a null would turn them to
    floating point, and large ids would change.
    """

    def pack(batches):
        part, number = TaskContext.get().partitionId(), 0
        stream, size = zlib.compressobj(LEVEL, zlib.DEFLATED, 31), 0
        out: list[bytes] = []
        for batch in batches:
            for row in batch.itertuples(index=False):
                record = record_bytes(row.page_id, row.url, bytes(row.payload), row.payload_digest, row.refers_to)
                out.append(stream.compress(record))
                size += len(record)
                if size >= archive_bytes:
                    out.append(stream.flush())
                    yield pd.DataFrame({"archive": [f"a{part:06d}-{number:05d}"], "data": [b"".join(out)]})
                    stream, size, out, number = zlib.compressobj(LEVEL, zlib.DEFLATED, 31), 0, [], number + 1
        if size:
            out.append(stream.flush())
            yield pd.DataFrame({"archive": [f"a{part:06d}-{number:05d}"], "data": [b"".join(out)]})

    named = records.withColumn("page_id", F.col("page_id").cast("string")).withColumn("refers_to", F.col("refers_to").cast("string"))
    _write_files(named.mapInPandas(pack, "archive string, data binary"), path, ["archive"])


def normalise_archives(spark, source: str, target: str) -> None:
    """Rewrite every archive below ``source`` (archive=NAME/...) to ``target``.

    archive=NAME/kind=warc has the chain of members, archive=NAME/kind=index the
    sidecar: gzipped JSON lines in the order of the offsets.
    """

    def rewrite(batches):
        for batch in batches:
            for name, content in zip(batch["archive"], batch["content"], strict=True):
                chain, index = normalise(content, name)
                lines = "".join(json.dumps(x) + "\n" for x in index).encode()
                yield pd.DataFrame({"archive": [name] * 2, "kind": ["warc", "index"], "data": [chain, gzip.compress(lines, mtime=0)]})

    found = _files(spark, source).select(F.col("archive").cast("string").alias("archive"), "content")
    _write_files(found.mapInPandas(rewrite, "archive string, kind string, data binary"), target, ["archive", "kind"])


def read_index(spark, path: str) -> DataFrame:
    """The entries of all sidecars: archive, offset, length, type, uri, id, digest."""

    def lines(batches):
        for batch in batches:
            for content in batch["content"]:
                rows = [json.loads(x) for x in gzip.decompress(bytes(content)).splitlines()]
                if rows:
                    yield pd.DataFrame(rows)

    files = _files(spark, path).where("kind = 'index'").select("content")
    return files.mapInPandas(lines, "archive string, offset long, length long, type string, uri string, id string, digest string")


READ = "archive string, offset long, length long, page_id string, payload_bytes long, payload_digest string, record_type string, refers_to string"


def read_archives(spark, path: str) -> DataFrame:
    """Every record of the normalised archives, member by member.

    Digest and length of a response are those of the payload read; a revisit has
    those that its header names.
    """
    import hashlib

    def records(batches):
        for batch in batches:
            for name, content in zip(batch["archive"], batch["content"], strict=True):
                rows, held = [], bytearray()
                for chunk, begin, end in inflate(content):
                    held += chunk
                    if end < 0 or not held:
                        continue
                    record, held = bytes(held), bytearray()
                    cut = record.index(b"\r\n\r\n")
                    head = parse_header(record[:cut])
                    block = record[cut + 4 : cut + 4 + int(head["content-length"])]
                    payload = block[block.index(b"\r\n\r\n") + 4 :]
                    kind = head["warc-type"]
                    full = (len(payload), hashlib.sha1(payload).hexdigest()) if kind == "response" else (int(head["x-payload-bytes"]), head["warc-payload-digest"].removeprefix("sha1:"))
                    rows.append((name, begin, end - begin, head.get("x-page-id"), *full, kind, head.get("x-refers-to-page")))
                yield pd.DataFrame(rows, columns=["archive", "offset", "length", "page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])

    files = _files(spark, path).where("kind = 'warc'").select(F.col("archive").cast("string").alias("archive"), "content")
    found = files.mapInPandas(records, READ)
    return found.withColumn("page_id", F.col("page_id").cast("long")).withColumn("refers_to", F.col("refers_to").cast("long"))


def _remove(spark, path: str) -> None:
    jvm = spark._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def op6_warc(spark, sf_dir: str) -> DataFrame:
    """Write all pages to monolithic archives, normalise these, and read them back.

    Each record comes back with its place in the normalised archives; its entry in
    the sidecar index must name the same place. Null html is an empty payload, a
    null page_id comes back null, repeated rows are records of their own. An
    empty table writes no archive and gives no rows.
    """
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    root = f"{shared_dir(spark).rstrip('/')}/warc-{uuid.uuid4().hex}"
    records = assign_records(pages)
    if not records.limit(1).count():
        return spark.createDataFrame([], "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")
    write_monolithic(records, f"{root}/monolithic")
    normalise_archives(spark, f"{root}/monolithic", f"{root}/normalised")
    _remove(spark, f"{root}/monolithic")
    back = read_archives(spark, f"{root}/normalised")
    entries = read_index(spark, f"{root}/normalised").select("archive", "offset", "length")
    return back.join(entries, ["archive", "offset", "length"]).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


SQL_OP6 = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
r AS (SELECT page_id, strlen(h)::BIGINT AS payload_bytes, sha1(h) AS payload_digest, max(page_id) OVER (PARTITION BY h) AS first_id FROM p)
SELECT page_id, payload_bytes, payload_digest,
       CASE WHEN payload_bytes >= 1000 AND page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 1000 AND page_id <> first_id THEN first_id END AS refers_to
FROM r
"""
