"""WARC archives: a writer with revisit records, and a reader that salvages damaged files.

Each record is a gzip member of its own, so a file is a plain multi-member archive.  Spark's
text sink writes the files: a member's last byte, the high byte of its little-endian
length, is zero, and the sink's line separator supplies it (a record of 16 MB or more ends
with an empty member, whose last byte is zero too).

The reader goes through a file's bytes.  After a failed check (member checksum, version
line, header, block length, payload digest) it searches the next gzip member or version
line, goes on there if a valid record follows, and logs the bytes between as a quarantined
gap with its reason.  Inside a member it does the same among the inflated bytes, and a
damaged or cut member gives the records that inflate whole.  Uncompressed records are read
too.

Of records with equal payloads of at least ``least`` bytes, the one with the smallest page
id is a response and the others revisit it.

Defined cases: a null html is an empty payload; rows with the smallest id of their group
are responses (all of them, if repeated); a null id revisits, unless all its group's are
null; null urls have no target line; an empty table makes no records; other columns take no
part.
"""

from __future__ import annotations

import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, LongType, StringType, StructField, StructType

from ._arrow import append_columns, checkpoint, column, shared_folder

LEAST = 100
RECORDS_PER_FILE = 4000
#: Payload bytes of a file, by the mean of all; the reader holds one file at a time.
FILE_BYTES = 256 << 20
#: A table of first pages is broadcast up to so many rows (under 100 bytes each).
BROADCAST_ROWS = 50_000
ID = "urn:page:"
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n"
#: Fixed value: an empty gzip member.
EMPTY = bytes.fromhex("1f8b080000000000000303000000000000000000")
VERSION = re.compile(rb"\x1f\x8b\x08|WARC/1\.[01]\r\n")
VERSION_LINE = re.compile(rb"WARC/1\.[01]\r\n")


def record(page_id, url: bytes | None, payload: bytes, digest: str, refers_to) -> bytes:
    """One WARC record; a revisit (``refers_to`` a 1-tuple) has no payload of its own."""
    head = [b"WARC/1.1", b"WARC-Type: " + (b"revisit" if refers_to else b"response")]
    head.append(f"WARC-Record-ID: <{ID}{page_id}>".encode())
    head.append(b"WARC-Date: 1970-01-01T00:00:00Z")
    if url is not None:
        head.append(b"WARC-Target-URI: " + b"".join(url.splitlines()))
    head.append(f"WARC-Payload-Digest: sha256:{digest}".encode())
    head.append(b"X-Payload-Length: %d" % len(payload))
    if refers_to:
        head.append(b"WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")
        head.append(f"WARC-Refers-To: <{ID}{refers_to[0]}>".encode())
    block = HTTP % len(payload) + (b"" if refers_to else payload)
    head.append(b"Content-Type: application/http; msgtype=response")
    head.append(b"Content-Length: %d" % len(block))
    return b"\r\n".join(head) + b"\r\n\r\n" + block + b"\r\n\r\n"


def member(data: bytes, level: int = 6) -> bytes:
    """``data`` as gzip members whose last byte is zero."""
    c = zlib.compressobj(level, zlib.DEFLATED, 31)
    made = c.compress(data) + c.flush()
    return made if made[-1] == 0 else made + EMPTY


def decide(pages: DataFrame, id_col: str = "page_id", text_col: str = "html", url_col: str | None = "url", least: int = LEAST) -> DataFrame:
    """(page_id, url, payload, digest, first, revisit) of every page."""
    return _decided(pages, id_col, text_col, url_col, least)[0]


def _decided(pages, id_col="page_id", text_col="html", url_col="url", least=LEAST) -> tuple[DataFrame, float]:
    """The rows of ``decide``, and the mean payload's bytes."""
    url = column(url_col) if url_col in pages.columns else F.lit(None)
    base = pages.select(
        column(id_col).alias("page_id"), url.cast("string").alias("url"),
        F.coalesce(column(text_col).cast("binary"), F.lit(b"")).alias("payload"),
    ).withColumn("digest", F.sha2("payload", 256))
    size = F.octet_length("payload")
    every = checkpoint(base.groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n"), F.max(size).cast("bigint").alias("size")))
    mean = every.agg(F.sum(F.col("n") * F.col("size")) / F.sum("n")).first()[0] or 0.0
    groups = every.where((F.col("n") > 1) & (F.col("size") >= least)).select(F.col("digest").alias("same"), "first")
    small = groups.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    joined = base.join(F.broadcast(groups) if small else groups, (F.col("digest") == F.col("same")), "left")
    revisit = F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
    return joined.select("page_id", "url", "payload", "digest", "first", revisit.alias("revisit")), mean


def write(pages: DataFrame, path: str, records_per_file: int = RECORDS_PER_FILE, **how) -> None:
    """Write every page as a record to archives in the folder ``path``: up to
    ``records_per_file`` a file, fewer where they are large."""
    rows, mean = _decided(pages, **how)
    records_per_file = max(1, min(records_per_file, int(FILE_BYTES / max(1, mean))))

    def kernel(ids, urls, payloads, digests, firsts, revisits):
        made = []
        for i, u, p, d, f, r in zip(ids, urls, payloads, digests, firsts, revisits):
            made.append((member(record("null" if i is None else i, u, p, d.decode(), (f,) if r else None))[:-1],))
        return made

    fields = StructType([StructField("member", BinaryType())])
    names = ["page_id", "url", "payload", "digest", "first", "revisit"]
    out = append_columns(rows, names, lambda: kernel, fields, keep=[])
    # the sink's separator is each member's last byte
    text = out.select(F.col("member").cast("string").alias("value"))
    text.write.option("lineSep", "\u0000").option("maxRecordsPerFile", records_per_file).text(path)


def unpack(data: bytes, at: int, step: int = 1 << 15) -> tuple[bytes, int | None]:
    """(contents, end) of the gzip member at ``at``: as far as it inflates, and None as its
    end, if it is damaged or cut off."""
    d, out, pos = zlib.decompressobj(31), [], at
    view = memoryview(data)
    try:
        while not d.eof:
            if pos >= len(data):
                return b"".join(out), None
            out.append(d.decompress(view[pos : pos + step]))
            pos = min(len(data), pos + step)
    except zlib.error:
        # the piece that failed once more in small bits: what comes before the damage counts
        return b"".join(out) + _before_damage(data, at, pos, sum(map(len, out))), None
    return b"".join(out), pos - len(d.unused_data)


def _before_damage(data: bytes, at: int, pos: int, had: int, step: int = 64) -> bytes:
    d, made, out = zlib.decompressobj(31), 0, []
    try:
        made = len(d.decompress(data[at:pos]))
        while pos < len(data):
            out.append(d.decompress(data[pos : pos + step]))
            pos += step
    except zlib.error:
        pass
    return b"".join(out) if made == had else b""


def inflate(data: bytes, at: int) -> tuple[bytes, int] | None:
    """(contents, end) of the gzip member at ``at``; None if it is damaged or cut off."""
    inner, end = unpack(data, at)
    return None if end is None else (inner, end)


def parse(data: bytes, at: int = 0) -> tuple[dict[str, bytes], bytes, int] | str:
    """(headers, block, end) of the record at ``at``, or what is wrong with it."""
    if not VERSION_LINE.match(data, at):
        return "no version line"
    stop = data.find(b"\r\n\r\n", at)
    if stop < 0:
        return "header without end"
    headers: dict[str, bytes] = {}
    for line in data[at:stop].split(b"\r\n")[1:]:
        name, colon, value = line.partition(b":")
        if not colon:
            return "header line without colon"
        headers[name.decode("latin-1").strip().lower()] = value.strip()
    size = headers.get("content-length", b"")
    if not size.isdigit():
        return "no block length"
    end = stop + 4 + int(size)
    if data[end : end + 4] != b"\r\n\r\n":
        return "block length is wrong"
    return headers, data[stop + 4 : end], end + 4


def check(headers: dict[str, bytes], block: bytes) -> str | None:
    """What is wrong with a record's payload; None if nothing is."""
    kind = headers.get("warc-type", b"")
    digest = headers.get("warc-payload-digest", b"")
    if kind == b"response" and digest.startswith(b"sha256:"):
        payload = block.partition(b"\r\n\r\n")[2] if block.startswith(b"HTTP/") else block
        if hashlib.sha256(payload).hexdigest().encode() != digest[7:]:
            return "payload digest is wrong"
    return None


def _records(data: bytes, at: int = 0) -> Iterator[tuple[int, int, object]]:
    """(start, end, (headers, block)) of valid records and (start, end, reason) of what lies
    between, over plain bytes; after a failed check the next version line is tried."""
    gap, reason = None, ""
    while at < len(data):
        made = parse(data, at)
        wrong = made if isinstance(made, str) else check(*made[:2])
        if not wrong:
            if gap is not None:
                yield gap, at, reason
                gap = None
            yield at, made[2], made[:2]
            at = made[2]
            continue
        if gap is None:
            gap, reason = at, wrong
        later = VERSION_LINE.search(data, at + 1)
        at = later.start() if later else len(data)
    if gap is not None:
        yield gap, len(data), reason


def salvage(data: bytes) -> Iterator[tuple[str, int, int, object]]:
    """("record", start, end, (headers, block)) and ("gap", start, end, reason), in order.

    Positions are those of the file.  Good records of a member are kept wherever its bad ones
    stand: a gap inside a sound member has the member's positions, and its own ones among
    the inflated bytes in the reason.  Of a damaged or cut member the records that inflate
    whole are kept, and its bytes are (part of) a gap."""
    at, gap, reason = 0, None, ""
    while at < len(data):
        end, found, wrong = None, [], "no member or version line"
        if data.startswith(b"\x1f\x8b\x08", at):
            inner, end = unpack(data, at)
            found = list(_records(inner))
            if end is None:
                wrong = "member is damaged"
                found = [f for f in found if not isinstance(f[2], str)]
            elif found and all(isinstance(f[2], str) for f in found):
                wrong, found, end = found[0][2], [], None
        elif data.startswith(b"WARC/", at):
            made = parse(data, at)
            wrong = made if isinstance(made, str) else check(*made[:2]) or ""
            if not wrong:
                found, end = [(0, 0, made[:2])], made[2]
        if gap is not None and end is not None:
            yield "gap", gap, at, reason
            gap = None
        stop = end
        if stop is None:
            later = VERSION.search(data, at + 1)
            stop = later.start() if later else len(data)
            if gap is None:
                gap, reason = at, wrong
        for s, e, what in found:
            if isinstance(what, str):
                yield "gap", at, stop, f"{what} (bytes {s} to {e} of the member)"
            else:
                yield "record", at, stop, what
        at = stop
    if gap is not None:
        yield "gap", gap, len(data), reason


RECORDS = StructType(
    [
        StructField("path", StringType()), StructField("start", LongType()), StructField("end", LongType()),
        StructField("kind", StringType()), StructField("reason", StringType()), StructField("page_id", StringType()),
        StructField("url", StringType()), StructField("record_type", StringType()), StructField("refers_to", StringType()),
        StructField("payload_digest", StringType()), StructField("payload_bytes", LongType()),
        StructField("payload", BinaryType()),
    ]
)


def read(spark: SparkSession, path: str, payload: bool = False) -> DataFrame:
    """Records and gaps (kind, with reason) of all archives under ``path``.

    ``payload`` keeps response bodies; else that column is null."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("path", "content")

    def run(batches):
        for batch in batches:
            for name, data in zip(batch.column(0).to_pylist(), batch.column(1)):
                rows: list[tuple] = []
                for kind, start, end, what in salvage(data.as_py()):
                    rows.append(_row(name, start, end, kind, what, payload))
                    if len(rows) == 500:
                        yield _batch(rows)
                        rows = []
                if rows:
                    yield _batch(rows)

    return files.mapInArrow(run, RECORDS)


def _row(name, start, end, kind, what, keep):
    if kind == "gap":
        return (name, start, end, kind, what, *[None] * 7)
    headers, block = what
    text = lambda h: headers[h].decode("utf-8", "replace") if h in headers else None
    own = lambda h: v.strip("<>").removeprefix(ID) if (v := text(h)) is not None else None
    body = block.partition(b"\r\n\r\n")[2] if block.startswith(b"HTTP/") else block
    kind_ = text("warc-type")
    size = int(headers["x-payload-length"]) if headers.get("x-payload-length", b"").isdigit() else len(body)
    digest = (text("warc-payload-digest") or "").removeprefix("sha256:") or None
    if kind_ == "response":
        size, digest = len(body), hashlib.sha256(body).hexdigest()
    return (name, start, end, kind, None, own("warc-record-id"), text("warc-target-uri"), kind_, own("warc-refers-to"), digest, size, body if keep else None)


def _batch(rows):
    from pyspark.sql.pandas.types import to_arrow_schema

    schema = to_arrow_schema(RECORDS)
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], f.type) for i, f in enumerate(schema)], schema=schema)


def new_folder(spark: SparkSession) -> str:
    """A fresh archive folder in the shared one."""
    return f"{shared_folder(spark)}/warc-{uuid.uuid4().hex}"
