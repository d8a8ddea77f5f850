"""WARC archives: writing pages as records, normalising monolithic gzip files, and reading back by offset.

An archive is one binary value of a table in the shared folder, so that any store Spark writes to will do. The
normaliser inflates a whole-file gzip stream once, as a stream, rewrites every record as a gzip member of its own and
lists where each member lies, so that a record can later be read alone."""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Iterator
from datetime import datetime, timezone
from urllib.parse import quote, unquote

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize, pick, slices, utf8_buffer

#: Bytes of payload in one archive, about; a larger record stands alone. Bounds the memory of a worker.
ARCHIVE_BYTES = 8 << 20
#: Copies of a repeated payload are dealt over so many parts when they look up their first occurrence.
SALTS = 64
CHUNK = 1 << 16
LEVEL = 1


def digest_of(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def payload_digests(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """pages -> (page_id, url, html, payload_bytes, digest); null html is the empty payload."""
    rows = pick(pages, page_id=id_col, url=url_col, html=html_col).withColumn("html", F.coalesce("html", F.lit("")))
    # SHA-1 as 40 hexadecimal digits; base 32 is written in the archive.
    return rows.withColumn("payload_bytes", F.octet_length("html").cast("long")).withColumn("digest", F.sha1(F.encode("html", "UTF-8")))


def classify(hashed: DataFrame, min_bytes: int = 0) -> DataFrame:
    """Adds record_type and refers_to: of equal payloads of at least min_bytes the smallest page_id is the response.

    Equal payloads with a null page_id revisit the smallest id that is not null; if all are null, all are responses.
    Rows that repeat the smallest id are responses too. The minimum is pre-aggregated per digest; only repeated
    digests are joined back, salted, so that a payload held by a third of all pages doesn't meet in one task."""
    firsts = hashed.where(F.col("payload_bytes") >= min_bytes).groupBy("digest", "payload_bytes").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1")
    salted = firsts.select(F.col("digest").alias("of"), "first", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("part"))
    dealt = hashed.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int"))
    joined = dealt.join(salted, (F.col("digest") == F.col("of")) & (F.col("salt") == F.col("part")), "left")
    again = F.coalesce(F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first")), F.lit(False))
    return joined.select("page_id", "url", "html", "payload_bytes", "digest", F.when(again, "revisit").otherwise("response").alias("record_type"), F.when(again, F.col("first")).alias("refers_to"))


def record(page_id, url: str, payload: bytes, digest: str, kind: str, refers_to, date: str) -> bytes:
    """One WARC/1.1 record. A revisit has no block; it keeps the length of the payload it stands for."""
    block = b"" if kind == "revisit" else payload
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {urn(page_id)}", f"WARC-Target-URI: {clean(url)}", f"WARC-Date: {date}", f"WARC-Payload-Digest: sha1:{digest}", f"WARC-Payload-Length: {len(payload)}"]
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {urn(refers_to)}"]
    head += ["Content-Type: text/html", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def urn(page_id) -> str:
    """The name of a page's record; ids that are not whole numbers are percent-encoded after a sign that tells them."""
    if page_id is None:
        return "<urn:page:>"
    return f"<urn:page:{page_id}>" if isinstance(page_id, int) else f"<urn:page:={quote(str(page_id), safe='')}>"


def clean(value: str | None) -> str:
    """A header value holds no line breaks."""
    return (value or "").replace("\r", " ").replace("\n", " ")


def write_archives(pages: DataFrame, date: datetime = datetime(2024, 1, 1, tzinfo=timezone.utc), archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """Classified pages -> (archive, n_records, content): whole-file gzip archives, as many older crawlers write them."""
    stamp = date.strftime("%Y-%m-%dT%H:%M:%SZ")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, serial = TaskContext.get().partitionId(), 0
        parts, packer, size, count = [], zlib.compressobj(LEVEL, zlib.DEFLATED, 31), 0, 0
        for batch in slices(batches, "html", archive_bytes):
            raw, at = utf8_buffer(batch.column(2))
            columns = [batch.column(i).to_pylist() for i in (0, 1, 4, 5, 6)]
            for i, (page_id, url, hexed, kind, refers_to) in enumerate(zip(*columns, strict=True)):
                payload = raw[at[i] : at[i + 1]].tobytes()
                if count and size + len(payload) > archive_bytes:
                    parts.append(packer.flush())
                    yield _archive(task, serial, count, b"".join(parts))
                    parts, packer, size, count, serial = [], zlib.compressobj(LEVEL, zlib.DEFLATED, 31), 0, 0, serial + 1
                digest = base64.b32encode(bytes.fromhex(hexed)).decode()
                parts.append(packer.compress(record(page_id, url, payload, digest, kind, refers_to, stamp)))
                size, count = size + len(payload), count + 1
        if count:
            parts.append(packer.flush())
            yield _archive(task, serial, count, b"".join(parts))

    return pages.mapInArrow(run, "archive string, n_records long, content binary")


def _archive(task: int, serial: int, count: int, content: bytes) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([f"part-{task:06d}-{serial:04d}.warc.gz"]), pa.array([count], pa.int64()), pa.array([content], pa.binary())], names=["archive", "n_records", "content"])


def inflated(content: bytes) -> Iterator[bytes]:
    """The bytes of a gzip file of one or more members, chunk by chunk, each inflated once."""
    view, at = memoryview(content), 0
    while at < len(view):
        stream = zlib.decompressobj(31)
        while not stream.eof:
            chunk = view[at : at + CHUNK]
            if not chunk:
                raise ValueError("gzip stream cut short")
            at += len(chunk)
            yield stream.decompress(chunk)
        at -= len(stream.unused_data)
        while at < len(view) and view[at] == 0:  # padding after a member
            at += 1


def records(chunks: Iterator[bytes]) -> Iterator[bytes]:
    """Whole records of an inflated stream, cut by their Content-Length: only one record is held at a time."""
    held = bytearray()

    def fill(n: int) -> bool:
        while len(held) < n:
            more = next(chunks, None)
            if more is None:
                return False
            held.extend(more)
        return True

    while True:
        while not held or held[:1] in b"\r\n":  # blank lines between records
            del held[: len(held) - len(held.lstrip(b"\r\n"))]
            if not held and not fill(1):
                return
        seen = 0
        while (end := held.find(b"\r\n\r\n", max(0, seen - 3))) < 0:
            seen = len(held)
            if not fill(seen + 1):
                raise ValueError("header cut short")
        size = int(headers(bytes(held[:end]))["content-length"])
        whole = end + 4 + size
        if not fill(whole):
            raise ValueError("block cut short")
        yield bytes(held[:whole]) + b"\r\n\r\n"
        del held[:whole]


def headers(head: bytes) -> dict[str, str]:
    lines = head.decode("utf-8", "replace").split("\r\n")
    return {k.strip().lower(): v.strip() for k, _, v in (line.partition(":") for line in lines[1:])}


def normalise(archives: DataFrame) -> DataFrame:
    """(archive, content) -> (archive, content, index): every record its own gzip member, and the sidecar index.

    index: an array of (offset, length, record_id) of the members in order. Accepts files that are already cut per
    record or hold several members."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, content in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                members, index, at = [], [], 0
                for whole in records(inflated(content.as_py() or b"")):
                    packer = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
                    member = packer.compress(whole) + packer.flush()
                    index.append({"offset": at, "length": len(member), "record_id": headers(whole[: whole.index(b"\r\n\r\n")]).get("warc-record-id")})
                    members.append(member)
                    at += len(member)
                yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([b"".join(members)], pa.binary()), pa.array([index], pa.list_(pa.struct([("offset", pa.int64()), ("length", pa.int64()), ("record_id", pa.string())])))], names=["archive", "content", "index"])

    return archives.select("archive", "content").mapInArrow(run, "archive string, content binary, index array<struct<offset:long,length:long,record_id:string>>")


def read_records(normalised: DataFrame, id_type: str = "bigint") -> DataFrame:
    """(archive, content, index) -> one row a record, each inflated from its own offset.

    A response's digest and length are computed from the payload read, and must agree with its header; a revisit's are
    those of the payload it stands for. id_type: that of page_id, whole numbers or text."""
    whole_numbers = id_type in ("tinyint", "smallint", "int", "bigint")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, content, index in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), strict=True):
                data, rows = memoryview(content.as_buffer()), []
                for entry in index or []:
                    whole = zlib.decompress(data[entry["offset"] : entry["offset"] + entry["length"]], 31)
                    end = whole.index(b"\r\n\r\n")
                    head = headers(whole[:end])
                    digest, size = head["warc-payload-digest"].removeprefix("sha1:"), int(head["warc-payload-length"])
                    if head["warc-type"] == "response":
                        block = whole[end + 4 : end + 4 + int(head["content-length"])]
                        if digest_of(block) != digest or len(block) != size:
                            raise ValueError(f"damaged record {head['warc-record-id']} in {name}")
                    rows.append((_page(head["warc-record-id"]), size, digest, head["warc-type"], _page(head.get("warc-refers-to"))))
                if rows:
                    own = pa.int64() if whole_numbers else pa.string()
                    kinds = (own, pa.int64(), pa.string(), pa.string(), own)
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])

    kind = "long" if whole_numbers else "string"
    return normalised.mapInArrow(run, f"page_id {kind}, payload_bytes long, payload_digest string, record_type string, refers_to {kind}")


def _page(record_id: str | None) -> int | str | None:
    text = (record_id or "").removeprefix("<urn:page:").removesuffix(">")
    return unquote(text[1:]) if text.startswith("=") else int(text) if text else None


def crawl_round_trip(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """Pages written as monolithic archives, normalised, and read back by offset: one row a page.

    Both forms are tables in the shared folder. Page ids are whole numbers or text, or null (null stays null); a null url is
    written empty; repeated rows give a record each; an empty table gives no rows."""
    hashed = payload_digests(pages)
    id_type = hashed.schema["page_id"].dataType.simpleString()
    stored = materialize(write_archives(classify(hashed, min_bytes)), "warc-monolithic")
    normalised = materialize(normalise(stored), "warc-normalised")
    discard(stored)
    return read_records(normalised, id_type)
