"""WARC archives of pages: written with segments, chunked transfer framing and revisits, read back by reassembly."""

from __future__ import annotations

import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coverdp.llm.textkit import col
from coverdp.runtime import materialise, remove, shared_folder

END = "\r\n\r\n"
#: Payloads of fewer bytes are never revisits.
LEAST = 100


def roles(pages: DataFrame, least: int = LEAST) -> DataFrame:
    """page_id, digest, record_type, refers_to: of equal payloads of `least` bytes or more the smallest page_id is the response."""
    html = F.coalesce(F.col("html").cast("string"), F.lit(""))
    digests = pages.select(F.col("page_id").cast("long").alias("page_id"), F.sha2(html.cast("binary"), 256).alias("digest"), (F.octet_length(html) >= least).alias("long_enough"))
    first = digests.where("long_enough").groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
    joined = digests.join(first, "digest", "left")
    again = F.col("long_enough") & F.col("first").isNotNull() & (F.col("first") != F.col("page_id"))
    return joined.select("page_id", "digest", F.when(again, "revisit").otherwise("response").alias("record_type"), F.when(again, F.col("first")).alias("refers_to"))


def _chunked(payload: str, step: int) -> str:
    parts = []
    for at in range(0, len(payload), step):
        piece = payload[at : at + step]
        parts.append(f"{len(piece.encode()):x}\r\n{piece}\r\n")
    return "".join([*parts, "0\r\n\r\n"])


def _record(fields: list[tuple[str, object]], block: str) -> str:
    head = "".join(f"{k}: {v}\r\n" for k, v in [*fields, ("Content-Length", len(block.encode()))])
    return f"WARC/1.1\r\n{head}\r\n{block}"


def records(page_id: int, url: str | None, html: str | None, digest: str, kind: str, refers_to: int | None, segment: int, chunk: int) -> list[str]:
    """The WARC records of a page; a block of over `segment` characters goes on in continuation records."""
    payload = html or ""
    target = re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url or "about:blank")
    own = f"<urn:x-page:{page_id}>"
    base = [("WARC-Date", "1970-01-01T00:00:00Z"), ("WARC-Target-URI", target), ("WARC-Payload-Digest", f"sha256:{digest}")]
    status = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n"
    if kind == "revisit":
        fields = [("WARC-Type", "revisit"), ("WARC-Record-ID", own), *base, ("WARC-Refers-To", f"<urn:x-page:{refers_to}>"), ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("Content-Type", "application/http; msgtype=response")]
        return [_record(fields, f"{status}\r\n")]
    framed = len(payload) % 2 == 0  # both framings of HTTP occur
    block = f"{status}Transfer-Encoding: chunked\r\n\r\n{_chunked(payload, chunk)}" if framed else f"{status}Content-Length: {len(payload.encode())}\r\n\r\n{payload}"
    pieces = [block[at : at + segment] for at in range(0, len(block), segment)]
    out = []
    for i, piece in enumerate(pieces, 1):
        fields = [("WARC-Type", "response" if i == 1 else "continuation"), ("WARC-Record-ID", own if i == 1 else f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{own}/{i}')}>"), *base]
        if len(pieces) > 1:
            fields += [("WARC-Segment-Number", i)]
        if i > 1:
            fields += [("WARC-Segment-Origin-ID", own)]
        if i == len(pieces) > 1:
            fields += [("WARC-Segment-Total-Length", len(block.encode()))]
        if i == 1:
            fields += [("Content-Type", "application/http; msgtype=response")]
        out.append(_record(fields, piece))
    return out


def write(pages: DataFrame, folder: str, segment: int = 8192, chunk: int = 2048, per_file: int = 8_000) -> None:
    """Archives of pages(page_id, url, html) in `folder`, gzip-compressed, `per_file` records a file at most. Null html: an empty payload."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                b = whole.slice(at, 256)
                out = []
                for row in b.to_pylist():
                    digest = hashlib.sha256((row["html"] or "").encode()).hexdigest()
                    out += records(row["page_id"], row["url"], row["html"], digest, "response" if row["refers_to"] is None else "revisit", row["refers_to"], segment, chunk)
                yield pa.record_batch({"value": pa.array(out, pa.string())})

    known = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).where("page_id is not null")
    again = materialise(roles(known).where("record_type = 'revisit'").select("page_id", "refers_to"))  # of known size: pages stay where they are while it's small
    whole = known.join(again, "page_id", "left").select("page_id", "url", "html", "refers_to")
    whole.mapInArrow(run, "value string").write.option("lineSep", END).option("maxRecordsPerFile", per_file).option("compression", "gzip").text(folder)


def _fields(head: bytes) -> dict[str, str]:
    lines = head.decode("utf-8", "replace").split("\r\n")
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:]) if k}


def parse(raw: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """(fields, block) of each record of an archive; Content-Length alone says where a block ends."""
    at = 0
    while (at := raw.find(b"WARC/", at)) >= 0:
        head_end = raw.find(b"\r\n\r\n", at)
        if head_end < 0:
            raise ValueError("a record's header doesn't end")
        fields = _fields(raw[at:head_end])
        begin = head_end + 4
        end = begin + int(fields["content-length"])
        if end > len(raw):
            raise ValueError("a record is cut off")
        yield fields, raw[begin:end]
        at = end


def dechunk(body: bytes) -> bytes:
    """The payload of chunked transfer framing; ValueError where sizes and bytes disagree."""
    out, at = [], 0
    while True:
        line = body.find(b"\r\n", at)
        if line < 0:
            raise ValueError("a chunk has no size")
        size = int(body[at:line].split(b";")[0], 16)
        at = line + 2
        if not size:
            return b"".join(out)
        if body[at + size : at + size + 2] != b"\r\n":
            raise ValueError("a chunk's size is wrong")
        out.append(body[at : at + size])
        at += size + 2


def payload(block: bytes) -> bytes:
    """The payload of an HTTP response."""
    head, _, body = block.partition(b"\r\n\r\n")
    fields = _fields(head)
    return dechunk(body) if fields.get("transfer-encoding", "").lower() == "chunked" else body


def _page(identifier: str) -> int:
    return int(identifier.strip("<>").rpartition(":")[2])


def _unpacked(raw: bytes) -> bytes:
    """An archive's bytes; gzip members are taken one after another."""
    if raw[:2] != b"\x1f\x8b":
        return raw
    parts, rest = [], raw
    while rest:
        d = zlib.decompressobj(31)
        parts.append(d.decompress(rest) + d.flush())
        rest = d.unused_data
    return b"".join(parts)


def _found(batches: Iterator[pa.RecordBatch], names: list[str], kinds: list[pa.DataType], row) -> Iterator[pa.RecordBatch]:
    """A row for each record for which `row` gives one, in batches of bounded bytes."""
    for b in batches:
        for raw in col(b, "content"):
            rows, size = [], 0
            for fields, block in parse(_unpacked(raw.as_buffer().to_pybytes())):
                if (one := row(fields, block)) is not None:
                    rows.append(one)
                    size += len(block)
                if size > 1 << 23:
                    yield pa.record_batch([pa.array(x, k) for x, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)
                    rows, size = [], 0
            if rows:
                yield pa.record_batch([pa.array(x, k) for x, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)


def _head(f: dict[str, str]) -> tuple:
    return f.get("warc-payload-digest", "").partition(":")[2], f["warc-type"], _page(f["warc-refers-to"]) if "warc-refers-to" in f else None


def _single(f: dict[str, str], block: bytes):
    """Records in one piece, decoded; a revisit has no payload."""
    if "warc-segment-number" not in f:
        return (_page(f["warc-record-id"]), None if f["warc-type"] == "revisit" else payload(block), *_head(f))


def _segment(f: dict[str, str], block: bytes):
    if "warc-segment-number" in f:
        total = int(f["warc-segment-total-length"]) if "warc-segment-total-length" in f else None
        return _page(f.get("warc-segment-origin-id", f["warc-record-id"])), int(f["warc-segment-number"]), total, block, *_head(f)


WHOLE = (["page_id", "payload", "digest", "record_type", "refers_to"], [pa.int64(), pa.binary(), pa.string(), pa.string(), pa.int64()])
PIECE = (["origin", "number", "total", "block", "digest", "record_type", "refers_to"], [pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.string(), pa.string(), pa.int64()])


def _singles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    return _found(batches, *WHOLE, _single)


def _segments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    return _found(batches, *PIECE, _segment)


def _assembled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Segments put in order, checked, joined and decoded; a record's fields are those of its first segment."""
    for b in batches:
        out = []
        for origin, own in zip(col(b, "origin").to_pylist(), col(b, "segments").to_pylist(), strict=True):
            own.sort(key=lambda s: s["number"])
            if [s["number"] for s in own] != list(range(1, len(own) + 1)):
                raise ValueError("segments are missing or repeated")
            block = b"".join(s["block"] for s in own)
            if own[-1]["total"] != len(block):
                raise ValueError("the segments' total length is wrong")
            out.append((origin, payload(block), own[0]["digest"], own[0]["record_type"], own[0]["refers_to"]))
        if out:
            yield pa.record_batch([pa.array(x, k) for x, k in zip(zip(*out, strict=True), WHOLE[1], strict=True)], WHOLE[0])


def read(spark, folder: str) -> DataFrame:
    """page_id, payload, digest, record_type, refers_to of every record in a folder of archives; a revisit has no payload of its own.

    Records in one piece are decoded where they are read and never move; only segments do, grouped by their origin's
    identifier. Archives are read twice, so nothing of them is written a second time.
    """
    files = spark.read.format("binaryFile").load(folder).select("content")
    kind = "page_id long, payload binary, digest string, record_type string, refers_to long"
    single = files.mapInArrow(_singles, kind)
    pieces = files.mapInArrow(_segments, "origin long, number long, total long, block binary, digest string, record_type string, refers_to long")
    several = pieces.groupBy("origin").agg(F.collect_list(F.struct("number", "total", "block", "digest", "record_type", "refers_to")).alias("segments"))
    return single.union(several.mapInArrow(_assembled, kind))


def archive_pages(pages: DataFrame, segment: int = 8192, chunk: int = 2048) -> DataFrame:
    """Write the pages to archives in the shared folder, read them back, and give page_id, payload_bytes, payload_digest, record_type, refers_to.

    Revisits take size and digest of the response that they refer to; payloads are hashed after decoding. An empty
    table gives no row; rows without page_id can't be archived and are left out; rows that repeat a page_id aren't
    allowed (their segments would be repeated: ValueError, or rows repeat).
    """
    spark = pages.sparkSession
    folder = f"{shared_folder(spark)}/coverdp-warc-{uuid.uuid4().hex}"
    write(pages, folder, segment, chunk)
    back = read(spark, folder)
    small = materialise(back.select("page_id", F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha2("payload", 256).alias("payload_digest"), "record_type", "refers_to"))
    remove(spark, folder)
    whole = small.where("record_type <> 'revisit'")
    source = whole.select(F.col("page_id").alias("refers_to"), "payload_bytes", "payload_digest")
    again = small.where("record_type = 'revisit'").drop("payload_bytes", "payload_digest").join(source, "refers_to", "left")
    names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    return whole.select(*names).union(again.select(*names))
