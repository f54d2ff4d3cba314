"""Web archives: records with chunked transfer framing, segmented on writing, reassembled on reading.

Writing: every page becomes a `response` record whose HTTP block carries the payload in chunked framing, or, if
another page holds the same payload, a `revisit` record that refers to it and stores headers only. A block longer
than `segment_bytes` is cut into a first record (segment 1) and `continuation` records; the last states the
total length. Records end with two line breaks, which is the line separator that Spark's text writer is told to put
behind each value: archives are written, committed and retried as any other Spark output, on any file system.

Reading: archive files are parsed record by record by Content-Length. Whole records are decoded where they are read;
only segments are shuffled, by the identifier of their origin, so that a group is one record. Segments are ordered by
number, checked for gaps and against the total length, and then the chunked framing is taken off.

Edge cases: a null payload counts as empty; a null page_id never refers nor is referred to; rows that repeat a page_id
with the same payload each give a record (all `response` if theirs is the smallest id); an empty table gives no
records; a record with missing segments, a wrong total length, a broken frame or a digest that differs comes back with
status `incomplete` or `corrupt` rather than being dropped.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

END = "\r\n\r\n"
_PARSED = (
    "record_id string, warc_type string, page_id long, url string, refers_to long, stated_digest string, "
    "origin string, segment int, total long, block binary"
)
_PAYLOADS = (
    "record_id string, page_id long, url string, record_type string, refers_to long, payload binary, "
    "payload_bytes long, payload_digest string, status string"
)


def revisits(pages: DataFrame, min_bytes: int) -> DataFrame:
    """page_id, refers_to for each page whose payload a page of a smaller id holds too. Thin rows are shuffled only."""
    body = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    thin = pages.where(F.col("page_id").isNotNull() & (F.octet_length(F.coalesce("html", F.lit(""))) >= min_bytes)).select("page_id", F.unhex(F.sha2(body, 256)).alias("digest"))
    groups = thin.groupBy("digest").agg(F.min("page_id").alias("refers_to"), F.count("*").alias("n")).where("n > 1").drop("n")
    return thin.join(groups, "digest").where("page_id > refers_to").select("page_id", "refers_to").distinct()


def _cuts(text: bytes, size: int) -> Iterator[bytes]:
    """Pieces of at most size bytes that begin at characters (so that each is UTF-8 by itself)."""
    at = 0
    while at < len(text):
        end = min(at + size, len(text))
        while end < len(text) and text[end] & 0xC0 == 0x80 and end - at > size - 4:
            end -= 1
        yield text[at:end]
        at = end


def _record(fields: list[tuple[str, object]], block: bytes) -> bytes:
    lines = [f"{k}: {v}" for k, v in [*fields, ("Content-Length", len(block))]]
    return ("WARC/1.1\r\n" + "\r\n".join(lines) + END).encode() + block


def _clean(url: str | None) -> str:
    return re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url or "")


def records_of(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, chunk_bytes: int, segment_bytes: int) -> Iterator[bytes]:
    """The records of one page, without the separator behind them."""
    digest = hashlib.sha256(payload).hexdigest()
    name = f"<urn:page:{'' if page_id is None else page_id}:{hashlib.md5((url or '').encode()).hexdigest()}>"
    common = [("WARC-Target-URI", _clean(url)), ("WARC-Date", "1970-01-01T00:00:00Z"), ("WARC-Payload-Digest", f"sha256:{digest}"), ("Content-Type", "application/http;msgtype=response")]
    if page_id is not None:
        common.append(("X-Page-Id", page_id))
    if refers_to is not None:
        head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
        profile = ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")
        yield _record([("WARC-Type", "revisit"), ("WARC-Record-ID", name), profile, ("WARC-Refers-To", f"<urn:page:{refers_to}>"), *common], head)
        return
    framed = [b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nTransfer-Encoding: chunked\r\n\r\n"]
    for piece in _cuts(payload, chunk_bytes):
        framed += [b"%x\r\n" % len(piece), piece, b"\r\n"]
    block = b"".join([*framed, b"0\r\n\r\n"])
    pieces = list(_cuts(block, segment_bytes))
    for k, piece in enumerate(pieces, 1):
        fields = [("WARC-Type", "response"), ("WARC-Record-ID", name)] if k == 1 else [("WARC-Type", "continuation"), ("WARC-Record-ID", name[:-1] + f":{k}>"), ("WARC-Segment-Origin-ID", name)]
        if len(pieces) > 1:
            fields.append(("WARC-Segment-Number", k))
            if k == len(pieces):
                fields.append(("WARC-Segment-Total-Length", len(block)))
        yield _record(fields + (common if k == 1 else []), piece)


def write_archives(pages: DataFrame, path: str, min_revisit_bytes: int = 100, chunk_bytes: int = 4096, segment_bytes: int = 65536, file_bytes: int = 64 << 20) -> None:
    """Writes the records of pages (page_id, url, html) as gzip archives of at most about file_bytes (uncompressed) below path.

    The html is moved only if the list of revisits is too long to be broadcast; then by page_id, which is even.
    """
    thin = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    joined = thin.join(revisits(thin, min_revisit_bytes), "page_id", "left")

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, urls, refs = (batch.column(n).to_pylist() for n in ("page_id", "url", "refers_to"))
            html, out, held, size = batch.column("html"), [], [], 0
            for k in range(batch.num_rows):
                payload = (html[k].as_py() or "").encode()
                for record in records_of(ids[k], urls[k], payload, refs[k], chunk_bytes, segment_bytes):
                    held.append(record)
                    size += len(record)
                    if size >= segment_bytes:
                        out.append(END.encode().join(held))
                        held, size = [], 0
                if len(out) * segment_bytes > 16 << 20:
                    yield pa.record_batch([pa.array(out, pa.binary()).cast(pa.string())], ["value"])
                    out = []
            if held:
                out.append(END.encode().join(held))
            yield pa.record_batch([pa.array(out, pa.binary()).cast(pa.string())], ["value"])

    # a row is some records of segment_bytes or more, and less than twice that and a head, so rows bound a file's bytes
    rows = max(1, file_bytes // (2 * segment_bytes))
    (joined.mapInArrow(emit, "value string").write.option("lineSep", END).option("maxRecordsPerFile", rows).option("compression", "gzip").text(path))


def parse_records(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields (names in lower case) and block of each record of an uncompressed archive."""
    at = 0
    while (at := data.find(b"WARC/", at)) >= 0:
        stop = data.find(END.encode(), at)
        if stop < 0:
            return
        fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in data[at:stop].decode("utf-8", "replace").split("\r\n")[1:])}
        start = stop + 4
        size = int(fields.get("content-length", 0))
        yield fields, data[start : start + size]
        at = start + size


def unchunk(body: bytes) -> tuple[bytes, bool]:
    """The content of a chunked body, and whether its frames are whole."""
    out, at = [], 0
    while (stop := body.find(b"\r\n", at)) >= 0:
        try:
            size = int(body[at:stop].split(b";")[0], 16)
        except ValueError:
            break
        if size == 0:
            return b"".join(out), True
        out.append(body[stop + 2 : stop + 2 + size])
        if body[stop + 2 + size : stop + 4 + size] != b"\r\n":
            break
        at = stop + 4 + size
    return b"".join(out), False


def http_payload(block: bytes, warc_type: str, stated: str) -> tuple[bytes | None, int, str, str]:
    """payload (None for a revisit), its length and digest, status."""
    head, _, body = block.partition(b"\r\n\r\n")
    fields = dict(re.findall(r"(?m)^([\w-]+):[ \t]*(.*?)\r?$", head.decode("utf-8", "replace").lower()))
    if warc_type == "revisit":
        return None, int(fields.get("content-length", 0)), stated, "ok"
    whole = True
    if fields.get("transfer-encoding") == "chunked":
        body, whole = unchunk(body)
    digest = hashlib.sha256(body).hexdigest()
    return body, len(body), digest, "ok" if whole and stated in ("", digest) else "corrupt"


def _number(text: str | None, pattern: str = r"(-?\d+)") -> int | None:
    found = re.fullmatch(pattern, text or "")
    return int(found[1]) if found else None


def _gunzip(data: bytes) -> bytes:
    """All members of a gzip file; other bytes as they are."""
    out = []
    while data[:2] == b"\x1f\x8b":
        member = zlib.decompressobj(31)
        out.append(member.decompress(data))
        data = member.unused_data
    return b"".join(out) if out else data


def read_segments(spark: SparkSession, path: str) -> DataFrame:
    """One row per record of the archives below path."""

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column("content"):
                rows, size = [], 0
                for f, block in parse_records(_gunzip(content.as_py())):
                    digest = f.get("warc-payload-digest", "").removeprefix("sha256:")
                    refers = _number(f.get("warc-refers-to"), r"<urn:page:(-?\d+)>")
                    rows.append((f.get("warc-record-id"), f.get("warc-type"), _number(f.get("x-page-id")), f.get("warc-target-uri"), refers, digest, f.get("warc-segment-origin-id"), _number(f.get("warc-segment-number")), _number(f.get("warc-segment-total-length")), block))
                    size += len(block)
                    if size > 16 << 20:
                        yield _batch(rows, _PARSED)
                        rows, size = [], 0
                yield _batch(rows, _PARSED)

    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("content")
    return files.mapInArrow(parse, _PARSED)


_ARROW = {"string": pa.string(), "long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    names, kinds = zip(*(x.split() for x in schema.split(", ")), strict=True)
    columns = zip(*rows, strict=True) if rows else [[] for _ in names]
    return pa.record_batch([pa.array(c, _ARROW[k]) for c, k in zip(columns, kinds, strict=True)], list(names))


def _decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for r in batch.to_pylist():
            parts = r["parts"]
            if parts is None:
                block, whole = r["block"], True
            else:
                parts.sort(key=lambda p: p["segment"])
                block = b"".join(p["block"] for p in parts)
                totals = {p["total"] for p in parts if p["total"] is not None}
                whole = [p["segment"] for p in parts] == list(range(1, len(parts) + 1)) and totals == {len(block)}
            payload, size, digest, status = http_payload(block, r["warc_type"] or "", r["stated_digest"] or "")
            rows.append((r["record_id"], r["page_id"], r["url"], r["warc_type"], r["refers_to"], payload, size, digest, status if whole else "incomplete"))
        yield _batch(rows, _PAYLOADS)


def read_payloads(spark: SparkSession, path: str) -> DataFrame:
    """One row per response or revisit record: record_id, page_id, url, record_type, refers_to, payload, payload_bytes, payload_digest, status."""
    records = read_segments(spark, path)
    head = ["record_id", "warc_type", "page_id", "url", "refers_to", "stated_digest"]
    part = F.struct("segment", "total", "block")
    kind = f"array<{'struct<segment:int,total:bigint,block:binary>'}>"
    whole = records.where("segment is null").select(*head, "block", F.lit(None).cast(kind).alias("parts"))
    first = F.col("segment") == 1
    # a repeated row of pages writes equal segments twice: they are one
    groups = records.where("segment is not null").groupBy(F.coalesce("origin", "record_id").alias("record_id")).agg(
        *[F.max(F.when(first, F.col(c))).alias(c) for c in head[1:]], F.lit(None).cast("binary").alias("block"), F.collect_set(part).alias("parts"), F.count(F.when(first, 1)).alias("times")
    )
    copies = groups.withColumn("times", F.explode(F.sequence(F.lit(1), F.greatest("times", F.lit(1)))))
    return whole.unionByName(copies.drop("times").select(*whole.columns)).mapInArrow(_decode, _PAYLOADS)
