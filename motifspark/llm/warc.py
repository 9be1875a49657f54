"""WARC archives: writing with revisits and segmented records, reading with segment reassembly.

Payloads travel in HTTP blocks with chunked transfer framing. A block beyond ``segment_bytes`` is cut: the record
itself is segment 1, continuation records carry the others with the origin's identifier, and the last one names the
total length. Reading groups continuations by origin, orders them by number, checks numbers and total length, and
decodes the framing. Archives are written by the text sink with the record terminator as its line separator, so any
file system which Spark writes to will do.
"""

from __future__ import annotations

import base64
import hashlib
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import durable, measured_bytes, new_folder

VERSION = b"WARC/1.1\r\n"
END = "\r\n\r\n"
RECORD = "record_id string, kind string, origin_id string, segment int, total long, page_id long, url string, digest string, refers_to long, block binary"
PAGE = "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, problem string"


@dataclass(frozen=True)
class ArchiveSpec:
    """``min_bytes``: smallest payload that may be a revisit. ``file_bytes``: aim for the size of an archive file.
    ``broadcast_bytes``: bound on the table of repeated digests that is broadcast; beyond it payloads are shuffled."""

    min_bytes: int = 0
    segment_bytes: int = 256 << 10
    chunk_bytes: int = 32 << 10
    file_bytes: int = 16 << 20
    broadcast_bytes: int = 32 << 20


def sha1_base32(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def chunked(data: bytes, size: int) -> bytes:
    cuts = [data[i : i + size] for i in range(0, len(data), size)]
    return b"".join(b"%x\r\n%s\r\n" % (len(c), c) for c in cuts) + b"0\r\n\r\n"


def unchunk(body: bytes) -> bytes:
    out, at = [], 0
    while True:
        end = body.index(b"\r\n", at)
        n = int(body[at:end].split(b";")[0], 16)
        at = end + 2
        if not n:
            return b"".join(out)
        out.append(body[at : at + n])
        if len(out[-1]) != n or body[at + n : at + n + 2] != b"\r\n":
            raise ValueError("chunk is cut short")
        at += n + 2


def _record(headers: list[tuple[str, object]], block: bytes) -> bytes:
    head = "".join(f"{k}: {v}\r\n" for k, v in [*headers, ("Content-Length", len(block))] if v is not None)
    return VERSION + head.encode() + b"\r\n" + block


def _records_of(page_id, url, payload: bytes, first_id, unique: str, spec: ArchiveSpec) -> Iterator[bytes]:
    own = f"<urn:page:{'' if page_id is None else page_id}:{unique}>"
    uri = None if url is None else " ".join(str(url).split())
    common = [("WARC-Date", "2024-01-01T00:00:00Z"), ("WARC-Target-URI", uri), ("WARC-Payload-Digest", f"sha1:{sha1_base32(payload)}")]
    http = [("Content-Type", "application/http; msgtype=response")]
    if first_id is not None and first_id != page_id:
        block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html\r\nContent-Length: %d\r\n\r\n" % len(payload)
        profile = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
        yield _record([("WARC-Type", "revisit"), ("WARC-Record-ID", own), *common, *http, ("WARC-Profile", profile), ("WARC-Refers-To", f"<urn:page:{first_id}>")], block)
        return
    block = b"HTTP/1.1 200 OK\r\nContent-Type: text/html\r\nTransfer-Encoding: chunked\r\n\r\n" + chunked(payload, spec.chunk_bytes)
    cuts = [block[i : i + spec.segment_bytes] for i in range(0, len(block), spec.segment_bytes)]
    for n, cut in enumerate(cuts, 1):
        kind = "response" if n == 1 else "continuation"
        segment = [] if len(cuts) == 1 else [("WARC-Segment-Number", n)]
        if n > 1:
            segment += [("WARC-Segment-Origin-ID", own)] + [("WARC-Segment-Total-Length", len(block))] * (n == len(cuts))
        own_id = own if n == 1 else own.replace("page:", f"segment:{n}:")
        yield _record([("WARC-Type", kind), ("WARC-Record-ID", own_id), *common, *segment, *(http if n == 1 else [])], cut)


def write_archives(pages: DataFrame, path: str, spec: ArchiveSpec | None = None, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> None:
    """Write one logical record per row. Of equal payloads of ``min_bytes`` or more, the least id is the response.

    Null payloads count as empty; a null id never refers nor is referred to; repeated rows of the least id are
    responses each. Only digests that occur more than once are joined; their table is broadcast below a
    bound, so payloads are shuffled, by page, only where repeats are many.
    """
    spec = spec or ArchiveSpec()
    payload = F.coalesce(F.col(html_col).cast("string").cast("binary"), F.lit(b""))
    own = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), payload.alias("payload"))
    own = own.withColumn("d", F.when(F.octet_length("payload") >= spec.min_bytes, F.sha1("payload")))
    firsts = own.where("d is not null and page_id is not null").groupBy("d").agg(F.min("page_id").alias("first_id"), F.count("*").alias("n"))
    firsts = durable(firsts.where("n > 1").drop("n"))
    if measured_bytes(firsts) <= spec.broadcast_bytes:
        joined = own.join(F.broadcast(firsts), "d", "left").select("page_id", "url", "payload", "first_id")
    else:  # digests meet without their payloads, which then travel by page and not by a digest that many may share
        roles = own.where("page_id is not null").select("page_id", "d").join(firsts, "d").where("first_id <> page_id").distinct()
        roles = durable(roles).select(F.col("page_id").alias("i"), F.col("d").alias("k"), "first_id")
        joined = own.join(roles, (F.col("page_id") == F.col("i")) & (F.col("d") == F.col("k")), "left").select("page_id", "url", "payload", "first_id")
    size = own.agg(F.avg(F.octet_length("payload"))).first()[0] or 0.0

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, k = TaskContext.get().partitionId(), 0
        for b in batches:
            out, held = [], 0
            for page_id, url, body, first in zip(*[c for c in b.columns], strict=True):
                k += 1
                for r in _records_of(page_id.as_py(), url.as_py(), body.as_py(), first.as_py(), f"{task}-{k}", spec):
                    out.append(r)
                    held += len(r)
                if held > 8 << 20:
                    yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["value"])
                    out, held = [], 0
            yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["value"])

    rows = joined.mapInArrow(run, "value binary").select(F.col("value").cast("string").alias("value"))
    per_file = int(max(16, min(1 << 20, spec.file_bytes // (size + 600))))
    rows.write.option("lineSep", END).option("maxRecordsPerFile", per_file).text(path)


def parse_archive(data: bytes) -> Iterator[tuple]:
    """Records of one archive file, gzip members or plain, as tuples of ``RECORD``."""
    while data[:2] == b"\x1f\x8b":
        plain, rest = [], data
        while rest[:2] == b"\x1f\x8b":
            z = zlib.decompressobj(31)
            plain.append(z.decompress(rest))
            rest = z.unused_data
        data = b"".join(plain)
    at = 0
    while (at := data.find(b"WARC/1.", at)) >= 0:
        end = data.index(b"\r\n\r\n", at)
        lines = data[at:end].decode("utf-8", "replace").split("\r\n")[1:]
        head = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}
        n = int(head["content-length"])
        block = data[end + 4 : end + 4 + n]
        at = end + 4 + n
        own, refers = head.get("warc-record-id", ""), head.get("warc-refers-to", "")
        number = lambda urn: int(x) if urn.startswith("<urn:page:") and (x := urn[10:-1].split(":")[0]).lstrip("-").isdigit() else None
        yield (
            own, head.get("warc-type"), head.get("warc-segment-origin-id"), int(head["warc-segment-number"]) if "warc-segment-number" in head else None,
            int(head["warc-segment-total-length"]) if "warc-segment-total-length" in head else None, number(own), head.get("warc-target-uri"),
            head.get("warc-payload-digest"), number(refers), block,
        )


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    kinds = {"string": pa.string(), "long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    fields = [x.split() for x in schema.split(", ")]
    cols = list(zip(*rows, strict=True)) or [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(list(c), kinds[t]) for c, (_, t) in zip(cols, fields, strict=True)], [n for n, _ in fields])


def read_records(spark: SparkSession, path: str) -> DataFrame:
    """All records of the archives in a folder, one row each; a task holds one file at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for content in b.column(0):
                rows, held = [], 0
                for r in parse_archive(content.as_py()):
                    rows.append(r)
                    held += len(r[-1])
                    if held > 8 << 20:
                        yield _batch(rows, RECORD)
                        rows, held = [], 0
                yield _batch(rows, RECORD)

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, RECORD)


def restore(blocks: list[tuple[int | None, int | None, bytes]]) -> tuple[bytes, str | None]:
    """Block of an origin record out of its ``(number, total, bytes)`` segments, and what is wrong with it."""
    blocks = sorted(blocks, key=lambda x: x[0] or 1)
    whole = b"".join(x[2] for x in blocks)
    if len(blocks) == 1 and blocks[0][0] is None:
        return whole, None
    if [x[0] for x in blocks] != list(range(1, len(blocks) + 1)):
        return whole, "segments are missing or repeated"
    total = blocks[-1][1]
    return whole, None if total == len(whole) else f"total length {len(whole)} is not {total}"


def _page(kind, page_id, url, digest, refers_to, blocks) -> tuple:
    block, problem = restore([(b["segment"], b["total"], b["block"]) for b in blocks])
    head, _, body = block.partition(b"\r\n\r\n")
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(b":") for x in head.split(b"\r\n")[1:])}
    told = (digest or "").removeprefix("sha1:")
    if kind == "revisit":
        return page_id, url, kind, refers_to, int(fields.get(b"content-length", b"0")), told, problem
    try:
        payload = unchunk(body) if fields.get(b"transfer-encoding", b"").lower() == b"chunked" else body
    except ValueError as e:
        payload, problem = body, problem or f"framing: {e}"
    own = sha1_base32(payload)
    return page_id, url, kind, None, len(payload), own, problem or (None if own == told or not told else "digest differs")


def read_pages(spark: SparkSession, path: str) -> DataFrame:
    """Logical records: segments are put together, framing decoded, lengths and digests verified (column ``problem``).

    Only segmented records are shuffled, by the identifier of their origin. Damaged records are returned with a
    ``problem``, never dropped; continuations whose origin is missing come back as kind ``continuation``.
    """
    records = read_records(spark, path).where("kind in ('response', 'revisit', 'continuation')")
    part = F.struct("segment", "total", "block")
    meta = ["kind", "page_id", "url", "digest", "refers_to"]
    single = records.where("segment is null").select(*meta, F.array(part).alias("blocks"))
    cut = records.where("segment is not null").withColumn("o", F.coalesce("origin_id", "record_id"))
    firsts = [F.coalesce(F.max(F.when(F.col("segment") == 1, F.col(c))), F.max(c)).alias(c) for c in meta]
    joined = cut.groupBy("o").agg(*firsts, F.collect_list(part).alias("blocks")).drop("o")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cols = [b.column(b.schema.get_field_index(c)) for c in [*meta, "blocks"]]
            yield _batch([_page(*[x.as_py() for x in row]) for row in zip(*cols, strict=True)], PAGE)

    return single.union(joined.select(*meta, "blocks")).mapInArrow(run, PAGE)


def round_trip(pages: DataFrame, spec: ArchiveSpec | None = None, path: str | None = None) -> DataFrame:
    """Write ``pages`` as archives in the shared folder and read them back, one row per page."""
    spark = pages.sparkSession
    path = path or new_folder(spark, "warc-")
    write_archives(pages, path, spec)
    return read_pages(spark, path)
