"""WARC records in seekable Zstandard bundles.

A bundle is a run of independent Zstandard frames, each holding some whole WARC records, closed by a
seek table in a skippable frame, so that one record is read by decompressing one frame. Bundles are
the rows of a table (bundle, content, index), so that they live in any store that Spark writes to;
``content`` is byte for byte what a ``.warc.zst`` file holds, and ``export`` writes such files.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
from collections.abc import Iterable, Iterator
from pathlib import Path

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Written

#: Fixed values of the seekable format: skippable frame, footer, and the size of the footer.
SKIPPABLE, FOOTER, FOOTER_BYTES = 0x184D2A5E, 0x8F92EAB1, 9
DATE = "1970-01-01T00:00:00Z"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
BUNDLES = "bundle string, content binary, records array<struct<page_id:bigint,frame:int,start:int,bytes:int>>"
READ = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint"


def urn(page_id: int | None) -> str:
    return f"<urn:page:{'' if page_id is None else page_id}>"


def page_of(name: str) -> int | None:
    number = name.removeprefix("<urn:page:").removesuffix(">")
    return int(number) if number else None


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, date: str = DATE) -> bytes:
    """One WARC/1.1 record. A revisit carries no payload, but its digest and length."""
    kind, body = ("response", payload) if refers_to is None else ("revisit", b"")
    clean = " ".join((url or "").split())
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {urn(page_id)}", f"WARC-Date: {date}", f"WARC-Target-URI: {clean}",
        f"WARC-Payload-Digest: sha1:{digest}", f"WARC-Payload-Length: {len(payload)}", "Content-Type: text/html; charset=utf-8", f"Content-Length: {len(body)}",
    ]
    if refers_to is not None:
        head += [f"WARC-Refers-To: {urn(refers_to)}", f"WARC-Profile: {REVISIT_PROFILE}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def parse(data: bytes, start: int = 0) -> tuple[dict[str, str], bytes, int]:
    """Headers and body of the record at ``start``, and where the next one starts."""
    end = data.index(b"\r\n\r\n", start)
    version, *lines = data[start:end].decode().split("\r\n")
    if not version.startswith("WARC/"):
        raise ValueError("not a WARC record")
    head = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines)
    n = int(head["Content-Length"])
    return head, data[end + 4 : end + 4 + n], end + 8 + n


class Bundle:
    """Gathers records into frames of about ``frame_bytes`` and closes with the seek table."""

    def __init__(self, frame_bytes: int = 1 << 16, level: int = 6):
        self.frame_bytes, self.zstd = frame_bytes, zstandard.ZstdCompressor(level=level)
        self.frames: list[bytes] = []
        self.sizes: list[tuple[int, int]] = []
        self.index: list[dict] = []
        self.open, self.bytes = bytearray(), 0

    def add(self, page_id: int, rec: bytes) -> None:
        self.index.append({"page_id": page_id, "frame": len(self.frames), "start": len(self.open), "bytes": len(rec)})
        self.open += rec
        if len(self.open) >= self.frame_bytes:
            self._cut()

    def _cut(self) -> None:
        if self.open:
            self.frames.append(self.zstd.compress(bytes(self.open)))
            self.sizes.append((len(self.frames[-1]), len(self.open)))
            self.bytes += len(self.frames[-1])
            self.open = bytearray()

    def close(self) -> bytes:
        self._cut()
        rows = b"".join(struct.pack("<II", *s) for s in self.sizes)
        return b"".join(self.frames) + struct.pack("<II", SKIPPABLE, len(rows) + FOOTER_BYTES) + rows + struct.pack("<IBI", len(self.sizes), 0, FOOTER)


def seek_table(content: bytes) -> list[tuple[int, int, int]]:
    """(offset, compressed bytes, plain bytes) of each frame, from the footer alone."""
    n, _, magic = struct.unpack("<IBI", content[-FOOTER_BYTES:])
    if magic != FOOTER:
        raise ValueError("no seek table")
    out, at = [], 0
    for packed, plain in struct.iter_unpack("<II", content[-FOOTER_BYTES - 8 * n : -FOOTER_BYTES]):
        out.append((at, packed, plain))
        at += packed
    return out


def read_record(content: bytes, frame: int, start: int) -> tuple[dict[str, str], bytes]:
    """One record, by decompressing its frame only."""
    at, packed, plain = seek_table(content)[frame]
    head, body, _ = parse(zstandard.ZstdDecompressor().decompress(content[at : at + packed], max_output_size=plain), start)
    return head, body


def with_revisits(pages: DataFrame, min_bytes: int = 1000) -> DataFrame:
    """(page_id, url, html, digest, refers_to). Digests are grouped first, without the payloads; a
    hot payload is one row per task at the exchange, and its join can be split. A page_id may come with several
    payloads: each has its own owner. A page without an id revisits the owner, and owns only among its like."""
    html = F.coalesce(F.col("html"), F.lit(""))
    payload = [F.sha1(html.cast("binary")).alias("digest"), F.xxhash64(html).alias("x"), F.octet_length(html).alias("n")]
    none = F.col("page_id").isNull().alias("none")
    keyed = pages.select("page_id", *payload)
    owners = keyed.where(F.col("n") >= min_bytes).groupBy("digest", "x", "n").agg(F.max("page_id").alias("owner"), F.count(F.lit(1)).alias("copies")).where("copies > 1")
    revisits = keyed.where(F.col("n") >= min_bytes).join(owners, ["digest", "x", "n"]).where("coalesce(page_id < owner, owner is not null)")
    revisits = revisits.groupBy(F.coalesce("page_id", F.lit(0)).alias("k"), none, "digest", "x", "n").agg(F.max("owner").alias("refers_to"))
    rows = pages.select("page_id", "url", html.alias("html"), *payload, none, F.coalesce("page_id", F.lit(0)).alias("k"))
    return rows.join(revisits, ["k", "none", "digest", "x", "n"], "left").select("page_id", "url", "html", "digest", "refers_to")


def write_bundles(pages: DataFrame, min_bytes: int = 1000, frame_bytes: int = 1 << 16, bundle_bytes: int = 16 << 20) -> DataFrame:
    """Table of bundles. Each task fills bundles of about ``bundle_bytes`` one after another.

    A null html is an empty payload, a null url an empty target, a null page_id a record without a number;
    repeated rows give repeated records; equal page_ids with equal payloads are all responses. An empty
    table gives no bundle. Other columns are not read.
    """

    def pack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        b, schema = Bundle(frame_bytes), None

        def flush() -> pa.RecordBatch:
            content = b.close()
            name = f"{hashlib.sha1(content).hexdigest()}.warc.zst"
            return pa.RecordBatch.from_pylist([{"bundle": name, "content": content, "records": b.index}], schema=schema)

        kinds = pa.list_(pa.struct([("page_id", pa.int64()), ("frame", pa.int32()), ("start", pa.int32()), ("bytes", pa.int32())]))
        schema = pa.schema([("bundle", pa.string()), ("content", pa.binary()), ("records", kinds)])
        for batch in batches:
            for i, url, html, digest, ref in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                b.add(i, record(i, url, html.encode(), digest, ref))
                if b.bytes >= bundle_bytes:
                    yield flush()
                    b = Bundle(frame_bytes)
        if b.index:
            yield flush()

    return with_revisits(pages, min_bytes).select("page_id", "url", "html", "digest", F.col("refers_to").cast("bigint")).mapInArrow(pack, BUNDLES)


def offsets(bundles: DataFrame) -> DataFrame:
    """(page_id, bundle, frame, start, bytes): record identifier to place within a frame."""
    return bundles.select("bundle", F.explode("records").alias("r")).select("r.page_id", "bundle", "r.frame", "r.start", "r.bytes")


def read_bundles(bundles: DataFrame) -> DataFrame:
    """One row per record, read frame by frame through each bundle's seek table. The digest and the
    length of a response are computed anew from its payload and must equal its headers."""

    def unpack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        z = zstandard.ZstdDecompressor()
        schema = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())])
        for batch in batches:
            for content in batch.column(0):
                content, rows = content.as_py(), []
                for at, packed, plain in seek_table(content):
                    data, start = z.decompress(content[at : at + packed], max_output_size=plain), 0
                    while start < len(data):
                        head, body, start = parse(data, start)
                        digest, n, kind = head["WARC-Payload-Digest"].removeprefix("sha1:"), int(head["WARC-Payload-Length"]), head["WARC-Type"]
                        if kind == "response" and (len(body) != n or hashlib.sha1(body).hexdigest() != digest):
                            raise ValueError(f"damaged record {head['WARC-Record-ID']}")
                        ref = head.get("WARC-Refers-To")
                        rows.append((page_of(head["WARC-Record-ID"]), n, digest, kind, ref and page_of(ref)))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    return bundles.select("content").mapInArrow(unpack, READ)


def lookup(bundles: DataFrame, ids: DataFrame) -> DataFrame:
    """(page_id, html) of the responses asked for. The offsets of one bundle are gathered before its
    content joins them, so that a bundle travels and is opened once however many records are asked for, and
    only their frames are decompressed, each once. Ids asked twice count once, null ids find nothing; an id that
    no response bears is left out."""

    def fetch(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        z = zstandard.ZstdDecompressor()
        for batch in batches:
            for k in range(batch.num_rows):
                content, table = batch.column(0)[k].as_py(), None
                frames = seek_table(content)
                for frame, start, page_id in sorted((r["frame"], r["start"], r["page_id"]) for r in batch.column(1)[k].as_py()):
                    if table is None or table[0] != frame:
                        at, packed, plain = frames[frame]
                        table = frame, z.decompress(content[at : at + packed], max_output_size=plain)
                    head, body, _ = parse(table[1], start)
                    if head["WARC-Type"] == "response":
                        yield pa.RecordBatch.from_arrays([pa.array([page_id], pa.int64()), pa.array([body.decode()])], names=["page_id", "html"])

    asked = offsets(bundles).join(ids.select("page_id"), "page_id", "left_semi")
    places = asked.groupBy("bundle").agg(F.collect_set(F.struct("frame", "start", "page_id")).alias("places"))
    # A bundle's name is that of its content: rows that repeat one come from repeated pages, and each gives its own.
    return bundles.select("bundle", "content").join(places, "bundle").select("content", "places").mapInArrow(fetch, "page_id bigint, html string")


def export(bundles: DataFrame, folder: str) -> None:
    """Writes the bundles as files of a folder that all tasks share (a mounted store). A file appears whole
    or not at all, and a task that runs again writes the same one; an empty table writes nothing."""

    def put(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, content in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                part = Path(folder, f".{name}.{uuid.uuid4().hex}")
                part.write_bytes(content)
                part.replace(Path(folder, name))
            yield batch.select([0])

    bundles.select("bundle", "content").mapInArrow(put, "bundle string").write.format("noop").mode("overwrite").save()


def archive_round_trip(pages: DataFrame, written: Written) -> DataFrame:
    """Writes the bundles to the shared folder and reads every record back from them."""
    return read_bundles(written.save(write_bundles(pages)))


SQL = """
with p as (select page_id, encode(coalesce(html, '')) as b from pages),
q as (select page_id, octet_length(b) as n, sha1(b) as d, max(page_id) over (partition by b) as m from p)
select page_id, cast(n as bigint) as payload_bytes, d as payload_digest, case when n >= 1000 and m <> page_id then 'revisit' else 'response' end as record_type,
 case when n >= 1000 and m <> page_id then m end as refers_to from q
"""
