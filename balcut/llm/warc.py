"""WARC bundles: independent Zstandard frames with a seek table at the end, and reading them back.

A bundle is a valid ``.warc.zst``: frames of whole records that decompress on their own, then a
skippable frame that lists the sizes of all frames, so a reader finds any frame from the file's end.
The index maps every record to bundle, frame and the place within the decompressed frame. Bundles lie
in the folder all executors share; each attempt of a task writes files of its own, and only
those that the index names belong to the archive, so lost executors leave nothing half-read.

Of records with equal payloads of some size, the smallest id is a response and the others revisit it.

Defined results: a null page is an empty payload; empty and small payloads are always responses;
repeated rows of the responding id are responses too; a row without an id is a response of its own; an empty table makes no bundle and
an empty result; any text, control characters included, comes back as it was; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import scratch_path, settle, table

#: Payloads under this size are stored each time.
MIN_REVISIT = 100
#: Bytes of records in a frame, and compressed bytes after which a new bundle begins.
FRAME_BYTES, BUNDLE_BYTES = 1 << 20, 256 << 20
LEVEL = 3
#: Numbers of the seekable format (fixed values): skippable frame, seek table.
SKIPPABLE, SEEKABLE = 0x184D2A5E, 0x8F92EAB1
DATE = "1970-01-01T00:00:00Z"
INDEX = "page_id bigint, bundle string, frame int, at int, length int"
RECORD = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint"


def record_id(page_id: int | None) -> str:
    return f"<urn:uuid:{uuid.UUID(bytes=hashlib.sha256(f'page {page_id}'.encode()).digest()[:16])}>"


def record(page_id: int | None, url: str, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One WARC record; a revisit has no block but the digest and length of what it stands for."""
    block = payload if refers_to is None else b""
    head = [
        "WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {record_id(page_id)}", f"WARC-Date: {DATE}",
        f"WARC-Target-URI: {' '.join(url.split())}", f"WARC-Payload-Digest: sha256:{digest}", f"X-Page-ID: {'' if page_id is None else page_id}", f"X-Payload-Length: {len(payload)}",
    ]
    if refers_to is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_id(refers_to)}", f"X-Refers-To-Page: {refers_to}"]
    head += ["Content-Type: text/html; charset=utf-8", f"Content-Length: {len(block)}", "", ""]
    return "\r\n".join(head).encode() + block + b"\r\n\r\n"


def records_in(frame: bytes) -> Iterator[tuple[int, dict[str, str], bytes]]:
    """(place, header, block) of every record of a decompressed frame."""
    at = 0
    while at < len(frame):
        end = frame.index(b"\r\n\r\n", at)
        header = dict(line.split(": ", 1) for line in frame[at:end].decode().split("\r\n")[1:])
        start, n = end + 4, int(header["Content-Length"])
        yield at, header, frame[start : start + n]
        at = start + n + 4


class Bundle:
    """Writes frames to one file and its seek table at the end."""

    def __init__(self, folder: str):
        import zstandard
        from pyarrow import fs

        self.name = f"{uuid.uuid4().hex}.warc.zst"
        store, path = fs.FileSystem.from_uri(folder)
        store.create_dir(path, recursive=True)
        self.out = store.open_output_stream(f"{path}/{self.name}", compression=None)
        self.press, self.frames, self.size = zstandard.ZstdCompressor(level=LEVEL), [], 0

    def add(self, frame: bytes) -> None:
        packed = self.press.compress(frame)
        self.out.write(packed)
        self.frames.append((len(packed), len(frame)))
        self.size += len(packed)

    def close(self) -> None:
        body = b"".join(struct.pack("<II", *f) for f in self.frames) + struct.pack("<IBI", len(self.frames), 0, SEEKABLE)
        self.out.write(struct.pack("<II", SKIPPABLE, len(body)) + body)
        self.out.close()


class Reader:
    """Opens a bundle by its seek table."""

    def __init__(self, folder: str, name: str):
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(folder)
        self.file = store.open_input_file(f"{path}/{name}")
        size = self.file.size()
        n, _, magic = struct.unpack("<IBI", self.file.read_at(9, size - 9))
        if magic != SEEKABLE:
            raise ValueError(f"{name} has no seek table")
        table = self.file.read_at(8 * n, size - 9 - 8 * n)
        self.frames, at = [], 0
        for packed, plain in struct.iter_unpack("<II", table):
            self.frames.append((at, packed, plain))
            at += packed

    def frame(self, k: int) -> bytes:
        import zstandard

        at, packed, plain = self.frames[k]
        return zstandard.ZstdDecompressor().decompress(self.file.read_at(packed, at), max_output_size=plain)


def revisits(pages: DataFrame, min_bytes: int = MIN_REVISIT) -> DataFrame:
    """(page_id, payload_digest, refers_to) of the records that repeat an earlier payload.

    Only ids and digests are shuffled; counts per digest are summed before.
    """
    sums = pages.select("page_id", "payload_digest", "payload_bytes").where(F.col("payload_bytes") >= min_bytes)
    first = sums.groupBy("payload_digest").agg(F.min("page_id").alias("refers_to"), F.max("page_id").alias("_last")).where("refers_to < _last").drop("_last")
    return sums.join(first, "payload_digest").where("page_id <> refers_to").select("page_id", "payload_digest", "refers_to").distinct()


def write_bundles(pages: DataFrame, folder: str, page_id: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """Write one record per row; gives the settled index (page_id, bundle, frame, at, length)."""
    body = F.coalesce(F.col(html), F.lit(""))
    rows = pages.select(F.col(page_id).alias("page_id"), F.coalesce(F.col(url), F.lit("")).alias("url"), body.alias("html"), F.sha2(body.cast("binary"), 256).alias("payload_digest"), F.octet_length(body).cast("long").alias("payload_bytes"))
    # The digests are computed once more for the joined table: cheaper than to move pages.
    joined = rows.join(revisits(rows), ["page_id", "payload_digest"], "left").select("page_id", "url", "html", "payload_digest", "refers_to")

    def write(batches):
        bundle, frame, size, places = None, [], 0, []

        def flush():
            nonlocal bundle, frame, size, places
            out = None
            if frame:
                bundle = bundle or Bundle(folder)
                k = len(bundle.frames)
                bundle.add(b"".join(frame))
                out = pa.RecordBatch.from_arrays([pa.array([p[0] for p in places], pa.int64()), pa.array([bundle.name] * len(places), pa.string()), pa.array([k] * len(places), pa.int32()), pa.array([p[1] for p in places], pa.int32()), pa.array([p[2] for p in places], pa.int32())], names=["page_id", "bundle", "frame", "at", "length"])
                if bundle.size >= BUNDLE_BYTES:
                    bundle.close()
                    bundle = None
            frame, size, places = [], 0, []
            return out

        for batch in batches:
            ids, urls, texts, sums, refers = (batch.column(k) for k in range(5))
            for k in range(batch.num_rows):
                one = record(ids[k].as_py(), urls[k].as_py(), texts[k].as_buffer().to_pybytes(), sums[k].as_py(), refers[k].as_py())
                places.append((ids[k].as_py(), size, len(one)))
                frame.append(one)
                size += len(one)
                if size >= FRAME_BYTES:
                    yield flush()
        if frame:
            yield flush()
        if bundle:
            bundle.close()

    return settle(joined.mapInArrow(write, INDEX), "warc-index")


def _parsed(header: dict[str, str], block: bytes) -> tuple:
    kind = header["WARC-Type"]
    if kind == "response":
        return int(header["X-Page-ID"]) if header["X-Page-ID"] else None, len(block), hashlib.sha256(block).hexdigest(), kind, None
    return int(header["X-Page-ID"]), int(header["X-Payload-Length"]), header["WARC-Payload-Digest"].removeprefix("sha256:"), kind, int(header["X-Refers-To-Page"])


def read_bundles(index: DataFrame, folder: str) -> DataFrame:
    """Read every frame that the index names, through the bundles' seek tables, and parse all its records."""
    frames = index.select("bundle", "frame").distinct()

    def read(batches):
        names, kinds = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"], [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
        for batch in batches:
            open_name, reader = None, None
            for name, k in sorted(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)):
                if name != open_name:
                    open_name, reader = name, Reader(folder, name)
                rows = [_parsed(header, block) for _, header, block in records_in(reader.frame(k))]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    return frames.mapInArrow(read, RECORD)


def fetch(index: DataFrame, folder: str, ids: DataFrame) -> DataFrame:
    """(page_id, payload) of chosen responses: only the frames that hold them are read."""
    chosen = index.join(ids.select("page_id").distinct(), "page_id", "left_semi").repartition("bundle").sortWithinPartitions("bundle", "frame", "at")

    def read(batches):
        open_name = open_frame = reader = data = None
        for batch in batches:
            out = []
            for page, name, k, at, n in zip(*(batch.column(c).to_pylist() for c in range(5)), strict=True):
                if name != open_name:
                    open_name, open_frame, reader = name, None, Reader(folder, name)
                if k != open_frame:
                    open_frame, data = k, reader.frame(k)
                _, header, block = next(records_in(data[at : at + n]))
                out.append((page, block if header["WARC-Type"] == "response" else None))
            yield pa.RecordBatch.from_arrays([pa.array([o[0] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.binary())], names=["page_id", "payload"])

    return chosen.select("page_id", "bundle", "frame", "at", "length").mapInArrow(read, "page_id bigint, payload binary")


def op7_warc_bundles(spark, sf_dir: str) -> DataFrame:
    folder = scratch_path(spark, "warc")
    return read_bundles(write_bundles(table(spark, sf_dir, "pages"), folder), folder)


OP7_SQL = f"""
with p as (select page_id, strlen(coalesce(html, '')) as payload_bytes, sha256(coalesce(html, '')) as payload_digest from pages),
f as (select payload_digest, min(page_id) as first from p where payload_bytes >= {MIN_REVISIT} group by payload_digest)
select page_id, payload_bytes, p.payload_digest,
  case when first < page_id then 'revisit' else 'response' end as record_type,
  case when first < page_id then first end as refers_to
from p left join f on f.payload_digest = p.payload_digest and payload_bytes >= {MIN_REVISIT}
"""
