"""WARC records in seekable Zstandard bundles.

A task writes its records into bundles: records are grouped into frames of
about ``FRAME_BYTES``, each an independent Zstandard frame, and a bundle ends in
a skippable frame with the sizes of all its frames (the seekable format's seek
table), so a reader finds a frame without reading those before it. The index
maps a record to its bundle, its frame and its place inside the frame.

Among records with equal payloads the one with the largest page id is the
response and the others are revisits that name it. Only digests are grouped;
the payloads are joined with the digests that occur twice, so that a payload
with a third of all rows is dealt like any other.

Bundles go to the shared folder through Arrow's file systems, first under a
name of the attempt and then renamed, so a task that is run again replaces its
bundles by equal ones.

Defined results: null html is an empty payload; rows with equal page id and
equal payload are all responses if the id is the largest; a null page id is
less than any other and is read back as null; a null URL has no target field;
an empty table writes nothing; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..joins import key_join
from ..scratch import materialise, new_path
from . import arrow

FRAME_BYTES = 256 * 1024
BUNDLE_BYTES = 128 * 1024 * 1024
LEVEL = 3
#: Frames that are read one after another from one opened bundle, and bytes of records that a reading task has on average.
RUN_FRAMES, TASK_BYTES = 16, 128 * 1024 * 1024
#: Fixed values of the seekable format: its skippable frame and the last four bytes.
SKIPPABLE, SEEKABLE = 0x184D2A5E, 0x8F92EAB1
#: All records carry one date, so equal inputs give equal bundles.
DATE = "2000-01-01T00:00:00Z"
_NAMES = uuid.UUID(int=0)

INDEX = "page_id long, record_id string, bundle string, frame int, offset long, length long"
RECORD = "page_id long, url string, record_id string, record_type string, refers_to long, payload_bytes long, payload_digest string"


@dataclass
class Record:
    """A parsed record; ``payload`` is empty for revisits."""

    headers: dict[str, str]
    payload: bytes

    @property
    def page_id(self) -> int | None:
        return int(x) if (x := self.headers.get("WARC-Page-ID")) is not None else None


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page_id: int | None, place: str = "") -> str:
    return f"<urn:uuid:{uuid.uuid5(_NAMES, f'{page_id}/{place}')}>"


def _clean(value: str) -> str:
    """A header value without characters that end a line."""
    return "".join(c if c >= " " and c != "\x7f" else f"%{ord(c):02X}" for c in value)


def build(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, place: str = "") -> tuple[str, bytes]:
    """Id and bytes of a record."""
    own = record_id(page_id, place)
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    head = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {own}", f"WARC-Date: {DATE}"]
    if page_id is not None:
        head.append(f"WARC-Page-ID: {page_id}")
    if url is not None:
        head.append(f"WARC-Target-URI: {_clean(url)}")
    head += [f"WARC-Payload-Digest: sha1:{base32_sha1(payload)}", f"WARC-Payload-Length: {len(payload)}", "Content-Type: application/http; msgtype=response"]
    if refers_to is not None:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_id(refers_to)}", f"WARC-Refers-To-Page: {refers_to}"]
    head.append(f"Content-Length: {len(block)}")
    return own, "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse(data: bytes, at: int = 0) -> tuple[Record, int]:
    """The record that begins at ``at`` and where it ends."""
    end = data.index(b"\r\n\r\n", at)
    lines = data[at:end].decode().split("\r\n")
    headers = dict(line.split(": ", 1) for line in lines[1:])
    start = end + 4
    stop = start + int(headers["Content-Length"])
    block = data[start:stop]
    return Record(headers, block[block.index(b"\r\n\r\n") + 4 :]), stop + 4


def records(frame: bytes) -> Iterator[Record]:
    at = 0
    while at < len(frame):
        record, at = parse(frame, at)
        yield record


class BundleWriter:
    """Writes frames to a stream and closes it with the seek table."""

    def __init__(self, stream):
        self.stream, self.sizes, self.written = stream, [], 0
        self.held, self.length = [], 0
        self.compressor = zstandard.ZstdCompressor(level=LEVEL, write_checksum=True)

    def add(self, record: bytes) -> tuple[int, int]:
        """Frame and place of a record."""
        if self.length and self.length + len(record) > FRAME_BYTES:
            self._flush()
        place = len(self.sizes), self.length
        self.held.append(record)
        self.length += len(record)
        return place

    def _flush(self) -> None:
        if self.held:
            packed = self.compressor.compress(b"".join(self.held))
            self.stream.write(packed)
            self.sizes.append((len(packed), self.length))
            self.written += len(packed)
            self.held, self.length = [], 0

    def close(self) -> None:
        self._flush()
        entries = b"".join(struct.pack("<II", *x) for x in self.sizes)
        footer = struct.pack("<IBI", len(self.sizes), 0, SEEKABLE)
        self.stream.write(struct.pack("<II", SKIPPABLE, len(entries) + len(footer)) + entries + footer)
        self.stream.close()


class BundleReader:
    """Reads single frames of a bundle by its seek table."""

    def __init__(self, source):
        self.source = source
        size = source.size()
        source.seek(size - 9)
        count, _, magic = struct.unpack("<IBI", source.read(9))
        if magic != SEEKABLE:
            raise ValueError("no seek table")
        source.seek(size - 9 - 8 * count)
        self.sizes = list(struct.iter_unpack("<II", source.read(8 * count)))
        self.starts = [0]
        for packed, _ in self.sizes:
            self.starts.append(self.starts[-1] + packed)

    def __len__(self) -> int:
        return len(self.sizes)

    def frame(self, i: int) -> bytes:
        packed, size = self.sizes[i]
        self.source.seek(self.starts[i])
        return zstandard.ZstdDecompressor().decompress(self.source.read(packed), max_output_size=max(1, size))

    def record(self, frame: int, offset: int) -> Record:
        return parse(self.frame(frame), offset)[0]


def open_bundle(uri: str) -> BundleReader:
    system, path = fs.FileSystem.from_uri(uri)
    return BundleReader(system.open_input_file(path))


def decided(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", least: int = 0) -> DataFrame:
    """Pages with the page that each refers to, null for responses; payloads under ``least`` bytes are all responses."""
    html = F.coalesce(F.col(html_col).cast("string"), F.lit(""))
    own = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), html.alias("html"))
    keyed = own.withColumns({"size": F.octet_length("html").cast("long"), "digest": F.unhex(F.sha1("html"))})
    twice = keyed.where(F.col("size") >= least).groupBy("digest", "size").agg(F.max("page_id").alias("first"), F.count(F.lit(1)).alias("times")).where("times > 1").drop("times")
    joined = key_join(keyed, materialise(twice, "warc-digests"), ["digest", "size"], "left")
    refers = F.when(F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first")), F.col("first"))
    return joined.select("page_id", "url", "html", refers.alias("refers_to"))


def write(pages: DataFrame, folder: str | None = None, **options) -> DataFrame:
    """Write all pages to bundles below ``folder`` and return the index; the bundles exist when it returns."""
    folder = folder or new_path(pages.sparkSession, "warc")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task = TaskContext.get()
        system, root = fs.FileSystem.from_uri(folder)
        system.create_dir(root, recursive=True)
        writer, name, rows, number, seen = None, "", [], 0, 0

        def finish() -> pa.RecordBatch:
            writer.close()
            system.move(f"{root}/.{name}-{task.taskAttemptId()}", f"{root}/{name}")
            return pa.RecordBatch.from_pylist([dict(zip(schema.names, r)) for r in rows], schema=schema)

        for part, column in arrow.text_chunks(batches, "html"):
            for page_id, url, html, refers_to in zip(part.column("page_id").to_pylist(), part.column("url").to_pylist(), column.to_pylist(), part.column("refers_to").to_pylist()):
                if writer is None:
                    name = f"bundle-{task.partitionId():06d}-{number:04d}.warc.zst"
                    writer, number = BundleWriter(system.open_output_stream(f"{root}/.{name}-{task.taskAttemptId()}")), number + 1
                own, data = build(page_id, url, html.encode(), refers_to, "" if page_id is not None else f"{task.partitionId()}/{seen}")
                seen += 1
                frame, offset = writer.add(data)
                rows.append((page_id, own, f"{folder}/{name}", frame, offset, len(data)))
                if writer.written > BUNDLE_BYTES:
                    yield finish()
                    writer, rows = None, []
        if writer is not None:
            yield finish()

    schema = pa.schema([("page_id", pa.int64()), ("record_id", pa.string()), ("bundle", pa.string()), ("frame", pa.int32()), ("offset", pa.int64()), ("length", pa.int64())])
    return materialise(decided(pages, **options).mapInArrow(run, INDEX), "warc-index")


_RECORD_SCHEMA = pa.schema(
    [("page_id", pa.int64()), ("url", pa.string()), ("record_id", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string())]
)


def _row(record: Record, payload: bool) -> dict:
    h = record.headers
    digest = h["WARC-Payload-Digest"].removeprefix("sha1:")
    if h["WARC-Type"] == "response" and (base32_sha1(record.payload) != digest or len(record.payload) != int(h["WARC-Payload-Length"])):
        raise ValueError(f"record {h['WARC-Record-ID']} differs from its digest")
    refers = h.get("WARC-Refers-To-Page")
    row = {"page_id": record.page_id, "url": h.get("WARC-Target-URI"), "record_id": h["WARC-Record-ID"], "record_type": h["WARC-Type"], "refers_to": int(refers) if refers else None}
    row |= {"payload_bytes": int(h["WARC-Payload-Length"]), "payload_digest": digest}
    return row | ({"payload": record.payload.decode()} if payload else {})


def read(spark: SparkSession, bundles: DataFrame, *, payload: bool = False) -> DataFrame:
    """All records of the bundles named in the column ``bundle``; payloads are checked against their digests."""
    schema = _RECORD_SCHEMA.append(pa.field("payload", pa.string())) if payload else _RECORD_SCHEMA

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri in batch.column("bundle").to_pylist():
                bundle = open_bundle(uri)
                for i in range(len(bundle)):
                    yield pa.RecordBatch.from_pylist([_row(r, payload) for r in records(bundle.frame(i))], schema=schema)

    names = bundles.select("bundle").distinct()
    return names.repartition(max(1, names.count()), "bundle").mapInArrow(run, RECORD + (", payload string" if payload else ""))


def fetch(index: DataFrame) -> DataFrame:
    """The records of index rows, each by its frame alone, with payloads."""
    schema = _RECORD_SCHEMA.append(pa.field("payload", pa.string()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple[str, BundleReader] | None = None
        for batch in batches:
            out = []
            for uri, frame, offset in zip(*(batch.column(c).to_pylist() for c in ("bundle", "frame", "offset"))):
                if held is None or held[0] != uri:
                    held = uri, open_bundle(uri)
                out.append(_row(held[1].record(frame, offset), True))
            yield pa.RecordBatch.from_pylist(out, schema=schema)

    return index.select("bundle", "frame", "offset").mapInArrow(run, RECORD + ", payload string")


def read_indexed(index: DataFrame, *, payload: bool = False) -> DataFrame:
    """All records of the index, by runs of frames that tasks share out; each must stand where the index says, with its id."""
    schema = _RECORD_SCHEMA.append(pa.field("payload", pa.string())) if payload else _RECORD_SCHEMA

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        uri, bundle = None, None
        for batch in batches:
            for row in batch.to_pylist():
                if row["bundle"] != uri:
                    uri, bundle = row["bundle"], open_bundle(row["bundle"])
                frame, out = bundle.frame(row["frame"]), []
                for entry in sorted(row["entries"], key=lambda e: e["offset"]):
                    record, end = parse(frame, entry["offset"])
                    if record.headers["WARC-Record-ID"] != entry["record_id"] or end - entry["offset"] != entry["length"]:
                        raise ValueError(f"{uri}, frame {row['frame']}: no record {entry['record_id']} at {entry['offset']}")
                    out.append(_row(record, payload))
                yield pa.RecordBatch.from_pylist(out, schema=schema)

    size = index.agg(F.count_distinct("bundle").alias("bundles"), F.coalesce(F.sum("length"), F.lit(0)).alias("bytes")).first()
    tasks = max(1, size["bundles"], -(-size["bytes"] // TASK_BYTES))
    runs = index.withColumn("run", F.floor(F.col("frame") / RUN_FRAMES)).repartition(tasks, "bundle", "run")
    # A frame's records are bounded by its bytes.
    frames = runs.groupBy("bundle", "run", "frame").agg(F.collect_list(F.struct("offset", "length", "record_id")).alias("entries"))
    return frames.sortWithinPartitions("bundle", "frame").select("bundle", "frame", "entries").mapInArrow(run, RECORD + (", payload string" if payload else ""))


def archive_and_read(pages: DataFrame, **options) -> DataFrame:
    """Write all pages, then read every record back by the index."""
    return read_indexed(write(pages, **options))
