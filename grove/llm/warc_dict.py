"""WARC archives compressed record by record with an embedded dictionary.

Each archive starts with a skippable frame that holds a Zstandard dictionary trained
on the first records to be archived (``SAMPLE_BYTES`` of them at most), followed by
one Zstandard frame a record, so a record can be read alone by its offset and still
compresses well. Archives roll over at ``roll`` payload bytes; a task only ever holds
the sample and one record.

Payloads that are equal are stored once: the row with the least page_id is a
``response``, the others are ``revisit`` records that refer to it. Digests are
compared as slim rows; payloads move once, by page.

An archive gets a new name at each attempt, and the table of records that the job
returns names the archives that count; what a lost executor left is never read.

Defined results: null html is an empty payload; a row with a null page_id is always
a response; rows repeated with the least page_id are responses.
"""

from __future__ import annotations

import base64
import hashlib
import re
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from grove.session import cut, scratch

#: Format constants: the skippable frame's magic number, line ends.
DICT_MAGIC = 0x184D2A5D
EOL = b"\r\n"
SAMPLE_BYTES, DICT_BYTES = 1 << 20, 64 << 10
#: Up to so many archive names are broadcast when archives are read.
MANY_ARCHIVES = 100_000
_BAD = re.compile(r"[\x00-\x20\x7f]")


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None, date: str) -> bytes:
    """One WARC/1.1 record."""
    head = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = head if refers_to is not None else head + payload
    name = f"urn:page:{page_id}" if page_id is not None else f"urn:uuid:{uuid.uuid4()}"
    fields = [
        "WARC/1.1",
        f"WARC-Type: {'response' if refers_to is None else 'revisit'}",
        f"WARC-Record-ID: <{name}>",
        f"WARC-Date: {date}",
        f"WARC-Target-URI: {_BAD.sub(lambda m: f'%{ord(m[0]):02X}', url or 'about:blank')}",
        f"WARC-Payload-Digest: sha1:{digest(payload)}",
    ]
    if refers_to is not None:
        fields += [f"WARC-Refers-To: <urn:page:{refers_to}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    fields += [f"X-Payload-Length: {len(payload)}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return EOL.join(f.encode() for f in fields) + EOL + EOL + block + EOL + EOL


class ArchiveWriter:
    """Archives in one folder, written through any file system that Arrow knows."""

    def __init__(self, folder: str, roll: int, level: int):
        from pyarrow import fs

        self.fs, self.root = fs.FileSystem.from_uri(folder if "://" in folder or folder.startswith("/") or ":" in folder else "/" + folder)
        self.fs.create_dir(self.root, recursive=True)
        self.roll, self.level = roll, level
        self.held: list[tuple] = []
        self.held_bytes = 0
        self.out = None

    def _open(self) -> None:
        self.name = f"{uuid.uuid4().hex}.warc.zst"
        self.out = self.fs.open_output_stream(f"{self.root}/{self.name}", compression=None)
        samples = [r for _, r in self.held]
        size = min(DICT_BYTES, max(4096, self.held_bytes // 8))
        try:
            words = zstandard.train_dictionary(size, [s[:16384] for s in samples], k=256, d=8, f=18, accel=4, split_point=1.0)
        except zstandard.ZstdError:  # too few or too uniform to train on: their own bytes serve, the last ones nearest
            words = zstandard.ZstdCompressionDict(b"".join(s[: max(8, size // len(samples))] for s in reversed(samples))[-size:], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        raw = words.as_bytes()
        self.out.write(struct.pack("<II", DICT_MAGIC, len(raw)) + raw)
        self.at = 8 + len(raw)
        self.took = 0
        self.packer = zstandard.ZstdCompressor(level=self.level, dict_data=words, write_checksum=True)

    def add(self, key: tuple, rec: bytes) -> Iterator[tuple]:
        if self.out is None:
            self.held.append((key, rec))
            self.held_bytes += len(rec)
            if self.held_bytes < SAMPLE_BYTES:
                return
            yield from self._flush()
        else:
            yield self._put(key, rec)
        if self.took >= self.roll:
            self.close()

    def _flush(self) -> Iterator[tuple]:
        self._open()
        for key, rec in self.held:
            yield self._put(key, rec)
        self.held, self.held_bytes = [], 0

    def _put(self, key: tuple, rec: bytes) -> tuple:
        frame = self.packer.compress(rec)
        self.out.write(frame)
        place = (*key, self.name, self.at, len(frame))
        self.at += len(frame)
        self.took += len(rec)
        return place

    def close(self) -> None:
        if self.out is not None:
            self.out.close()
            self.out = None

    def finish(self) -> Iterator[tuple]:
        if self.held:
            yield from self._flush()
        self.close()


def write_archives(pages: DataFrame, folder: str, roll: int = 32 << 20, level: int = 3, least_revisit: int = 0, date: str = "1970-01-01T00:00:00Z") -> DataFrame:
    """Archive ``pages(page_id, url, html)`` in ``folder``; return the written table of records
    (page_id, archive, at, size): where each record's frame lies."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce("html", F.lit("")).alias("html"))
    slim = rows.where(F.octet_length("html") >= least_revisit).select("page_id", F.sha1(F.col("html").cast("binary")).alias("sha"))
    least = slim.where("page_id is not null").groupBy("sha").agg(F.min("page_id").alias("first"))
    again = slim.join(least, "sha").where("page_id <> first").select(F.col("page_id").alias("_page"), F.col("sha").alias("_sha"), "first").distinct()
    keyed = rows.withColumn("sha", F.sha1(F.col("html").cast("binary"))).join(again, (F.col("page_id") == F.col("_page")) & (F.col("sha") == F.col("_sha")), "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = ArchiveWriter(folder, roll, level)
        done: list[tuple] = []

        def out() -> pa.RecordBatch:
            cols = list(zip(*done, strict=True)) if done else [[]] * 4
            done.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.string(), pa.int64(), pa.int64()), strict=True)], names=["page_id", "archive", "at", "size"])

        for b in batches:
            for page, url, html, first in zip(*(b.column(c) for c in ("page_id", "url", "html", "first")), strict=True):
                p = page.as_py()
                done.extend(w.add((p,), record(p, url.as_py(), html.as_py().encode(), first.as_py(), date)))
            if len(done) > 10_000:
                yield out()
        done.extend(w.finish())
        yield out()

    placed = keyed.select("page_id", "url", "html", "first").mapInArrow(run, "page_id long, archive string, at long, size long")
    return cut(placed, "records")


def parse_archive(data) -> Iterator[tuple[dict, bytes]]:
    """(fields, block) of each record of an archive."""
    view = memoryview(data)
    magic, size = struct.unpack("<II", view[:8])
    if magic != DICT_MAGIC:
        raise ValueError("not an archive with a leading dictionary frame")
    words = zstandard.ZstdCompressionDict(bytes(view[8 : 8 + size])) if size else None
    reader = zstandard.ZstdDecompressor(dict_data=words).stream_reader(view[8 + size :], read_across_frames=True)
    buf, at = b"", 0
    while True:
        end = buf.find(EOL + EOL, at)
        while end < 0:
            more = reader.read(1 << 20)
            if not more:
                break
            buf, at = buf[at:] + more, 0
            end = buf.find(EOL + EOL, at)
        if end < 0:
            return
        lines = buf[at:end].split(EOL)
        fields = dict(x.decode().split(": ", 1) for x in lines[1:])
        start, n = end + 4, int(fields["Content-Length"])
        while len(buf) < start + n + 4:
            more = reader.read(max(1 << 20, start + n + 4 - len(buf)))
            if not more:
                raise ValueError("archive ends inside a record")
            buf, start, at = buf[at:] + more, start - at, 0
        yield fields, buf[start : start + n]
        at = start + n + 4


def read_archives(records: DataFrame, folder: str) -> DataFrame:
    """(page_id, url, record_type, refers_to, payload_bytes, payload_digest, html) of every record in the
    archives that ``records`` names; html is null for revisits."""
    spark = records.sparkSession
    named = cut(records.select("archive").distinct(), "archives")
    schema = "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, html string"
    how_many = named.count()
    if how_many == 0:
        return spark.createDataFrame([], schema)
    if how_many <= MANY_ARCHIVES:  # names of 41 bytes
        named = F.broadcast(named)
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.warc.zst").load(folder).select(F.element_at(F.split("path", "/"), -1).alias("archive"), "content")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        page = re.compile(r"<urn:page:(-?\d+)>")

        def number(x: str | None) -> int | None:
            m = page.fullmatch(x or "")
            return int(m[1]) if m else None

        for b in batches:
            for content in b.column("content"):
                rows, size = [], 0
                for f, block in parse_archive(content.as_buffer()):
                    kind, want = f["WARC-Type"], f["WARC-Payload-Digest"].removeprefix("sha1:")
                    html = None
                    if kind == "response":
                        html = block[block.index(EOL + EOL) + 4 :]
                        if digest(html) != want or len(html) != int(f["X-Payload-Length"]):
                            raise ValueError(f"payload of {f['WARC-Record-ID']} differs from its digest")
                    rows.append((number(f["WARC-Record-ID"]), f["WARC-Target-URI"], kind, number(f.get("WARC-Refers-To")), int(f["X-Payload-Length"]), want, html))
                    size += len(block)
                    if size > 4 << 20:
                        yield pack(rows)
                        rows, size = [], 0
                if rows:
                    yield pack(rows)

    types = (pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
    names = ["page_id", "url", "record_type", "refers_to", "payload_bytes", "payload_digest", "html"]

    def pack(rows: list[tuple]) -> pa.RecordBatch:
        cols = list(zip(*rows, strict=True))
        cols[6] = [None if x is None else x.decode() for x in cols[6]]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=names)

    return files.join(named, "archive", "left_semi").select("content").mapInArrow(run, schema)


def round_trip(pages: DataFrame) -> DataFrame:
    """Write ``pages`` to a fresh folder and return what is read back."""
    folder = scratch(pages.sparkSession, "warc")
    return read_archives(write_archives(pages, folder), folder)
