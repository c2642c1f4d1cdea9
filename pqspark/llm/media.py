"""Media columns: a Spark data source over archives of media members.

An archive is a ZIP file whose members are stored as they are; its directory
gives the place of each.  A scan is planned from the archives' names and sizes alone:
each is cut into byte ranges, and a task reads the directory of its archive and
streams the payloads of the members that begin in its range as Arrow batches.  A member that fails to read or to pass its
checksum is tried again by its offset, alone.

Members here are PNG images: 8-bit samples, 64 RGB pixels (192 bytes) to a row.
"""

from __future__ import annotations

import hashlib
import json
import struct
import time
import zipfile
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from uuid import uuid4

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage

from pqspark.llm.common import Files, fresh_path, lean_batches

SAMPLES = 192
#: Bytes of a read partition and of an archive, about; attempts for a member.
RANGE_BYTES, ARCHIVE_BYTES, ATTEMPTS = 8 << 20, 256 << 20, 3
SCHEMA = "name string, media binary, archive string, member_offset long"
MANIFEST = "_members.json"


# ------------------------------------------------------------------ samples


def padded(text: str | None) -> tuple[int, bytes]:
    """(bytes of the text, its UTF-8 with spaces up to a positive multiple of 192)."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    return len(raw), raw.ljust(max(1, -(-len(raw) // SAMPLES)) * SAMPLES, b" ")


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


PNG = b"\x89PNG\r\n\x1a\n"


def to_image(n_bytes: int, payload: bytes) -> bytes:
    """A PNG whose samples are the payload; a text chunk keeps the length without padding."""
    rows = len(payload) // SAMPLES
    raster = np.zeros((rows, SAMPLES + 1), np.uint8)
    raster[:, 1:] = np.frombuffer(payload, np.uint8).reshape(rows, SAMPLES)
    head = struct.pack(">IIBBBBB", SAMPLES // 3, rows, 8, 2, 0, 0, 0)
    return PNG + _chunk(b"IHDR", head) + _chunk(b"tEXt", b"bytes\0%d" % n_bytes) + _chunk(b"IDAT", zlib.compress(raster.tobytes(), 4)) + _chunk(b"IEND", b"")


def from_image(media: bytes) -> tuple[int, bytes]:
    """(bytes without padding, samples) of an image that to_image made; checks every chunk."""
    if media[:8] != PNG:
        raise ValueError("not a PNG")
    at, n_bytes, rows, data = 8, -1, 0, []
    while at < len(media):
        (size,) = struct.unpack_from(">I", media, at)
        kind, body = media[at + 4 : at + 8], media[at + 8 : at + 8 + size]
        if struct.unpack_from(">I", media, at + 8 + size)[0] != zlib.crc32(kind + body):
            raise ValueError("a chunk is damaged")
        if kind == b"IHDR":
            rows = struct.unpack_from(">II", body)[1]
        elif kind == b"tEXt":
            n_bytes = int(body.partition(b"\0")[2])
        elif kind == b"IDAT":
            data.append(body)
        at += 12 + size
    raster = np.frombuffer(zlib.decompress(b"".join(data)), np.uint8).reshape(rows, SAMPLES + 1)
    if raster[:, 0].any():
        raise ValueError("filtered rows are not ours")
    return n_bytes, raster[:, 1:].tobytes()


def feature(payload: bytes) -> str:
    """Rows, mean and spread of the samples, distinct values, and shares of eight bands, all in whole numbers."""
    x = np.frombuffer(payload, np.uint8)
    counts = np.bincount(x, minlength=256).astype(object)
    total, n = sum(int(c) * v for v, c in enumerate(counts)), len(x)
    square = sum(int(c) * v * v for v, c in enumerate(counts))
    bands = [int(sum(counts[k : k + 32])) * 1000 // n for k in range(0, 256, 32)]
    return f"rows={n // SAMPLES};mean={1000 * total // n};var={(n * square - total * total) // (n * n)};values={int((counts > 0).sum())};bands={','.join(map(str, bands))}"


# -------------------------------------------------------------- data source


@dataclass
class Written(WriterCommitMessage):
    archives: list[tuple[str, int]]  # name, bytes


@dataclass
class Range(InputPartition):
    archive: str
    first: int  # the members whose headers begin from here
    end: int  # to before here


class ArchiveSource(DataSource):
    """format("media_archives"): option path is a folder of archives with a list of those that are committed."""

    @classmethod
    def name(cls) -> str:
        return "media_archives"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> ArchiveReader:
        return ArchiveReader(self.options)

    def writer(self, schema, overwrite: bool) -> ArchiveWriter:
        return ArchiveWriter(self.options["path"])


class ArchiveWriter(DataSourceArrowWriter):
    """Each task writes archives of its own; commit lists them, and unlisted ones don't count."""

    def __init__(self, path: str):
        self.path = path

    def write(self, iterator: Iterator[pa.RecordBatch]) -> Written:
        files, written = Files(self.path), []
        rows = ((n, m) for batch in iterator for n, m in zip(batch.column("name").to_pylist(), (v.as_py() for v in batch.column("media")), strict=True))
        head = next(rows, None)
        while head is not None:
            name, sink = f"{uuid4().hex}.zip", _Sink()

            def chunks(sink=sink):
                nonlocal head
                with zipfile.ZipFile(sink, "w", zipfile.ZIP_STORED) as archive:
                    while head is not None and sink.place < ARCHIVE_BYTES:
                        archive.writestr(zipfile.ZipInfo(head[0]), head[1])
                        head = next(rows, None)
                        yield sink.drain()
                yield sink.drain()

            written.append((name, files.write(name, chunks())))
        return Written(written)

    def commit(self, messages: list[Written | None]) -> None:
        listed = sorted(a for m in messages if m for a in m.archives)
        Files(self.path).write(MANIFEST, [json.dumps(listed).encode()])

    def abort(self, messages: list[Written | None]) -> None:
        """Nothing to undo: no list was written."""


class _Sink:
    """What zipfile writes to: keeps only what has not been passed on."""

    def __init__(self):
        self.place, self.held = 0, []

    def write(self, data: bytes) -> int:
        self.held.append(bytes(data))
        self.place += len(data)
        return len(data)

    def tell(self) -> int:
        return self.place

    def flush(self) -> None:
        pass

    def seekable(self) -> bool:
        return False

    def drain(self) -> bytes:
        out, self.held = b"".join(self.held), []
        return out


class ArchiveReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"]
        self.range_bytes = int(options.get("rangeBytes", RANGE_BYTES))
        self.attempts = int(options.get("attempts", ATTEMPTS))

    def partitions(self) -> list[Range]:
        """Byte ranges of the listed archives; none is opened."""
        with Files(self.path).open(MANIFEST) as f:
            listed = json.loads(f.read())
        return [Range(name, at, at + self.range_bytes) for name, size in listed for at in range(0, size, self.range_bytes)] or [Range("", 0, 0)]

    @staticmethod
    def members(file, first: int, end: int) -> list[tuple[str, int, int, int]]:
        """(name, offset of the header, bytes, checksum) of the members that begin in a range, from the archive's directory."""
        with zipfile.ZipFile(file) as archive:
            return sorted(((m.filename, m.header_offset, m.file_size, m.CRC) for m in archive.infolist() if first <= m.header_offset < end), key=lambda m: m[1])

    def read(self, partition: Range) -> Iterator[pa.RecordBatch]:
        if not partition.archive:
            return
        files, file, held, size = Files(self.path), None, [], 0

        def tried(read: Callable, *args):
            """What read gives, on a new handle after each failure."""
            nonlocal file
            for attempt in range(1, self.attempts + 1):
                try:
                    file = file or files.open(partition.archive)
                    return read(file, *args)
                except (OSError, ValueError, zipfile.BadZipFile):
                    if file is not None:
                        file.close()
                    file = None
                    if attempt == self.attempts:
                        raise
                    time.sleep(0.05 * attempt)

        try:
            for name, *place in tried(self.members, partition.first, partition.end):
                held.append((name, tried(self.member, *place), partition.archive, place[0]))
                size += place[1]
                if size >= 1 << 20 or len(held) >= 500:
                    yield self._batch(held)
                    held, size = [], 0
        finally:
            if file is not None:
                file.close()
        if held:
            yield self._batch(held)

    @staticmethod
    def member(file, offset: int, size: int, crc: int) -> bytes:
        file.seek(offset)
        head = file.read(30)
        if head[:4] != b"PK\x03\x04":
            raise ValueError("no member starts here")
        name, extra = struct.unpack_from("<HH", head, 26)
        file.seek(offset + 30 + name + extra)
        data = file.read(size)
        if len(data) != size or zlib.crc32(data) != crc:
            raise ValueError("a member is damaged")
        return data

    @staticmethod
    def _batch(rows: list[tuple]) -> pa.RecordBatch:
        kinds = (("name", pa.string()), ("media", pa.binary()), ("archive", pa.string()), ("member_offset", pa.int64()))
        return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kind) for k, (_, kind) in enumerate(kinds)], names=[n for n, _ in kinds])


# -------------------------------------------------------------------- query


def _image_rows(batches):
    for batch in batches:
        names = [f"{'' if d is None else d}.png" for d in batch.column(0).to_pylist()]
        media = [to_image(*padded(t)) for t in batch.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(media, pa.binary())], names=["name", "media"])


RESULT = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _digest_rows(batches):
    names = [c.split()[0] for c in RESULT.split(", ")]
    kinds = [pa.int64() if c.split()[1] == "long" else pa.string() for c in RESULT.split(", ")]
    for batch in batches:
        out = []
        for name, media in zip(batch.column(0).to_pylist(), (v.as_py() for v in batch.column(1)), strict=True):
            n_bytes, payload = from_image(media)
            number = name[: -len(".png")]
            out.append((int(number) if number else None, n_bytes, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(media), hashlib.sha256(media).hexdigest(), feature(payload)))
        yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], kind) for k, kind in enumerate(kinds)], names=names)


def write_archives(docs: DataFrame, path: str) -> None:
    """Store the whole texts of docs(doc_id, text) as images in archives under path."""
    spark = docs.sparkSession
    lean_batches(spark)
    spark.dataSource.register(ArchiveSource)
    images = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_image_rows, "name string, media binary")
    images.write.format("media_archives").mode("append").save(path)


def read_archives(spark: SparkSession, path: str, **options) -> DataFrame:
    """(name, media, archive, member_offset) of all members in the archives under path."""
    spark.dataSource.register(ArchiveSource)
    return spark.read.format("media_archives").options(**options).load(path)


def digested(docs: DataFrame) -> DataFrame:
    """Store every text losslessly as image samples, read the stored bytes back, and describe them.

    A null text is an empty one (one row of spaces); a null doc_id stays null;
    rows that repeat are stored and returned as often as they come; other columns
    are not read; an empty table gives an empty result.
    """
    path = fresh_path(docs.sparkSession, "media")
    write_archives(docs, path)
    return read_archives(docs.sparkSession, path).select("name", "media").mapInArrow(_digest_rows, RESULT)
