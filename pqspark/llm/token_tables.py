"""Token ids in sorted-string-table shards.

A shard file holds the documents of one range of numbers, in key order:

    data block *    entries with prefix-compressed keys, a restart list, zstd-compressed as a whole
    index block     last key, place, raw size and checksum of each data block
    filter block    a Bloom filter over all keys
    footer          places of the two, counts, magic

A lookup reads the footer, asks the filter, bisects the index, and then bisects
the restarts of one block.  Keys are the document number (null first), big-endian
with the sign bit turned, and then a count for rows that repeat a number.  Values
are ids as little-endian 16-bit numbers where the vocabulary allows, else 32-bit.
"""

from __future__ import annotations

import bisect
import re
import struct
import zlib
from collections.abc import Iterable, Iterator
from functools import lru_cache
from uuid import uuid4

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pqspark.llm.common import Files, fresh_path, lean_batches, partitions, stored

# Fixed values of the format
MAGIC = b"pqsst001"
FOOTER = struct.Struct("<QQQQQQB7x8s")
BLOCK_BYTES, RESTART = 1 << 16, 16
BLOOM_BITS, BLOOM_HASHES = 10, 7

#: Documents of a shard, at most about (fewer where the cluster has more partitions); tokens of the end mark and of the vocabulary file.
SHARD_ROWS = 16_384
END_ID = 2
#: Distinct pre-tokens whose ids a worker remembers.
WORDS_HELD = 1_000_000
VOCABULARY = "byte_bpe_50k.json"


def varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def read_varint(raw: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = raw[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


def key_of(doc_id: int | None, copy: int = 0) -> bytes:
    return (b"\0" + bytes(8) if doc_id is None else b"\1" + ((doc_id + (1 << 63)) & (1 << 64) - 1).to_bytes(8, "big")) + copy.to_bytes(4, "big")


def id_of(key: bytes) -> int | None:
    return int.from_bytes(key[1:9], "big") - (1 << 63) if key[0] else None


def _bloom_bits(key: bytes, m: int) -> list[int]:
    a, b = zlib.crc32(key), zlib.crc32(key, 0x9747B28C) | 1
    return [(a + k * b) % m for k in range(BLOOM_HASHES)]


class TableWriter:
    """Turns (key, value) pairs in key order into the bytes of a shard; holds one block and the index."""

    def __init__(self, item: int):
        self.item, self.entries, self.ids = item, 0, 0
        self.keys: list[bytes] = []
        self.index: list[bytes] = []
        self.place = 0
        self.zstd = zstandard.ZstdCompressor(level=3)
        self._clear()

    def _clear(self) -> None:
        self.block, self.restarts, self.count, self.last, self.size = [], [], 0, b"", 0

    def add(self, key: bytes, value: bytes) -> Iterator[bytes]:
        shared = 0
        if self.count % RESTART == 0:
            self.restarts.append(self.size)
        else:
            while shared < len(key) and key[shared] == self.last[shared]:
                shared += 1
        head = varint(shared) + varint(len(key) - shared) + varint(len(value)) + key[shared:]
        self.block += [head, value]
        self.size += len(head) + len(value)
        self.count, self.last = self.count + 1, key
        self.keys.append(key[:9])
        self.entries, self.ids = self.entries + 1, self.ids + len(value) // self.item
        if self.size >= BLOCK_BYTES:
            yield self._close()

    def _close(self) -> bytes:
        raw = b"".join(self.block) + struct.pack(f"<{len(self.restarts)}I", *self.restarts) + struct.pack("<I", len(self.restarts))
        out = self.zstd.compress(raw)
        self.index.append(struct.pack("<H", len(self.last)) + self.last + struct.pack("<QQQI", self.place, len(out), len(raw), zlib.crc32(out)))
        self.place += len(out)
        self._clear()
        return out

    def finish(self) -> Iterator[bytes]:
        if self.count:
            yield self._close()
        index = self.zstd.compress(b"".join(self.index))
        m = max(64, BLOOM_BITS * len(self.keys))
        bits = np.zeros(-(-m // 8), np.uint8)
        for key in self.keys:
            for b in _bloom_bits(key, m):
                bits[b >> 3] |= 1 << (b & 7)
        bloom = struct.pack("<Q", m) + bits.tobytes()
        yield index
        yield bloom
        yield FOOTER.pack(self.place, len(index), self.place + len(index), len(bloom), self.entries, self.ids, self.item, MAGIC)


class TableReader:
    """A shard file opened for scans and lookups."""

    def __init__(self, file):
        self.file = file
        file.seek(0, 2)
        end = file.tell()
        file.seek(end - FOOTER.size)
        index_at, index_size, self.bloom_at, self.bloom_size, self.entries, self.ids, self.item, magic = FOOTER.unpack(file.read(FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a token table")
        self.zstd = zstandard.ZstdDecompressor()
        raw, at = self.zstd.decompress(self._at(index_at, index_size), max_output_size=1 << 31), 0
        self.last, self.blocks = [], []
        while at < len(raw):
            (n,) = struct.unpack_from("<H", raw, at)
            self.last.append(raw[at + 2 : at + 2 + n])
            self.blocks.append(struct.unpack_from("<QQQI", raw, at + 2 + n))
            at += 2 + n + 28
        self.bloom: bytes | None = None

    def _at(self, place: int, size: int) -> bytes:
        self.file.seek(place)
        return self.file.read(size)

    def _block(self, k: int) -> tuple[bytes, list[int]]:
        place, size, raw_size, crc = self.blocks[k]
        packed = self._at(place, size)
        if zlib.crc32(packed) != crc:
            raise OSError(f"block {k} is damaged")
        raw = self.zstd.decompress(packed, max_output_size=raw_size)
        (n,) = struct.unpack_from("<I", raw, len(raw) - 4)
        return raw[: len(raw) - 4 - 4 * n], list(struct.unpack_from(f"<{n}I", raw, len(raw) - 4 - 4 * n))

    @staticmethod
    def _entries(raw: bytes, at: int = 0) -> Iterator[tuple[bytes, bytes]]:
        key = b""
        while at < len(raw):
            shared, at = read_varint(raw, at)
            own, at = read_varint(raw, at)
            size, at = read_varint(raw, at)
            key = key[:shared] + raw[at : at + own]
            at += own
            yield key, raw[at : at + size]
            at += size

    def numbers(self, value: bytes) -> np.ndarray:
        return np.frombuffer(value, "<u2" if self.item == 2 else "<u4")

    def scan(self) -> Iterator[tuple[int | None, np.ndarray]]:
        for k in range(len(self.blocks)):
            for key, value in self._entries(self._block(k)[0]):
                yield id_of(key), self.numbers(value)

    def maybe(self, doc_id: int | None) -> bool:
        if self.bloom is None:
            self.bloom = self._at(self.bloom_at, self.bloom_size)
        (m,) = struct.unpack_from("<Q", self.bloom)
        return all(self.bloom[8 + (b >> 3)] >> (b & 7) & 1 for b in _bloom_bits(key_of(doc_id)[:9], m))

    def get(self, doc_id: int | None, copy: int = 0) -> np.ndarray | None:
        """The ids of a document, None where the shard has none of that number."""
        key = key_of(doc_id, copy)
        if not self.maybe(doc_id) or (k := bisect.bisect_left(self.last, key)) == len(self.last):
            return None
        raw, restarts = self._block(k)
        lead = bisect.bisect_right(restarts, key, key=lambda at: next(self._entries(raw, at))[0]) - 1
        for found, value in self._entries(raw, restarts[max(0, lead)]):
            if found == key:
                return self.numbers(value)
            if found > key:
                break
        return None


def _byte_letters() -> dict[int, int]:
    """The letter that a byte-level vocabulary writes each byte as: printable ones themselves, the others from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return {b: b if b in plain else next(rest) for b in range(256)}


class _Words(dict):
    """Ids of a pre-token as bytes; each distinct one goes through the library's merges once."""

    def __init__(self, tokenizer, kind: str):
        super().__init__()
        self.tokenize, self.kind, self.letters = tokenizer.model.tokenize, kind, _byte_letters()

    def __missing__(self, word: str) -> bytes:
        if len(self) > WORDS_HELD:
            self.clear()
        out = self[word] = np.array([t.id for t in self.tokenize(word.encode().decode("latin-1").translate(self.letters))], self.kind).tobytes()
        return out


# The same cuts as the library's pattern for texts of these characters only, where the standard module agrees with it.
_PLAIN_CUT = re.compile(r"'(?:[sdmt]|ll|ve|re)| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+")
_NOT_PLAIN = re.compile(r"[^\x00-\x1b\x20-\x7fÀ-ÖØ-öø-ÿŒœ]")


@lru_cache(maxsize=2)
def encoder(vocabulary: str = VOCABULARY, item: int = 2):
    """A function from a text to its ids as bytes, equal to the library's ids of the whole text; kept for a worker's later tasks.

    The library cuts a text at its pattern before it merges, so ids of a text
    are those of its cuts in a row; cuts repeat, and each distinct one is
    merged once.  Texts that hold an added token are encoded in one piece.
    """
    import public_tokenizers
    import regex
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(public_tokenizers.path(vocabulary))
    added = [t.content for t in tokenizer.get_added_tokens_decoder().values()]
    cut, kind = regex.compile(public_tokenizers.PATTERN).findall, "<u2" if item == 2 else "<u4"
    words = _Words(tokenizer, kind)

    def ids(text: str) -> bytes:
        if any(a in text for a in added):
            return np.array(tokenizer.encode(text, add_special_tokens=False).ids, kind).tobytes()
        return b"".join([words[w] for w in (cut if _NOT_PLAIN.search(text) else _PLAIN_CUT.findall)(text)])

    return ids


def _encoded_rows(vocabulary: str, item: int, bounds: list[int]):
    def rows(batches):
        ids, end = encoder(vocabulary, item), END_ID.to_bytes(item, "little")
        edge = np.array(bounds, np.int64)
        for batch in batches:
            numbers = batch.column(0)
            shard = np.searchsorted(edge, numbers.fill_null(-(1 << 63)).to_numpy())
            values = [ids(t or "") + end for t in batch.column(1).to_pylist()]
            crc = pa.array([zlib.crc32(v) for v in values], pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(shard.astype(np.int32)), numbers, crc, pa.array(values, pa.binary())], names=["shard", "doc_id", "crc", "ids"])

    return rows


def _written_rows(path: str, item: int):
    """A manifest row per shard; rows come sorted by shard and key."""

    def entries(batches) -> Iterator[tuple[int, int | None, bytes]]:
        for batch in batches:
            yield from zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), (v.as_py() for v in batch.column(3)), strict=True)

    def rows(batches):
        files, source = Files(path), entries(batches)
        head = next(source, None)
        while head is not None:
            shard = head[0]
            writer, name = TableWriter(item), f"shard-{shard:06d}-{uuid4().hex}.sst"

            def chunks(writer=writer, shard=shard) -> Iterable[bytes]:
                nonlocal head
                before, copy = (), 0
                while head is not None and head[0] == shard:
                    copy = copy + 1 if before == (head[1],) else 0
                    before = (head[1],)
                    yield from writer.add(key_of(head[1], copy), head[2])
                    head = next(source, None)
                yield from writer.finish()

            size = files.write(name, chunks())
            yield pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([name]), pa.array([writer.entries], pa.int64()), pa.array([writer.ids], pa.int64()), pa.array([size], pa.int64())], names=["shard", "file", "n_docs", "n_ids", "n_bytes"])

    return rows


MANIFEST = "shard int, file string, n_docs long, n_ids long, n_bytes long"


def write_tables(docs: DataFrame, path: str, vocabulary: str = VOCABULARY, item: int = 2, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """Encode docs(doc_id, text) into shard files under path; returns the stored manifest with each shard's first position.

    A null text is an empty one, whose ids are the end mark alone; null numbers
    come first; rows that repeat a number follow each other.  A file counts once
    the manifest names it, so repeated or lost tasks leave at most unnamed files.
    """
    spark = docs.sparkSession
    lean_batches(spark)
    light = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    n = light.count()
    shards = max(1, -(-n // shard_rows), min(n // 256, partitions(spark)))
    bounds = []
    if shards > 1:
        got = light.agg(F.percentile_approx("doc_id", [k / shards for k in range(1, shards)], 100_000)).first()[0]
        bounds = sorted(set(got or []))
    rows = light.mapInArrow(_encoded_rows(vocabulary, item, bounds), "shard int, doc_id long, crc long, ids binary")
    dealt = rows.repartition(min(len(bounds) + 1, 4 * partitions(spark)), "shard").sortWithinPartitions("shard", "doc_id", "crc", "ids")
    manifest = stored(dealt.mapInArrow(_written_rows(path, item), MANIFEST), "manifest")
    # a row per shard: few, whatever the corpus holds
    before = F.sum("n_ids").over(Window.partitionBy().orderBy("shard")) - F.col("n_ids")
    return stored(manifest.withColumn("start", before), "manifest")


def read_tables(manifest: DataFrame, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32, shard) of every document in the manifest's files, read block by block."""

    def rows(batches):
        files = Files(path)
        for batch in batches:
            for shard, name, start in zip(*(batch.column(c).to_pylist() for c in ("shard", "file", "start")), strict=True):
                with files.open(name) as file:
                    out: list[tuple] = []
                    for doc_id, ids in TableReader(file).scan():
                        out.append((doc_id, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes()), shard))
                        start += len(ids)
                        if len(out) >= 5000:
                            yield table(out)
                            out = []
                    yield table(out)

    def table(out: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32())
        return pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], kind) for k, kind in enumerate(kinds)], names=["doc_id", "start", "n_tokens", "ids_crc32", "shard"])

    spread = manifest.repartition(2 * partitions(manifest.sparkSession), "shard")
    return spread.mapInArrow(rows, "doc_id long, start long, n_tokens long, ids_crc32 long, shard int")


def encoded(docs: DataFrame, vocabulary: str = VOCABULARY, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """Write docs as token tables in the shared folder and return what a scan of the files finds."""
    path = fresh_path(docs.sparkSession, "token-tables")
    return read_tables(write_tables(docs, path, vocabulary, shard_rows=shard_rows), path)
