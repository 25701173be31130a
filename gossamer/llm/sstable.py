"""Token ids in sorted-string-table shards.

A shard is one file::

    magic | data block ... | index block | Bloom filter | footer

Keys are document ids in an order-preserving 9-byte form, values are the ids of the document as
little-endian integers of 2 or 4 bytes. A data block holds entries with the prefix shared with the key
before left out, restart points every ``RESTART`` entries, and is compressed and check-summed. The
sparse index has the last key, place and number of ids before each block; a lookup asks the Bloom
filter, bisects the index, bisects the restart points and scans at most ``RESTART`` entries.

Cases: a null text is an empty document (its end id alone); a null doc_id sorts first; equal doc_ids
stay, ordered by the hash of their texts; an empty table gives no shard rows; other columns of the
input are not read. Each attempt of a task writes a file of its own name, and only the manifest of
successful attempts is read, so retries and speculation leave at most orphan files. A shard that reaches
``SHARD_BYTES`` is closed and the task opens the next, so what a writer holds (index and key hashes) is bounded.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from array import array
from bisect import bisect_left
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

MAGIC = b"GSMSST01"
RESTART = 16
BLOCK_BYTES = 64 << 10
BLOOM_BITS, BLOOM_HASHES = 10, 7
SHARD_BYTES = 256 << 20
PARTS = 1 << 20  #: shard numbers of one task
FOOTER = struct.Struct("<QQQQQQQI8s")  # index place, size; Bloom place, size, bits; documents, ids; id width; magic
MANIFEST = "shard long, path string, first_key binary, last_key binary, n_docs long, n_ids long, n_bytes long"


def key_of(doc_id: int | None) -> bytes:
    return b"\x00" * 9 if doc_id is None else b"\x01" + struct.pack(">Q", (doc_id + (1 << 63)) & (2**64 - 1))


def id_of(key: bytes) -> int | None:
    return None if key[0] == 0 else struct.unpack(">Q", key[1:])[0] - (1 << 63)


def _put_varint(out: bytearray, n: int) -> None:
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)


def _varint(data: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = data[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


class Block:
    """Entries of one block, built up or taken apart."""

    def __init__(self) -> None:
        self.data, self.restarts, self.n, self.last = bytearray(), [], 0, b""

    def add(self, key: bytes, value: bytes) -> None:
        shared = 0
        if self.n % RESTART == 0:
            self.restarts.append(len(self.data))
        else:
            top = min(len(key), len(self.last))
            while shared < top and key[shared] == self.last[shared]:
                shared += 1
        for x in (shared, len(key) - shared, len(value)):
            _put_varint(self.data, x)
        self.data += key[shared:]
        self.data += value
        self.last, self.n = key, self.n + 1

    def packed(self) -> bytes:
        raw = bytes(self.data) + struct.pack(f"<{len(self.restarts)}I", *self.restarts) + struct.pack("<I", len(self.restarts))
        body = zstandard.ZstdCompressor(level=1).compress(raw)
        return body + struct.pack("<I", zlib.crc32(body))


def _unpacked(stored: bytes) -> tuple[bytes, list[int], int]:
    """The entries, the restart points and where the entries end."""
    body, (crc,) = stored[:-4], struct.unpack("<I", stored[-4:])
    if zlib.crc32(body) != crc:
        raise ValueError("a block's checksum is wrong")
    raw = zstandard.ZstdDecompressor().decompress(body)
    (n,) = struct.unpack("<I", raw[-4:])
    end = len(raw) - 4 - 4 * n
    return raw, list(struct.unpack(f"<{n}I", raw[end:-4])), end


def _entries(raw: bytes, at: int, end: int) -> Iterator[tuple[bytes, bytes]]:
    key = b""
    while at < end:
        shared, at = _varint(raw, at)
        own, at = _varint(raw, at)
        size, at = _varint(raw, at)
        key = key[:shared] + raw[at : at + own]
        at += own
        yield key, raw[at : at + size]
        at += size


def _bloom_hashes(key: bytes) -> tuple[int, int]:
    return xxhash.xxh64_intdigest(key, seed=1) >> 8, xxhash.xxh64_intdigest(key, seed=2) >> 8 | 1


def _bloom_places(hashes: np.ndarray, bits: int) -> np.ndarray:
    """Filter places of keys, ``hashes`` two a row."""
    a, b = hashes[:, :1] % np.uint64(bits), hashes[:, 1:] % np.uint64(bits)
    return (a + np.arange(BLOOM_HASHES, dtype=np.uint64) * b) % np.uint64(bits)


class ShardWriter:
    def __init__(self, out, width: int):
        self.out, self.width, self.at = out, width, 0
        self.block, self.index, self.hashes = Block(), [], array("Q")
        self.n_docs = self.n_ids = self.block_ids = 0
        self.first = self.last = None
        self._write(MAGIC)

    def _write(self, data: bytes) -> None:
        self.out.write(data)
        self.at += len(data)

    def add(self, key: bytes, ids: bytes) -> None:
        """``ids``: little-endian unsigned 32-bit."""
        if self.last is not None and key < self.last:
            raise ValueError("keys must come in ascending order")
        self.first, self.last = key if self.first is None else self.first, key
        if self.width == 2:
            wide = np.frombuffer(ids, "<u4")
            if len(wide) and wide.max() > 0xFFFF:
                raise ValueError("ids over 65,535 need a width of 4 bytes")
            self.block.add(key, wide.astype("<u2").tobytes())
        else:
            self.block.add(key, ids)
        self.hashes.extend(_bloom_hashes(key))
        self.n_docs, self.n_ids, self.block_ids = self.n_docs + 1, self.n_ids + len(ids) // 4, self.block_ids + len(ids) // 4
        if len(self.block.data) >= BLOCK_BYTES:
            self._end_block()

    def _end_block(self) -> None:
        if self.block.n:
            stored = self.block.packed()
            self.index.append((self.block.last, self.at, len(stored), self.n_ids - self.block_ids))
            self._write(stored)
            self.block, self.block_ids = Block(), 0

    def close(self) -> None:
        self._end_block()
        index = Block()
        for last, at, size, before in self.index:
            index.add(last, struct.pack("<QQQ", at, size, before))
        stored, index_at = index.packed(), self.at
        self._write(stored)
        bits = max(64, BLOOM_BITS * self.n_docs)
        bloom = np.zeros((bits + 7) // 8 * 8, dtype=bool)
        hashes = np.frombuffer(self.hashes, np.uint64).reshape(-1, 2)
        for a in range(0, len(hashes), 65_536):
            bloom[_bloom_places(hashes[a : a + 65_536], bits)] = True
        packed, bloom_at = np.packbits(bloom).tobytes(), self.at
        self._write(packed)
        self._write(FOOTER.pack(index_at, len(stored), bloom_at, len(packed), bits, self.n_docs, self.n_ids, self.width, MAGIC))
        self.out.close()


class ShardReader:
    """``source``: a seekable binary file."""

    def __init__(self, source):
        self.source = source
        source.seek(0, 2)
        size = source.tell()
        source.seek(size - FOOTER.size)
        index_at, index_size, self.bloom_at, self.bloom_size, self.bits, self.n_docs, self.n_ids, self.width, magic = FOOTER.unpack(source.read(FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a shard file")
        raw, _, end = _unpacked(self._read(index_at, index_size))
        self.index = [(k, *struct.unpack("<QQQ", v)) for k, v in _entries(raw, 0, end)]
        self.last_keys = [x[0] for x in self.index]
        self.bloom: np.ndarray | None = None

    def _read(self, at: int, size: int) -> bytes:
        self.source.seek(at)
        return self.source.read(size)

    def _ids(self, value: bytes) -> bytes:
        return np.frombuffer(value, "<u2").astype("<u4").tobytes() if self.width == 2 else value

    def may_hold(self, key: bytes) -> bool:
        if self.bloom is None:
            self.bloom = np.unpackbits(np.frombuffer(self._read(self.bloom_at, self.bloom_size), np.uint8))
        return bool(self.bloom[_bloom_places(np.asarray([_bloom_hashes(key)], np.uint64), self.bits)].all())

    def get(self, key: bytes) -> list[bytes]:
        """The ids of every document of this key."""
        found: list[bytes] = []
        if not self.may_hold(key):
            return found
        for b in range(bisect_left(self.last_keys, key), len(self.index)):
            raw, restarts, end = _unpacked(self._read(self.index[b][1], self.index[b][2]))
            heads = [next(_entries(raw, r, end))[0] for r in restarts] if len(restarts) < 8 else None
            low = 0
            if heads is None:  # bisect the restart points without reading them all
                lo, hi = 0, len(restarts)
                while lo < hi:
                    mid = (lo + hi) // 2
                    if next(_entries(raw, restarts[mid], end))[0] < key:
                        lo = mid + 1
                    else:
                        hi = mid
                low = max(0, lo - 1)
            else:
                low = max(0, bisect_left(heads, key) - 1)
            for k, v in _entries(raw, restarts[low], end):
                if k > key:
                    return found
                if k == key:
                    found.append(self._ids(v))
        return found

    def scan(self) -> Iterator[tuple[bytes, int, bytes]]:
        """Key, ids of this shard before the document, ids; in order."""
        for _, at, size, before in self.index:
            raw, _, end = _unpacked(self._read(at, size))
            for key, value in _entries(raw, 0, end):
                ids = self._ids(value)
                yield key, before, ids
                before += len(ids) // 4


def _opened(uri: str):
    filesystem, path = pafs.FileSystem.from_uri(uri)
    return filesystem, path


def write_shards(docs: DataFrame, tokenizer: str, out: str, end_id: int = 1, splits: str = "space", width: int = 2, most: int = SHARD_BYTES) -> DataFrame:
    """Encodes ``docs (doc_id, text)`` and writes the shards of each range of doc_ids; returns the manifest.

    Only the raw rows are shuffled, by range; encoding and writing follow in the same task, in order.
    The manifest has one row a shard; ``shard`` ascends with the keys.
    """
    rows = common.texts(docs).withColumn("tie", F.xxhash64("text"))
    ranged = rows.repartitionByRange(F.col("doc_id").asc_nulls_first(), "tie").sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "tie", "text")
    end = np.asarray([end_id], "<u4").tobytes()

    def write(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        shard, writer, place = TaskContext.get().partitionId() * PARTS, None, ""
        encoder = common.text_encoder(tokenizer, splits)
        filesystem, folder = _opened(out)

        def closed() -> pa.RecordBatch:
            writer.close()
            row = (shard, place, writer.first, writer.last, writer.n_docs, writer.n_ids, writer.at)
            return pa.RecordBatch.from_arrays([pa.array([x], type=t) for x, t in zip(row, (pa.int64(), pa.string(), pa.binary(), pa.binary(), *[pa.int64()] * 3), strict=True)], ["shard", "path", "first_key", "last_key", "n_docs", "n_ids", "n_bytes"])

        for part in common.slices(batches):
            for doc_id, ids in zip(part.column(0).to_pylist(), encoder.batch(part.column(1)), strict=True):
                if writer is None:
                    filesystem.create_dir(folder, recursive=True)
                    name = f"shard-{shard:012d}-{uuid.uuid4().hex}.sst"
                    place, writer = f"{out}/{name}", ShardWriter(filesystem.open_output_stream(f"{folder}/{name}"), width)
                writer.add(key_of(doc_id), ids + end)
                if writer.at >= most:
                    yield closed()
                    shard, writer = shard + 1, None
        if writer is not None:
            yield closed()

    return common.settled(ranged.select("doc_id", "text").mapInArrow(write, MANIFEST), "manifest")


def with_starts(manifest: DataFrame) -> DataFrame:
    """Adds ``before``: the ids of all shards before. One narrow row a shard passes through one task."""
    before = F.sum("n_ids").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1))
    return manifest.withColumn("before", F.coalesce(before, F.lit(0)).cast("long"))


def as_ids(ids: bytes) -> bytes:
    return ids


def read_shards(manifest: DataFrame, tasks: int, kind: str = "ids binary", derive: Callable[[bytes], object] = as_ids) -> DataFrame:
    """Every document of the shards: ``doc_id, start, n_tokens, ids`` (little-endian unsigned 32-bit).

    ``kind`` and ``derive``: a column made of the ids in the same task instead of the ids themselves.
    """
    from pyspark.sql.pandas.types import to_arrow_type
    from pyspark.sql.types import StructType

    field = StructType.fromDDL(kind).fields[0]
    names, own = ["doc_id", "start", "n_tokens", field.name], to_arrow_type(field.dataType)

    def read(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, before in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                filesystem, place = _opened(path)
                with filesystem.open_input_file(place) as source:
                    held, size = [], 0
                    for key, at, ids in ShardReader(source).scan():
                        held.append((id_of(key), before + at, len(ids) // 4, derive(ids)))
                        size += len(ids) + 64
                        if size > common.SLICE_BYTES:
                            yield _rows(held)
                            held, size = [], 0
                    if held:
                        yield _rows(held)

    def _rows(held: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(x, type=t) for x, t in zip(zip(*held, strict=True), (pa.int64(), pa.int64(), pa.int64(), own), strict=True)], names)

    paths = with_starts(manifest).select("path", "before").repartition(tasks)
    return paths.mapInArrow(read, f"doc_id long, start long, n_tokens long, {kind}")


#: Shards whose first and last keys a lookup sends to its tasks at most: 512 TB in shards of ``SHARD_BYTES``.
MOST_SHARDS = 2_000_000


def lookup(manifest: DataFrame, wanted: DataFrame) -> DataFrame:
    """The documents of ``wanted (doc_id)`` by binary search: each id goes to the shards whose range has it.

    The key ranges (18 bytes a shard) are bisected in the tasks, then ids meet their shards by number; each task
    keeps its reader open.
    """
    ranges = [(bytes(r.first_key), bytes(r.last_key), r.shard) for r in manifest.select("first_key", "last_key", "shard").orderBy("shard").limit(MOST_SHARDS + 1).toLocalIterator()]
    if len(ranges) > MOST_SHARDS:
        raise ValueError(f"a lookup takes at most {MOST_SHARDS} shards")
    sent = manifest.sparkSession.sparkContext.broadcast(ranges)
    ids = wanted.select(F.col("doc_id").cast("long")).where("doc_id is not null").distinct()

    def route(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lasts = [r[1] for r in sent.value]
        for batch in batches:
            found = []
            for doc_id in batch.column(0).to_pylist():
                key = key_of(doc_id)
                at = bisect_left(lasts, key)
                while at < len(lasts) and sent.value[at][0] <= key:
                    found.append((doc_id, sent.value[at][2]))
                    at += 1
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in found], pa.int64()) for i in (0, 1)], ["doc_id", "shard"])

    routed = ids.mapInArrow(route, "doc_id long, shard long").join(manifest.select("shard", "path"), "shard")

    def find(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        path, reader = None, None
        for batch in batches:
            found = []
            for doc_id, p in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if p != path:
                    filesystem, place = _opened(p)
                    path, reader = p, ShardReader(filesystem.open_input_file(place))
                found += [(doc_id, ids) for ids in reader.get(key_of(doc_id))]
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in found], pa.int64()), pa.array([x[1] for x in found], pa.binary())], ["doc_id", "ids"])

    return routed.select("doc_id", "path").repartition("path").sortWithinPartitions("path", "doc_id").mapInArrow(find, "doc_id long, ids binary")


def shard_folder(spark: SparkSession) -> str:
    return common.fresh_path(spark, "shards")
