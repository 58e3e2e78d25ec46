"""Sorted-string-table shards of token ids, keyed by document.

One shard holds a range of documents in ascending order of their id:

    blocks | index | Bloom filter | footer

A block holds entries whose keys share prefixes: varint(shared) varint(own) varint(bytes of value) own-key value, with a
full key at each restart; then the restart offsets and their number (uint32 each). Blocks are zstd frames, each followed
by its crc32. The sparse index has, for each block: last key (varint length, bytes), offset and length (varints),
documents and ids before it (varints). The footer (fixed width) says where index and filter are, how many documents and
ids there are, how wide an id is, the crc32 of index and filter, and ends in the magic bytes.
A key is the id as a big-endian unsigned 64-bit number with its sign bit turned, so that bytes sort as ids do; a null id's
key is empty and sorts first.

Writing: documents are dealt by id ranges, each task writes one shard to a name of its own attempt in the shared folder
and then renames it, so that a task that runs again replaces its file by an equal one. Only the manifest (one row for
each shard) is gathered. Reading opens each shard in a task of its own and streams its blocks.

Defined results: null and empty texts hold just the end id; repeated ids lie side by side, in the order of their texts,
rows alike in both each with an entry of its own; null ids come first; a very long text is one entry, in a block of its
own if need be; an empty table gives no shards; other columns are ignored.
"""

from __future__ import annotations

import bisect
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parley.llm.common import fresh_path
from parley.llm.word_encoding import encoder

MAGIC = b"PARLSST1"
FOOTER = struct.Struct("<QQQQQQQBI8s")
BLOCK_BYTES = 128 << 10
RESTART = 16
BLOOM_BITS, BLOOM_HASHES = 10, 7
END_ID = 2
MANIFEST = "shard int, file string, n_docs long, n_tokens long"


def key_of(doc_id: int | None) -> bytes:
    return b"" if doc_id is None else struct.pack(">Q", (doc_id & 0xFFFFFFFFFFFFFFFF) ^ (1 << 63))


def id_of(key: bytes) -> int | None:
    if not key:
        return None
    x = struct.unpack(">Q", key)[0] ^ (1 << 63)
    return x - (1 << 64) if x >> 63 else x


def put_varint(out: bytearray, x: int) -> None:
    while x > 127:
        out.append(x & 127 | 128)
        x >>= 7
    out.append(x)


def get_varint(data: bytes, at: int) -> tuple[int, int]:
    x = shift = 0
    while True:
        b = data[at]
        at += 1
        x |= (b & 127) << shift
        if b < 128:
            return x, at
        shift += 7


def probes(key: bytes, bits: int) -> list[int]:
    h = xxhash.xxh3_128_intdigest(key)
    a, b = h & 0xFFFFFFFFFFFFFFFF, h >> 64 | 1
    return [(a + k * b & 0xFFFFFFFFFFFFFFFF) % bits for k in range(BLOOM_HASHES)]


class Writer:
    """Streams one shard to a file-like sink; keys must not descend."""

    def __init__(self, sink, width: int):
        self.sink, self.width, self.at = sink, width, 0
        self.docs = self.ids = self.block_docs = self.block_ids = 0
        self.block, self.restarts, self.held, self.last = bytearray(), [], 0, b""
        self.index, self.keys = bytearray(), []
        self.pack = zstandard.ZstdCompressor(level=1)

    def add(self, doc_id: int, ids: bytes) -> None:
        key = key_of(doc_id)
        if self.docs and key < self.last:
            raise ValueError("keys must not descend")
        shared = 0
        if self.held % RESTART == 0:
            self.restarts.append(len(self.block))
        else:
            while shared < min(len(key), len(self.last)) and key[shared] == self.last[shared]:
                shared += 1
        for x in (shared, len(key) - shared, len(ids)):
            put_varint(self.block, x)
        self.block += key[shared:]
        self.block += ids
        self.held += 1
        self.docs += 1
        self.ids += len(ids) // self.width
        if not self.keys or key != self.last:
            self.keys.append(key)
        self.last = key
        if len(self.block) >= BLOCK_BYTES:
            self._close_block()

    def _put(self, data: bytes) -> None:
        self.sink.write(data)
        self.at += len(data)

    def _close_block(self) -> None:
        if not self.held:
            return
        frame = self.pack.compress(bytes(self.block) + np.array([*self.restarts, len(self.restarts)], "<u4").tobytes())
        put_varint(self.index, len(self.last))
        self.index += self.last
        for x in (self.at, len(frame), self.block_docs, self.block_ids):
            put_varint(self.index, x)
        self._put(frame + struct.pack("<I", zlib.crc32(frame)))
        self.block, self.restarts, self.held = bytearray(), [], 0
        self.block_docs, self.block_ids = self.docs, self.ids

    def close(self) -> None:
        self._close_block()
        bits = max(64, -(-len(self.keys) * BLOOM_BITS // 8) * 8)
        bloom = bytearray(bits // 8)
        for key in self.keys:
            for p in probes(key, bits):
                bloom[p >> 3] |= 1 << (p & 7)
        index_at, crc = self.at, zlib.crc32(bloom, zlib.crc32(self.index))
        self._put(bytes(self.index))
        bloom_at = self.at
        self._put(bytes(bloom))
        self._put(FOOTER.pack(index_at, len(self.index), bloom_at, len(bloom), self.docs, self.ids, bits, self.width, crc, MAGIC))


class Reader:
    """Random access and scans of one shard through any seekable source."""

    def __init__(self, source, size: int):
        self.source = source
        index_at, index_len, bloom_at, bloom_len, self.docs, self.ids, self.bits, self.width, crc, magic = FOOTER.unpack(self._get(size - FOOTER.size, FOOTER.size))
        index, self.bloom = self._get(index_at, index_len), self._get(bloom_at, bloom_len)
        if magic != MAGIC or zlib.crc32(self.bloom, zlib.crc32(index)) != crc:
            raise ValueError("not a shard, or a damaged one")
        self.last, self.places, at = [], [], 0
        while at < len(index):
            n, at = get_varint(index, at)
            self.last.append(index[at : at + n])
            at += n
            place = []
            for _ in range(4):
                x, at = get_varint(index, at)
                place.append(x)
            self.places.append(place)
        self.unpack = zstandard.ZstdDecompressor()
        self.dtype = np.dtype(f"<u{self.width}")

    def _get(self, at: int, n: int) -> bytes:
        self.source.seek(at)
        return self.source.read(n)

    def _block(self, k: int) -> tuple[bytes, np.ndarray]:
        at, n, _, _ = self.places[k]
        raw = self._get(at, n + 4)
        if zlib.crc32(raw[:n]) != struct.unpack("<I", raw[n:])[0]:
            raise ValueError(f"block {k} is damaged")
        data = self.unpack.decompress(raw[:n])
        count = int(np.frombuffer(data[-4:], "<u4")[0])
        return data[: -4 * (count + 1)], np.frombuffer(data[-4 * (count + 1) : -4], "<u4")

    def _entries(self, data: bytes, at: int, key: bytes = b"") -> Iterator[tuple[bytes, bytes]]:
        while at < len(data):
            shared, at = get_varint(data, at)
            own, at = get_varint(data, at)
            n, at = get_varint(data, at)
            key = key[:shared] + data[at : at + own]
            at += own
            yield key, data[at : at + n]
            at += n

    def scan(self) -> Iterator[tuple[int | None, np.ndarray]]:
        """(doc_id, ids) in order."""
        for k in range(len(self.places)):
            for key, value in self._entries(self._block(k)[0], 0):
                yield id_of(key), np.frombuffer(value, self.dtype)

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        """The ids of every row with this id: filter, binary search of blocks, then of a block's restarts."""
        key = key_of(doc_id)
        if not all(self.bloom[p >> 3] >> (p & 7) & 1 for p in probes(key, self.bits)):
            return []
        found: list[np.ndarray] = []
        for k in range(bisect.bisect_left(self.last, key), len(self.last)):
            data, restarts = self._block(k)
            first = max(0, bisect.bisect_left(restarts, key, key=lambda r: next(self._entries(data, int(r)))[0]) - 1)
            for other, value in self._entries(data, int(restarts[first])):
                if other > key:
                    return found
                if other == key:
                    found.append(np.frombuffer(value, self.dtype))
        return found


def _open(path: str):
    fs, inner = pafs.FileSystem.from_uri(path)
    return fs, inner


def read_shard(path: str) -> Reader:
    fs, inner = _open(path)
    return Reader(fs.open_input_file(inner), fs.get_file_info(inner).size)


def _write_shard(folder: str, tokenizer: str, end_id: int):
    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, shard = encoder(tokenizer), TaskContext.get().partitionId()
        fs, inner = _open(folder)
        end, writer, sink, mine = np.array([end_id], enc.dtype).tobytes(), None, None, f"{inner}/.attempt-{uuid.uuid4().hex}"
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for at in range(0, len(ids), 200):
                for doc, tokens in zip(ids[at : at + 200], enc.encode(texts[at : at + 200]), strict=True):
                    if writer is None:
                        sink = fs.open_output_stream(mine)
                        writer = Writer(sink, enc.dtype.itemsize)
                    writer.add(doc, tokens + end)
        if writer is not None:
            writer.close()
            sink.close()
            fs.move(mine, f"{inner}/shard-{shard:06d}.sst")
            yield pa.RecordBatch.from_pylist([{"shard": shard, "file": f"{folder}/shard-{shard:06d}.sst", "n_docs": writer.docs, "n_tokens": writer.ids}], pa.schema([("shard", pa.int32()), ("file", pa.string()), ("n_docs", pa.int64()), ("n_tokens", pa.int64())]))

    return write


def write_shards(df: DataFrame, tokenizer: str, folder: str | None = None, id_col: str = "doc_id", text_col: str = "text", end_id: int = END_ID, shards: int | None = None) -> tuple[str, list]:
    """Write df's documents as shards; returns the folder and the manifest's rows in order (one for each shard)."""
    spark = df.sparkSession
    folder = folder or fresh_path(spark, "shards")
    fs, inner = _open(folder)
    fs.create_dir(inner, recursive=True)
    n = shards or int(spark.conf.get("spark.sql.shuffle.partitions"))
    docs = df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    dealt = docs.repartitionByRange(n, "doc_id").sortWithinPartitions("doc_id", "text")
    manifest = dealt.mapInArrow(_write_shard(folder, tokenizer, end_id), MANIFEST).collect()
    return folder, sorted(manifest, key=lambda r: r.shard)


def _scan_shards(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for row in batch.to_pylist():
            start, rows = row["start"], []
            for doc, ids in read_shard(row["file"]).scan():
                rows.append((doc, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                start += len(ids)
                if len(rows) == 4096:
                    yield _digest(rows)
                    rows = []
            yield _digest(rows)


def _digest(rows: list) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) or [[]] * 4
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["doc_id", "start", "n_tokens", "ids_crc32"])


def shard_list(spark: SparkSession, manifest: list) -> DataFrame:
    """One row and one partition for each shard, with the number of ids before it."""
    rows, before = [], 0
    for r in manifest:
        rows.append((r.shard, r.file, before))
        before += r.n_tokens
    listed = spark.createDataFrame(rows, "shard int, file string, start long")
    return listed.repartition(max(1, len(rows)), "shard") if rows else listed


def digests(spark: SparkSession, manifest: list) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) read back from the shards."""
    return shard_list(spark, manifest).mapInArrow(_scan_shards, "doc_id long, start long, n_tokens long, ids_crc32 long")
