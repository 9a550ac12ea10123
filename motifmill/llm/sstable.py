"""Token ids in sorted-string-table shards.

A shard holds documents in ascending order of their identifiers: data blocks whose
keys are prefix-compressed against the key before, a sparse index with one entry
per block, a Bloom filter over the identifiers, and a footer of fixed length. All
numbers are little-endian.

| part | content |
|-|-|
| block | compressed with zstd: entries of (shared, rest, n: varints; rest of the key; n ids) |
| index | per block: key length u16, first key, offset u64, length u32, entries u32, ids before it u64 |
| filter | bits of the Bloom filter |
| footer | index offset u64, index length u32, filter offset u64, filter length u32, hashes u8, id width u8, documents u64, ids u64, magic 8 bytes |

A key is the identifier as 8 big-endian bytes with the sign bit flipped, so byte
order is number order. A null identifier has the empty key and comes first.
Repeated identifiers are repeated entries, in the order of a hash of the text. A null
text is the empty text: its only id is the end id. A very long text is one entry of one
block. An empty table gives no rows; further columns are dropped.

Texts are range-partitioned by identifier, and among texts with one identifier by a hash,
into ranges of about ``SHARD_BYTES`` of text, so no hot identifier is one range. They are
encoded where they are written. Each attempt of a task writes a shard of its own name, and
the manifest, which Spark commits, names the shards that count: a task that is run again
cannot spoil one. Readers go by the manifest and fetch one block at a time, whatever a
shard's size; point lookups go through ``TokenTable``.
"""

from __future__ import annotations

import os
import struct
import uuid
import zlib
from bisect import bisect_right
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from motifmill.functions.scratch import fresh_path, materialise
from motifmill.llm.bpe import codec
from motifmill.llm.words import byte_slices

MAGIC = b"TOKSST01"
FOOTER = struct.Struct("<QIQIBBQQ8s")
BLOCK_BYTES = 1 << 18
#: Bytes of text that are encoded at once, and pieces in a generation of the memo: the writers hold little else.
SLICE_BYTES, MEMO = 4 << 20, 400_000
#: Bytes of text for a shard.
SHARD_BYTES = 128 << 20
BITS_PER_KEY, HASHES = 10, 7
MANIFEST = "shard int, name string, docs bigint, ids bigint, first_id bigint, last_id bigint"


def encode_key(doc_id: int | None) -> bytes:
    return b"" if doc_id is None else struct.pack(">Q", (doc_id + (1 << 63)) & ((1 << 64) - 1))


def decode_key(key: bytes) -> int | None:
    return None if not key else struct.unpack(">Q", key)[0] - (1 << 63)


def put_varint(out: bytearray, x: int) -> None:
    while x > 0x7F:
        out.append(x & 0x7F | 0x80)
        x >>= 7
    out.append(x)


def get_varint(data: bytes, at: int) -> tuple[int, int]:
    x = shift = 0
    while True:
        b = data[at]
        at += 1
        x |= (b & 0x7F) << shift
        if b < 0x80:
            return x, at
        shift += 7


def bloom_places(key: bytes, bits: int, hashes: int) -> list[int]:
    a, b = struct.unpack("<QQ", xxhash.xxh3_128_digest(key))
    return [(a + i * (b | 1)) % bits for i in range(hashes)]


class ShardWriter:
    """Writes entries, which must come in key order, to an open binary stream."""

    def __init__(self, out, width: int):
        self.out, self.width, self.at = out, width, 0
        self.block, self.first, self.last, self.entries = bytearray(), b"", b"", 0
        self.index, self.keys = [], []
        self.docs = self.ids = self.before = 0
        self.pack = zstandard.ZstdCompressor(level=1)

    def add(self, key: bytes, ids: np.ndarray) -> None:
        if self.docs and key < self.last:
            raise ValueError("keys out of order")
        if not self.entries:
            self.first, self.last = key, b""
        shared = 0 if self.entries == 0 else len(os.path.commonprefix([self.last, key]))
        put_varint(self.block, shared)
        put_varint(self.block, len(key) - shared)
        put_varint(self.block, len(ids))
        self.block += key[shared:]
        self.block += ids.astype(f"<u{self.width}").tobytes()
        self.last = key
        self.entries += 1
        self.docs += 1
        self.ids += len(ids)
        self.keys.append(key)
        if len(self.block) >= BLOCK_BYTES:
            self.flush()

    def flush(self) -> None:
        if self.entries:
            data = self.pack.compress(bytes(self.block))
            self.out.write(data)
            self.index.append(struct.pack("<H", len(self.first)) + self.first + struct.pack("<QIIQ", self.at, len(data), self.entries, self.before))
            self.at += len(data)
            self.before = self.ids
            self.block, self.entries = bytearray(), 0

    def close(self) -> None:
        self.flush()
        index = b"".join(self.index)
        bits = max(64, (len(self.keys) * BITS_PER_KEY + 7) // 8 * 8)
        bloom = bytearray(bits // 8)
        for key in self.keys:
            for p in bloom_places(key, bits, HASHES):
                bloom[p >> 3] |= 1 << (p & 7)
        self.out.write(index)
        self.out.write(bytes(bloom))
        self.out.write(FOOTER.pack(self.at, len(index), self.at + len(index), len(bloom), HASHES, self.width, self.docs, self.ids, MAGIC))


class ShardReader:
    """Reads a shard through ``read(offset, length)``; only the blocks asked for are fetched."""

    def __init__(self, read: Callable[[int, int], bytes], size: int):
        self.read = read
        index_at, index_len, self.bloom_at, self.bloom_len, self.hashes, self.width, self.docs, self.ids, magic = FOOTER.unpack(read(size - FOOTER.size, FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a token shard")
        data, at = read(index_at, index_len), 0
        self.firsts, self.blocks = [], []
        while at < len(data):
            n = struct.unpack_from("<H", data, at)[0]
            self.firsts.append(data[at + 2 : at + 2 + n])
            self.blocks.append(struct.unpack_from("<QIIQ", data, at + 2 + n))
            at += 2 + n + struct.calcsize("<QIIQ")
        self._bloom: bytes | None = None

    @classmethod
    def of_bytes(cls, data: bytes | pa.Buffer) -> ShardReader:
        view = memoryview(data)
        return cls(lambda at, n: bytes(view[at : at + n]), len(view))

    def block(self, k: int) -> Iterator[tuple[bytes, np.ndarray]]:
        at, length, entries, _ = self.blocks[k]
        data, at, key = zstandard.ZstdDecompressor().decompress(self.read(at, length)), 0, b""
        for _ in range(entries):
            shared, at = get_varint(data, at)
            rest, at = get_varint(data, at)
            n, at = get_varint(data, at)
            key = key[:shared] + data[at : at + rest]
            at += rest
            yield key, np.frombuffer(data, dtype=f"<u{self.width}", count=n, offset=at)
            at += n * self.width

    def entries(self) -> Iterator[tuple[bytes, np.ndarray]]:
        for k in range(len(self.blocks)):
            yield from self.block(k)

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        """Ids of all entries of one identifier: Bloom filter, binary search in the index, one or a few blocks."""
        key = encode_key(doc_id)
        if self._bloom is None:
            self._bloom = self.read(self.bloom_at, self.bloom_len)
        if any(not self._bloom[p >> 3] >> (p & 7) & 1 for p in bloom_places(key, 8 * self.bloom_len, self.hashes)):
            return []
        out, k = [], max(0, bisect_right(self.firsts, key) - 1)
        while k > 0 and self.firsts[k] == key:
            k -= 1
        while k < len(self.blocks) and self.firsts[k] <= key:
            out += [ids for found, ids in self.block(k) if found == key]
            k += 1
        return out


class TokenTable:
    """Point lookups over a folder of shards."""

    def __init__(self, manifest: list[tuple[str, int | None, int | None]], folder: str):
        """manifest: (name, first_id, last_id) of each shard in order."""
        self.files, self.root = pyarrow.fs.FileSystem.from_uri(folder)
        self.names = [m[0] for m in manifest]
        self.lasts = [encode_key(m[2]) for m in manifest]
        self.firsts = [encode_key(m[1]) for m in manifest]

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        key, out = encode_key(doc_id), []
        for k, name in enumerate(self.names):
            if self.firsts[k] <= key <= self.lasts[k]:
                with self.files.open_input_file(f"{self.root}/{name}") as f:
                    out += ShardReader(lambda at, n, f=f: f.read_at(n, at), f.size()).get(doc_id)
        return out


def write_shards(docs: DataFrame, folder: str, tokenizer: str, end_id: int | None = 0, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Encode all rows, append ``end_id`` to each, write the shards to ``folder``; returns the manifest, written as well."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(tokenizer, MEMO)
        width = 2 if max(len(own.tokens), (end_id or 0) + 1) <= 1 << 16 else 4
        tail = np.array([] if end_id is None else [end_id], dtype=np.int32)
        part = TaskContext.get().partitionId()
        writer = stream = first = None
        files, root = pyarrow.fs.FileSystem.from_uri(folder)
        name = f"shard-{part:06d}-{uuid.uuid4().hex}.sst"
        for batch in byte_slices(batches, 1, SLICE_BYTES):
            ids = own.encode_column(batch.column(1))
            flat, ends = ids.values.to_numpy(), ids.offsets.to_pylist()
            for doc_id, a, b in zip(batch.column(0).to_pylist(), ends, ends[1:], strict=False):
                if writer is None:
                    files.create_dir(root, recursive=True)
                    stream, first = files.open_output_stream(f"{root}/{name}"), doc_id
                    writer = ShardWriter(stream, width)
                writer.add(encode_key(doc_id), np.append(flat[a:b], tail))
            del ids, flat, ends
        if writer is None:
            return
        writer.close()
        stream.close()
        row = [[part], [name], [writer.docs], [writer.ids], [first], [decode_key(writer.last)]]
        kinds = [pa.int32(), pa.string(), *[pa.int64()] * 4]
        yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(row, kinds, strict=True)], ["shard", "name", "docs", "ids", "first_id", "last_id"])

    rows = docs.select(F.col(key).cast("bigint").alias("key"), F.col(text).alias("text"))
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    ranges = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-size // SHARD_BYTES))
    ordered = rows.repartitionByRange(ranges, "key", F.xxhash64("text")).sortWithinPartitions("key", F.xxhash64("text"))
    return materialise(ordered.mapInArrow(run, MANIFEST), "shards")


IDS = "shard int, key bigint, local_start bigint, ids array<int>"
DIGESTS = "shard int, key bigint, local_start bigint, n_tokens bigint, ids_crc32 bigint"


def read_shards(manifest: DataFrame, folder: str, digests: bool = False) -> DataFrame:
    """(shard, key, local_start, ids) of every entry, read from the files of a manifest; with ``digests`` the ids' number and CRC-32 instead.

    The checksum is that of the ids as little-endian 32-bit numbers.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, root = pyarrow.fs.FileSystem.from_uri(folder)
        for batch in batches:
            for shard, name in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                with files.open_input_file(f"{root}/{name}") as f:
                    yield from blocks(shard, ShardReader(lambda at, n, f=f: f.read_at(n, at), f.size()))

    def blocks(shard: int, reader: ShardReader) -> Iterator[pa.RecordBatch]:
        start = 0
        for k in range(len(reader.blocks)):
            keys, ids = [], []
            for key, x in reader.block(k):
                keys.append(decode_key(key))
                ids.append(x.astype("<u4"))
            size = np.array([len(x) for x in ids], dtype=np.int64)
            ends = np.append(0, np.cumsum(size))
            columns = [pa.array([shard] * len(keys), pa.int32()), pa.array(keys, pa.int64()), pa.array(ends[:-1] + start)]
            start += int(ends[-1])
            if digests:
                columns += [pa.array(size), pa.array([zlib.crc32(x) for x in ids], pa.int64())]
            else:
                columns.append(pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(np.concatenate(ids).view(np.int32))))
            yield pa.RecordBatch.from_arrays(columns, [c.split()[0] for c in schema.split(", ")])

    schema = DIGESTS if digests else IDS
    shards = manifest.count()  # a row for each shard: dealt out one by one
    return manifest.select("shard", "name").coalesce(1).repartition(max(1, shards)).mapInArrow(run, schema)


def op10_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Place and checksum of every document's ids, from files written and read back."""
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = fresh_path(spark, "tokens")
    manifest = write_shards(docs, folder, public_tokenizers.path("byte_bpe_50k.json"))
    if manifest.isEmpty():
        return spark.createDataFrame([], "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint, shard int")
    before = F.sum("ids").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1))
    bases = manifest.select(F.col("shard").alias("__shard"), F.coalesce(before, F.lit(0)).alias("base"))
    rows = read_shards(manifest, folder, digests=True)
    return rows.join(bases, F.col("shard") == F.col("__shard")).select(
        F.col("key").alias("doc_id"), (F.col("base") + F.col("local_start")).alias("start"), "n_tokens", "ids_crc32", "shard"
    )
