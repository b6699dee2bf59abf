"""Sorted-string-table shards of token ids.

A shard holds documents in ascending key order::

    data block*   zstd( entry* restart_offset* n_restarts ) + CRC-32 of the compressed bytes
    filter        Bloom filter over all keys
    index         for each block: its last key, offset and size
    footer        fixed size: places of filter and index, counts, width of an id, magic

An entry is ``varint(shared) varint(unshared) varint(value size) key suffix value``: its key shares its first bytes
with the entry before; every 16th entry holds its whole key (a restart), so a lookup bisects the index, reads one
block, bisects the restarts and walks at most 16 entries.  A key is the document id in order-preserving bytes and
a running number that tells repeated ids apart.  A value is the document's start in the shard and its ids.

Rows with a null id are kept and sort first; repeated ids and repeated rows are all kept, ordered by their texts;
a null text is an empty one (only the end id is stored); an empty table gives no shard; other columns are not read.
"""

from __future__ import annotations

import bisect
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs
import xxhash
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from segcube.llm import encoding, shared
from segcube.llm import kernel as K

MAGIC = 0x5E6C_0BE5_55AB_1E01
_FOOTER = struct.Struct("<QQQQQQIIQ")  # filter, index: offset and size; entries, tokens; id width, hashes; magic
_RESTART = 16
_MANIFEST = "shard int, path string, first_id bigint, last_id bigint, docs bigint, tokens bigint, file_bytes bigint"


def put_varint(out: bytearray, n: int) -> None:
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)


def get_varint(data: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = data[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


def key_of(doc_id: int | None, number: int = 0) -> bytes:
    """Order-preserving bytes of a document id (null first) and a running number among equal ids."""
    if doc_id is None:
        return b"\x00" + bytes(8) + struct.pack(">I", number)
    return b"\x01" + struct.pack(">Q", doc_id + (1 << 63)) + struct.pack(">I", number)


def id_of(key: bytes) -> int | None:
    return struct.unpack(">Q", key[1:9])[0] - (1 << 63) if key[0] else None


def _filter_hashes(id_part: bytes) -> tuple[int, int]:
    h = xxhash.xxh3_128_intdigest(id_part)
    return h & (2**64 - 1), h >> 64 | 1


def file_system(path: str) -> tuple[pa.fs.FileSystem, str]:
    return pa.fs.FileSystem.from_uri(path if "://" in path else f"file://{path.removeprefix('file:')}")


class Writer:
    """Writes one shard; keys must come in ascending order."""

    def __init__(self, path: str, width: int = 2, block_bytes: int = 64 << 10, bits_per_key: int = 10):
        fs, self.local = file_system(path)
        fs.create_dir(self.local.rpartition("/")[0], recursive=True)
        self.out = fs.open_output_stream(self.local)
        self.width, self.block_bytes, self.bits = width, block_bytes, bits_per_key
        self.packer = zstandard.ZstdCompressor(level=1)
        self.block, self.restarts, self.n_in_block, self.last = bytearray(), [], 0, b""
        self.index: list[tuple[bytes, int, int]] = []
        self.at = self.entries = self.tokens = 0
        self.filter_keys: list[tuple[int, int]] = []

    def add(self, key: bytes, ids: np.ndarray) -> None:
        if self.last and key <= self.last:
            raise ValueError("keys must ascend")
        share = 0
        if self.n_in_block % _RESTART:
            top = min(len(key), len(self.last))
            while share < top and key[share] == self.last[share]:
                share += 1
        else:
            self.restarts.append(len(self.block))
        head = bytearray()
        put_varint(head, self.tokens)
        if len(ids) and int(ids.max()) >= 1 << (8 * self.width):
            raise ValueError(f"an id of {int(ids.max())} does not fit {self.width} bytes")
        body = ids.astype("<u2" if self.width == 2 else "<u4").tobytes()
        put_varint(self.block, share)
        put_varint(self.block, len(key) - share)
        put_varint(self.block, len(head) + len(body))
        self.block += key[share:] + head + body
        self.filter_keys.append(_filter_hashes(key[:9]))
        self.n_in_block += 1
        self.entries += 1
        self.tokens += len(ids)
        self.last = key
        if len(self.block) >= self.block_bytes:
            self._end_block()

    def _put(self, data: bytes) -> tuple[int, int]:
        self.out.write(data)
        self.at += len(data)
        return self.at - len(data), len(data)

    def _end_block(self) -> None:
        if self.n_in_block:
            raw = bytes(self.block) + struct.pack(f"<{len(self.restarts)}I", *self.restarts) + struct.pack("<I", len(self.restarts))
            packed = self.packer.compress(raw)
            self.index.append((self.last, *self._put(packed + struct.pack("<I", zlib.crc32(packed)))))
            self.block, self.restarts, self.n_in_block = bytearray(), [], 0

    def close(self) -> int:
        """Write filter, index and footer; gives the file's size."""
        self._end_block()
        n_hashes = max(1, round(self.bits * 0.69))
        n_bits = max(64, self.entries * self.bits)
        bits = np.zeros((n_bits + 7) // 8 * 8, dtype=np.uint8)
        if self.filter_keys:
            h = np.array(self.filter_keys, dtype=np.uint64)
            for i in range(n_hashes):
                bits[(h[:, 0] + np.uint64(i) * h[:, 1]) % np.uint64(n_bits)] = 1
        bloom = self._put(struct.pack("<Q", n_bits) + np.packbits(bits).tobytes())
        entries = bytearray()
        for key, offset, size in self.index:
            put_varint(entries, len(key))
            entries += key
            put_varint(entries, offset)
            put_varint(entries, size)
        index = self._put(bytes(entries))
        self._put(_FOOTER.pack(*bloom, *index, self.entries, self.tokens, self.width, n_hashes, MAGIC))
        self.out.close()
        return self.at


class Reader:
    """Looks up single documents, or walks all, reading a block at a time."""

    def __init__(self, path: str):
        fs, local = file_system(path)
        self.file = fs.open_input_file(local)
        size = self.file.size()
        foot = self.file.read_at(_FOOTER.size, size - _FOOTER.size) if size >= _FOOTER.size else b""
        if len(foot) != _FOOTER.size or _FOOTER.unpack(foot)[-1] != MAGIC:
            raise ValueError(f"not a shard: {path}")
        bloom_at, bloom_size, index_at, index_size, self.entries, self.tokens, self.width, self.n_hashes, _ = _FOOTER.unpack(foot)
        bloom = self.file.read_at(bloom_size, bloom_at)
        self.n_bits, self.bloom = struct.unpack("<Q", bloom[:8])[0], bloom[8:]
        raw, at = self.file.read_at(index_size, index_at), 0
        self.last_keys, self.places = [], []
        while at < len(raw):
            n, at = get_varint(raw, at)
            self.last_keys.append(raw[at : at + n])
            offset, at = get_varint(raw, at + n)
            size, at = get_varint(raw, at)
            self.places.append((offset, size))
        self.unpacker = zstandard.ZstdDecompressor()

    def may_hold(self, doc_id: int | None) -> bool:
        a, b = _filter_hashes(key_of(doc_id)[:9])
        bits = (((a + i * b) % 2**64) % self.n_bits for i in range(self.n_hashes))
        return all(self.bloom[x >> 3] >> (7 - (x & 7)) & 1 for x in bits)

    def _block(self, i: int) -> tuple[bytes, np.ndarray]:
        offset, size = self.places[i]
        packed = self.file.read_at(size, offset)
        if zlib.crc32(packed[:-4]) != struct.unpack("<I", packed[-4:])[0]:
            raise ValueError("a block's checksum differs")
        raw = self.unpacker.decompress(packed[:-4])
        n = struct.unpack("<I", raw[-4:])[0]
        return raw[: len(raw) - 4 - 4 * n], np.frombuffer(raw, dtype="<u4", count=n, offset=len(raw) - 4 - 4 * n)

    def _walk(self, raw: bytes, at: int = 0) -> Iterator[tuple[bytes, int, np.ndarray]]:
        key = b""
        while at < len(raw):
            share, at = get_varint(raw, at)
            rest, at = get_varint(raw, at)
            size, at = get_varint(raw, at)
            key = key[:share] + raw[at : at + rest]
            at += rest
            start, body = get_varint(raw, at)
            count = (at + size - body) // self.width
            yield key, start, np.frombuffer(raw, dtype="<u2" if self.width == 2 else "<u4", count=count, offset=body).astype(np.uint32)
            at += size

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        """The ids of every document with this id, in stored order (an empty list: none)."""
        found: list[np.ndarray] = []
        if not self.may_hold(doc_id):
            return found
        first = key_of(doc_id)
        for i in range(bisect.bisect_left(self.last_keys, first), len(self.places)):
            raw, restarts = self._block(i)
            low, high = 0, len(restarts) - 1
            while low < high:  # the last restart whose key is not beyond the one sought
                mid = (low + high + 1) // 2
                if next(self._walk(raw, int(restarts[mid])))[0] <= first:
                    low = mid
                else:
                    high = mid - 1
            for key, _, ids in self._walk(raw, int(restarts[low])):
                if key[:9] > first[:9]:
                    return found
                if key[:9] == first[:9]:
                    found.append(ids)
        return found

    def scan(self) -> Iterator[tuple[bytes, int, np.ndarray]]:
        """Every entry: key, start within the shard, ids."""
        for i in range(len(self.places)):
            yield from self._walk(self._block(i)[0])


def write_shards(docs: DataFrame, folder: str, tokenizer: str, layout: str = "words", end_id: int = 1, id_width: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode every text and write shards in ascending order of ids; gives the manifest, one row per shard.

    Rows are range-partitioned by id (then text and row number, so that one repeated id cannot fill a single task), each
    task sorts its range, encodes it and writes one file.  A file's name is new for each attempt and only the
    attempts that Spark accepted are in the manifest, so a lost executor or a speculative copy leaves no doubt.
    """

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        shard = TaskContext.get().partitionId()
        path = f"{folder}/shard-{shard:06d}-{uuid.uuid4().hex}.sst"
        writer, last, number, first_id = None, None, 0, None
        encoder = encoding.encoder(tokenizer, layout)
        for batch in batches:
            for part in K.steps(batch, "text"):
                ids, offsets = encoding.append_end(*encoder.encode(part.column("text")), end_id)
                for k, doc_id in enumerate(part.column("doc_id").to_pylist()):
                    if writer is None:
                        writer, first_id = Writer(path, id_width), doc_id
                    else:
                        number = number + 1 if doc_id == last else 0
                    writer.add(key_of(doc_id, number), ids[offsets[k] : offsets[k + 1]])
                    last = doc_id
        if writer is not None:
            size = writer.close()
            row = [[shard], [path], [first_id], [last], [writer.entries], [writer.tokens], [size]]
            types = [pa.int32(), pa.string(), *[pa.int64()] * 5]
            names = ["shard", "path", "first_id", "last_id", "docs", "tokens", "file_bytes"]
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(row, types, strict=True)], names=names)

    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    keys = [F.col("doc_id").asc_nulls_first(), F.xxhash64("text"), F.col("row")]
    rows = rows.withColumn("row", F.monotonically_increasing_id()).repartitionByRange(*keys).sortWithinPartitions(*keys)
    return shared.materialised(rows.select("doc_id", "text").mapInArrow(write, _MANIFEST), "manifest")


def read_shards(manifest: DataFrame) -> DataFrame:
    """Each stored document from its shard's file: id, start over all shards, number of ids and their CRC-32."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, base in zip(batch.column("path").to_pylist(), batch.column("base").to_pylist(), strict=True):
                rows: list[tuple] = []
                for key, start, ids in Reader(path).scan():
                    rows.append((id_of(key), base + start, len(ids), encoding.crc32(ids)))
                    if len(rows) == 4096:
                        yield _rows(rows)
                        rows = []
                if rows:
                    yield _rows(rows)

    def _rows(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)  # over shards, not documents
    placed = manifest.select("path", F.coalesce(F.sum("tokens").over(before), F.lit(0)).alias("base"))
    parts = max(1, min(manifest.count(), 4 * manifest.sparkSession.sparkContext.defaultParallelism))
    return placed.repartition(parts, "path").mapInArrow(read, "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")


#: Shards whose ranges a lookup sends to all workers at most; more are met by a join.
BROADCAST_SHARDS = 100_000


def lookup(manifest: DataFrame, wanted: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The ids of the documents asked for: shards are pruned by their range, then by filter, index and restarts."""

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        readers: dict[str, Reader] = {}
        for batch in batches:
            out_ids, out = [], []
            for path, doc_id in zip(batch.column("path").to_pylist(), batch.column("doc_id").to_pylist(), strict=True):
                if path not in readers:
                    readers.clear()
                    readers[path] = Reader(path)
                for ids in readers[path].get(doc_id):
                    out_ids.append(doc_id)
                    out.append(ids.astype(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(out_ids, pa.int64()), pa.array(out, pa.list_(pa.int64()))], names=["doc_id", "ids"])

    ids = wanted.select(F.col(id_col).cast("bigint").alias("doc_id")).distinct()
    in_range = (F.col("doc_id") >= F.coalesce("first_id", "doc_id")) & (F.col("doc_id") <= F.col("last_id"))
    shards = manifest.select("path", "first_id", "last_id")
    size = shards.agg(F.count(F.lit(1)).alias("n"), F.min("first_id").alias("low"), F.max("last_id").alias("high")).first()
    if size.n <= BROADCAST_SHARDS or size.low is None:
        pairs = ids.join(F.broadcast(shards), in_range)
    else:  # by equal cells of the id range; a shard is in the cells it meets, about two on average
        width = (size.high - size.low) // size.n + 1
        cell = lambda c: F.floor((c - size.low) / width)
        cells = F.sequence(cell(F.coalesce("first_id", F.lit(size.low))), cell(F.col("last_id")))
        pairs = ids.withColumn("cell", cell(F.col("doc_id"))).join(shards.withColumn("cell", F.explode(cells)), "cell").filter(in_range)
    return pairs.sortWithinPartitions("path").select("path", "doc_id").mapInArrow(find, "doc_id bigint, ids array<bigint>")
