"""Sorted-string-table shards of token ids.

Documents are dealt by range of their identifier, tokenised where they land and
written in ascending key order.  A shard is one file::

    block*  index  bloom  meta  footer

A block holds entries ``shared, unshared, value length, key suffix, value`` with
prefix-compressed keys, restart points every 16 entries for binary search, and
is compressed as a whole.  The index has the first key, offset, length and CRC
of every block; the Bloom filter answers most absent keys without a block read;
the footer has the offsets of the three parts and a magic number.

Null identifiers sort first, repeated identifiers keep one entry each (ordered
by a hash of the text), null and empty texts become the end token alone, and an
empty table writes no shard.  Other columns of the input are ignored.
"""

from __future__ import annotations

import bisect
import json
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tallquant.llm.common import Workspace, as_bytes, default_tokenizer, filesystem, publish, text_slices, word_encoder

MAGIC = b"TQSST\x00\x01\n"
FOOTER = struct.Struct("<6Q8s")
RESTART = 16
MANIFEST = "part int, piece int, file string, n_docs long, n_tokens long, n_bytes long, first_key binary, last_key binary"


def key_bytes(key: int | str | None) -> bytes:
    """Order-preserving bytes of a key; null first, then integers, then strings."""
    if key is None:
        return b"\x00"
    if isinstance(key, str):
        return b"\x02" + key.encode()
    return b"\x01" + (key + (1 << 63)).to_bytes(8, "big")


def key_value(raw: bytes) -> int | str | None:
    if raw[0] == 0:
        return None
    return raw[1:].decode() if raw[0] == 2 else int.from_bytes(raw[1:], "big") - (1 << 63)


def _varint(n: int) -> bytes:
    out = bytearray()
    while n >= 128:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_varint(raw: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = raw[at]
        n |= (b & 127) << shift
        at += 1
        if b < 128:
            return n, at
        shift += 7


def _bloom_slots(key: bytes, n_bits: int, n_hashes: int = 7) -> list[int]:
    import xxhash

    h = xxhash.xxh3_128_intdigest(key)
    a, b = h & 0xFFFFFFFFFFFFFFFF, h >> 64 | 1
    return [(a + i * b) % n_bits for i in range(n_hashes)]


class ShardWriter:
    """Writes one shard; entries must come in ascending key order."""

    def __init__(self, uri: str, width: int, block_bytes: int = 65_536):
        self.fs, self.path = filesystem(uri)
        self.temp = f"{self.path}.{uuid.uuid4().hex}.tmp"
        self.out = self.fs.open_output_stream(self.temp)
        self.width, self.block_bytes = width, block_bytes
        self.index: list[tuple[str, int, int, int]] = []
        self.keys: list[bytes] = []
        self.at = self.n_docs = self.n_tokens = 0
        self.squeeze = zstandard.ZstdCompressor(level=1)
        self._begin()

    def _begin(self) -> None:
        self.block, self.restarts, self.entries, self.last, self.first = bytearray(), [], 0, b"", b""

    def add(self, key: bytes, ids: np.ndarray) -> None:
        if self.entries % RESTART == 0:
            self.restarts.append(len(self.block))
            shared = 0
        else:
            shared = next((i for i, (x, y) in enumerate(zip(key, self.last, strict=False)) if x != y), min(len(key), len(self.last)))
        value = ids.astype("<u2" if self.width == 2 else "<u4").tobytes()
        self.block += _varint(shared) + _varint(len(key) - shared) + _varint(len(value)) + key[shared:] + value
        self.first = self.first or key
        self.last, self.entries = key, self.entries + 1
        self.keys.append(key)
        self.n_docs += 1
        self.n_tokens += len(ids)
        if len(self.block) >= self.block_bytes:
            self._flush()

    def _flush(self) -> None:
        if self.entries:
            raw = bytes(self.block) + struct.pack(f"<{len(self.restarts)}II", *self.restarts, len(self.restarts))
            data = self.squeeze.compress(raw)
            self.index.append((self.first.hex(), self.at, len(data), zlib.crc32(data)))
            self.out.write(data)
            self.at += len(data)
            self._begin()

    def close(self) -> int:
        """Finish the file and move it to its name; returns its length."""
        self._flush()
        n_bits = max(64, 10 * len(self.keys))
        bits = bytearray((n_bits + 7) // 8)
        for key in self.keys:
            for slot in _bloom_slots(key, n_bits):
                bits[slot >> 3] |= 1 << (slot & 7)
        parts = [self.squeeze.compress(json.dumps(self.index).encode()), bytes(bits), json.dumps({"width": self.width, "n_docs": self.n_docs, "n_tokens": self.n_tokens, "bloom_bits": n_bits}).encode()]
        places: list[int] = []
        for part in parts:
            places += [self.at, len(part)]
            self.out.write(part)
            self.at += len(part)
        self.out.write(FOOTER.pack(*places, MAGIC))
        self.out.close()
        publish(self.fs, self.temp, self.path)
        return self.at + FOOTER.size


class Shard:
    """Reads one shard: ``get`` by binary search, ``scan`` in key order."""

    def __init__(self, uri: str):
        self.fs, self.path = filesystem(uri)
        self.file = self.fs.open_input_file(self.path)
        size = self.file.size()
        *places, magic = FOOTER.unpack(self.file.read_at(FOOTER.size, size - FOOTER.size))
        if magic != MAGIC:
            raise ValueError(f"{uri} is not a shard")
        index, self.bloom, meta = (self.file.read_at(n, at) for at, n in zip(places[::2], places[1::2], strict=True))
        self.meta = json.loads(meta)
        self.index = json.loads(zstandard.ZstdDecompressor().decompress(index))
        self.first = [bytes.fromhex(x[0]) for x in self.index]
        self.kind = "<u2" if self.meta["width"] == 2 else "<u4"

    def _block(self, k: int) -> tuple[bytes, tuple[int, ...], int]:
        _, at, n, crc = self.index[k]
        data = self.file.read_at(n, at)
        if zlib.crc32(data) != crc:
            raise ValueError(f"{self.path}: block {k} is damaged")
        raw = zstandard.ZstdDecompressor().decompress(data)
        (n,) = struct.unpack_from("<I", raw, len(raw) - 4)
        end = len(raw) - 4 - 4 * n
        return raw, struct.unpack_from(f"<{n}I", raw, end), end

    def _entries(self, raw: bytes, at: int, end: int) -> Iterator[tuple[bytes, np.ndarray]]:
        last = b""
        while at < end:
            shared, at = _read_varint(raw, at)
            rest, at = _read_varint(raw, at)
            n, at = _read_varint(raw, at)
            last = last[:shared] + raw[at : at + rest]
            at += rest
            yield last, np.frombuffer(raw, self.kind, n // self.meta["width"], at)
            at += n

    def scan(self) -> Iterator[tuple[int | str | None, np.ndarray]]:
        for k in range(len(self.index)):
            raw, _, end = self._block(k)
            for key, ids in self._entries(raw, 0, end):
                yield key_value(key), ids

    def get(self, key: int | str | None) -> list[np.ndarray]:
        """Values of all entries with this key."""
        want = key_bytes(key)
        if not all(self.bloom[s >> 3] >> (s & 7) & 1 for s in _bloom_slots(want, self.meta["bloom_bits"])):
            return []
        found = []
        k = max(0, bisect.bisect_left(self.first, want) - 1)
        while k < len(self.index) and self.first[k] <= want:
            raw, restarts, end = self._block(k)
            heads = [next(self._entries(raw, r, end))[0] for r in restarts]
            at = restarts[max(0, bisect.bisect_left(heads, want) - 1)]
            for x, ids in self._entries(raw, at, end):
                if x > want:
                    return found
                if x == want:
                    found.append(ids)
            k += 1
        return found


def write_shards(docs: DataFrame, work: Workspace, *, tokenizer: str | None = None, end_id: int = 1, shard_bytes: int = 64 << 20) -> DataFrame:
    """Tokenise ``docs(doc_id, text)`` and write shards; returns their manifest, one row a shard.

    A partition starts another shard once it has ``shard_bytes`` of ids, so a
    shard stays small however uneven the ranges are.
    """
    tokenizer, root = tokenizer or default_tokenizer(), work.path("shards")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = word_encoder(tokenizer)
        width = 2 if encoder.lib.get_vocab_size() <= 65_536 and end_id < 65_536 else 4
        part, piece, writer, rows = TaskContext.get().partitionId(), 0, None, []

        def done() -> None:
            rows.append((part, piece, f"part-{part:06d}-{piece:04d}.sst", writer.n_docs, writer.n_tokens, writer.close(), writer.keys[0], writer.keys[-1]))

        for batch in batches:
            keys, texts = batch.column(0).to_pylist(), as_bytes(batch.column(1))
            for a, b in text_slices(texts):
                for key, ids in zip(keys[a:b], encoder.encode(texts[a:b]), strict=True):
                    writer = writer or ShardWriter(f"{root}/part-{part:06d}-{piece:04d}.sst", width)
                    writer.add(key_bytes(key), np.append(ids, np.uint32(end_id)))
                    if writer.n_tokens * width >= shard_bytes:
                        done()
                        writer, piece = None, piece + 1
        if writer:
            done()
        names = [f.split()[0] for f in MANIFEST.split(", ")]
        kinds = [pa.int32(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary()]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)

    fs, path = filesystem(root)
    fs.create_dir(path, recursive=True)
    tie = F.xxhash64("text")
    # equal rows come in any order, so where they came from splits a row that repeats without end
    keyed = docs.select("doc_id", "text", F.spark_partition_id().alias("origin"))
    ranged = keyed.repartitionByRange("doc_id", tie, "origin").sortWithinPartitions("doc_id", tie).select("doc_id", "text")
    return work.save(ranged.mapInArrow(write, MANIFEST), "manifest")


def read_shards(spark: SparkSession, work: Workspace, manifest: DataFrame, with_ids: bool = False) -> DataFrame:
    """Every document of the shards: ``doc_id, start, n_tokens, ids_crc32`` and, if asked for, ``ids``.

    ``start`` counts the ids of all documents before it: those of the parts before,
    one row a part, and of the shards before in its part.
    """
    root = work.path("shards")
    parts = manifest.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    before = parts.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("base"))
    here = F.sum("n_tokens").over(Window.partitionBy("part").orderBy("piece")) - F.col("n_tokens")
    files = manifest.select("part", F.concat(F.lit(f"{root}/"), "file").alias("file"), here.alias("here")).join(before, "part").select("file", (F.col("here") + F.col("base")).alias("start"))
    kinds = [("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())] + [("ids", pa.list_(pa.int32()))] * with_ids
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<int>" * with_ids

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def batch(out: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], k) for i, (_, k) in enumerate(kinds)], names=[n for n, _ in kinds])

        for files in batches:
            for uri, start in zip(files.column(0).to_pylist(), files.column(1).to_pylist(), strict=True):
                out: list[tuple] = []
                for key, ids in Shard(uri).scan():
                    out.append((key, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes()), *[ids.astype(np.int32)] * with_ids))
                    start += len(ids)
                    if len(out) >= (256 if with_ids else 10_000):
                        yield batch(out)
                        out = []
                if out:
                    yield batch(out)

    return files.repartition(max(1, min(manifest.count(), 100_000)), "file").mapInArrow(read, schema)


def lookup(work: Workspace, manifest: DataFrame, key: int | str | None) -> list[np.ndarray]:
    """Ids of the documents with a key: the key ranges of the manifest name the shards, whose Bloom filters and indexes find the block."""
    want = F.lit(key_bytes(key))
    near = manifest.where((F.col("first_key") <= want) & (F.col("last_key") >= want)).select("part", "piece", "file").collect()
    return [ids for r in sorted(near) for ids in Shard(f"{work.path('shards')}/{r.file}").get(key)]


def encode_to_shards(spark: SparkSession, docs: DataFrame, *, tokenizer: str | None = None) -> DataFrame:
    """Write shards and return what they hold, read back from the files."""
    work = Workspace(spark, "sstable")
    return read_shards(spark, work, write_shards(docs, work, tokenizer=tokenizer))
