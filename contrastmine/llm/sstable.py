"""Sorted-string-table shards of token ids.

A shard holds (key, ids) entries in ascending key order: blocks of prefix-compressed keys, a sparse index with each
block's last key, a Bloom filter over the keys and a fixed-size footer. A lookup reads the footer, asks the filter,
binary-searches the index and reads one block.

Keys are nine bytes: 0 for a null identifier, or 1 and the identifier biased so that byte order is number order.
Repeated identifiers keep all their rows, next to each other, ordered by a hash of the text."""

from __future__ import annotations

import bisect
import io
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import clean_text, file_system, fresh_path, stored, tidy, to_frame, whole
from .tokens import batches, encoder

MAGIC = b"CMSSTAB1"
FOOTER = "<QQQQQQ8s"  # index at, index bytes, filter at, filter bytes, entries, ids, magic
KEY_BYTES = 9


def pack_key(doc_id: int | None) -> bytes:
    return b"\0" * KEY_BYTES if doc_id is None else b"\1" + (doc_id + (1 << 63)).to_bytes(8, "big")


def unpack_key(key: bytes) -> int | None:
    return None if key[0] == 0 else int.from_bytes(key[1:], "big") - (1 << 63)


def varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def read_varint(data: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = data[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


def bloom_bits(key: bytes, n_bits: int, probes: int) -> list[int]:
    a, b = zlib.crc32(key), zlib.crc32(key, 0x9E3779B9) | 1
    return [(a + i * b) % n_bits for i in range(probes)]


class ShardWriter:
    """Streams entries to an open binary sink; memory holds one block, the index and the filter's keys."""

    def __init__(self, sink, block_bytes: int = 65536, bits_per_key: int = 10, probes: int = 7):
        self.sink, self.block_bytes, self.bits_per_key, self.probes = sink, block_bytes, bits_per_key, probes
        self.block, self.last, self.at = bytearray(), b"", 0
        self.index: list[tuple[bytes, int, int]] = []
        self.keys: list[bytes] = []
        self.entries = self.total = 0

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        key = pack_key(doc_id)
        if self.last and key < self.last:
            raise ValueError("keys must come in ascending order")
        shared = 0
        if self.block:
            while shared < KEY_BYTES and key[shared] == self.last[shared]:
                shared += 1
        value = ids.astype("<u2" if ids.dtype.itemsize == 2 else "<u4").tobytes()
        self.block += bytes((shared, KEY_BYTES - shared, ids.dtype.itemsize)) + varint(len(ids)) + key[shared:] + value
        if not self.keys or self.keys[-1] != key:
            self.keys.append(key)
        self.last = key
        self.entries += 1
        self.total += len(ids)
        if len(self.block) >= self.block_bytes:
            self._flush()

    def _flush(self) -> None:
        if self.block:
            body = bytes(self.block) + struct.pack("<I", zlib.crc32(self.block))
            self.sink.write(body)
            self.index.append((self.last, self.at, len(body)))
            self.at += len(body)
            self.block = bytearray()

    def finish(self) -> None:
        self._flush()
        n_bits = max(64, self.bits_per_key * len(self.keys))
        bits = np.zeros((n_bits + 7) // 8, np.uint8)
        for key in self.keys:
            for b in bloom_bits(key, n_bits, self.probes):
                bits[b >> 3] |= 1 << (b & 7)
        index = b"".join(k + struct.pack("<QQ", at, size) for k, at, size in self.index)
        bloom = struct.pack("<QB", n_bits, self.probes) + bits.tobytes()
        self.sink.write(index + bloom + struct.pack(FOOTER, self.at, len(index), self.at + len(index), len(bloom), self.entries, self.total, MAGIC))


class ShardReader:
    """Reads a shard from a random-access file."""

    def __init__(self, source, size: int):
        self.source = source
        (self.index_at, self.index_bytes, self.bloom_at, self.bloom_bytes, self.entries, self.total, magic) = struct.unpack(FOOTER, self._read(size - struct.calcsize(FOOTER), struct.calcsize(FOOTER)))
        if magic != MAGIC:
            raise ValueError("not a shard of this format")
        raw = self._read(self.index_at, self.index_bytes)
        step = KEY_BYTES + 16
        self.index = [(raw[i : i + KEY_BYTES], *struct.unpack("<QQ", raw[i + KEY_BYTES : i + step])) for i in range(0, len(raw), step)]
        self.bloom: bytes | None = None

    def _read(self, at: int, size: int) -> bytes:
        self.source.seek(at)
        return self.source.read(size)

    def _block(self, k: int) -> Iterator[tuple[bytes, np.ndarray]]:
        _, at, size = self.index[k]
        raw = self._read(at, size)
        body = raw[:-4]
        if zlib.crc32(body) != struct.unpack("<I", raw[-4:])[0]:
            raise ValueError("a block is damaged")
        p, key = 0, b""
        while p < len(body):
            shared, rest, width = body[p : p + 3]
            n, q = read_varint(body, p + 3)
            key = key[:shared] + body[q : q + rest]
            p = q + rest + n * width
            yield key, np.frombuffer(body, f"<u{width}", n, q + rest)

    def may_hold(self, doc_id: int | None) -> bool:
        if self.bloom is None:
            self.bloom = self._read(self.bloom_at, self.bloom_bytes)
        n_bits, probes = struct.unpack("<QB", self.bloom[:9])
        return all(self.bloom[9 + (b >> 3)] >> (b & 7) & 1 for b in bloom_bits(pack_key(doc_id), n_bits, probes))

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        """Ids of every entry with this key."""
        if not self.may_hold(doc_id):
            return []
        key, out = pack_key(doc_id), []
        k = bisect.bisect_left(self.index, key, key=lambda x: x[0])
        while k < len(self.index):
            for found, ids in self._block(k):
                if found == key:
                    out.append(ids)
                elif found > key:
                    return out
            k += 1
        return out

    def scan(self) -> Iterator[tuple[int | None, np.ndarray]]:
        for k in range(len(self.index)):
            for key, ids in self._block(k):
                yield unpack_key(key), ids


MANIFEST = "shard int, path string, n_docs long, n_ids long, first_key binary, last_key binary, n_bytes long"
ENTRIES = "doc_id long, start long, n_tokens long, ids_crc32 long"


def write_shards(docs: DataFrame, folder: str, tokenizer_path: str, end_id: int = 2, block_bytes: int = 65536) -> DataFrame:
    """Encode every text and write shards in ascending doc_id order; returns the manifest, already computed.

    Range partitioning on the identifier and a hash of the text spreads even one identifier over many shards. A task
    writes under a name of its own, so a retried or doubled task leaves a file that no manifest row names.
    Null text is empty, null doc_id comes first, an empty table gives an empty manifest, other columns are ignored.
    """
    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), clean_text().alias("text")).withColumn("tie", F.xxhash64("text"))
    ordered = ordered.repartitionByRange(F.col("doc_id").asc_nulls_first(), "tie").sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "tie").drop("tie")

    def write(frames):
        from pyspark import TaskContext

        enc, writer, sink, first = encoder(tokenizer_path), None, None, b""
        store, base = file_system(folder)
        name = f"{base}/shard-{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex}.sst"
        for frame in frames:
            texts, keys = frame["text"].tolist(), whole(frame["doc_id"])
            for a, b in batches(texts):
                for k, ids in zip(keys[a:b], enc.encode(texts[a:b], end_id), strict=True):
                    if writer is None:
                        store.create_dir(base, recursive=True)
                        sink, first = store.open_output_stream(name), pack_key(k)
                        writer = ShardWriter(sink, block_bytes)
                    writer.add(k, ids)
        if writer is not None:
            writer.finish()
            sink.close()
            size = store.get_file_info(name).size
            path = name if "://" not in folder and not folder.startswith("file:") else folder.rstrip("/") + name[len(base) :]
            yield to_frame([(TaskContext.get().partitionId(), path, writer.entries, writer.total, first, writer.last, size)], MANIFEST)

    return stored(ordered.mapInPandas(tidy(write), MANIFEST), "manifest")


def open_shard(path: str) -> ShardReader:
    store, name = file_system(path)
    return ShardReader(store.open_input_file(name), store.get_file_info(name).size)


def read_shards(manifest: DataFrame, per_batch: int = 2000) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every entry, read back from the files. The driver holds one row per shard."""
    spark = manifest.sparkSession
    rows, before = [], 0
    for r in sorted(manifest.select("shard", "path", "n_ids").collect()):
        rows.append((r.path, before))
        before += r.n_ids
    files = spark.createDataFrame(rows, "path string, before long").repartition(max(1, len(rows)))

    def read(frames):
        for frame in frames:
            for path, before in zip(frame["path"], frame["before"], strict=True):
                out = []
                for k, ids in open_shard(path).scan():
                    out.append((k, before, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                    before += len(ids)
                    if len(out) == per_batch:
                        yield to_frame(out, ENTRIES)
                        out = []
                if out:
                    yield to_frame(out, ENTRIES)

    return files.mapInPandas(tidy(read), ENTRIES)


def lookup(manifest: DataFrame, doc_ids: list[int | None]) -> dict[int | None, list[np.ndarray]]:
    """Ids of a few identifiers: the manifest names the shards whose key range holds one, and each is searched."""
    found: dict[int | None, list[np.ndarray]] = {k: [] for k in doc_ids}
    rows = manifest.collect()
    for k in found:
        key = pack_key(k)
        for r in sorted(rows, key=lambda r: r.shard):
            if bytes(r.first_key) <= key <= bytes(r.last_key):
                found[k] += open_shard(r.path).get(k)
    return found


def token_shards(docs: DataFrame, tokenizer_path: str, end_id: int = 2, folder: str | None = None) -> DataFrame:
    """Write all documents as shards and return what the files say about each: (doc_id, start, n_tokens, ids_crc32).

    Null texts are empty and have their end id only; null ids come first; rows that repeat an id are entries of their own,
    in order of a hash of the text; an empty table gives none; other columns are ignored."""
    return read_shards(write_shards(docs, folder or fresh_path(docs.sparkSession, "token-shards"), tokenizer_path, end_id))


def in_memory(entries: list[tuple[int | None, np.ndarray]], **options) -> ShardReader:
    """A shard in a buffer, for tests and small lookups."""
    sink = io.BytesIO()
    writer = ShardWriter(sink, **options)
    for k, ids in entries:
        writer.add(k, ids)
    writer.finish()
    return ShardReader(sink, len(sink.getvalue()))
