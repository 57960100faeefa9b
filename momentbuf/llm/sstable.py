"""Token-id output as sorted-string-table shards.

A shard holds documents in key order: data blocks with prefix-compressed keys
and restart points, a sparse index (one entry a block), a Bloom filter and a
footer that says where these lie. A lookup reads footer, filter and index, then
one block, and searches it by its restart points.

Keys are doc_id as nine bytes that sort as the ids do (null first). Ids of rows
with the same doc_id are all kept, in the order of their bytes. Null and empty
texts hold the end id alone.
"""

from __future__ import annotations

import bisect
import os
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from momentbuf.llm.common import arrow_map, cut, records, shared_dir, table, text_chunks
from momentbuf.llm.tokens import encoder, vocabulary

MAGIC = b"MBSST\x00\x01\n"
_FOOTER = struct.Struct("<QQQQQQ8s")
_ENTRY = struct.Struct("<HHI")


def key_of(doc_id: int | None) -> bytes:
    return b"\x00" * 9 if doc_id is None else b"\x01" + struct.pack(">Q", doc_id + (1 << 63))


def id_of(key: bytes) -> int | None:
    return None if key[:1] == b"\x00" else struct.unpack(">Q", key[1:])[0] - (1 << 63)


def _bloom_bits(key: bytes, bits: int, probes: int) -> list[int]:
    a, b = zlib.crc32(key), zlib.crc32(key, 0x9E3779B9) | 1
    return [(a + i * b) % bits for i in range(probes)]


class ShardWriter:
    """Append documents in key order; `close` returns the number of documents and of ids. Memory: one block, the index and ten bits a key."""

    def __init__(self, sink, block_bytes: int = 256 << 10, restart: int = 16, bits_a_key: int = 10):
        self.sink, self.block_bytes, self.restart, self.bits_a_key = sink, block_bytes, restart, bits_a_key
        self.at = self.docs = self.ids = 0
        self.index: list[tuple[bytes, int, int]] = []
        self.hashes = bytearray()
        self.pack = zstandard.ZstdCompressor(level=1)
        self._open()

    def _open(self) -> None:
        self.block, self.restarts, self.n, self.last, self.first = bytearray(), [], 0, b"", None

    def add(self, key: bytes, ids: bytes) -> None:
        if key < self.last or (self.index and self.first is None and key < self.index[-1][0]):
            raise ValueError("keys must be appended in order")
        if self.n % self.restart == 0:
            self.restarts.append(len(self.block))
            shared = 0
        else:
            shared = len(os.path.commonprefix([self.last, key]))
        narrow = np.frombuffer(ids, "<u4")
        value = b"\x02" + narrow.astype("<u2").tobytes() if not len(narrow) or narrow.max() < 65536 else b"\x04" + ids
        self.block += _ENTRY.pack(shared, len(key) - shared, len(value)) + key[shared:] + value
        self.first, self.last, self.n = key if self.first is None else self.first, key, self.n + 1
        self.hashes += struct.pack("<II", zlib.crc32(key), zlib.crc32(key, 0x9E3779B9) | 1)
        self.docs, self.ids = self.docs + 1, self.ids + len(narrow)
        if len(self.block) >= self.block_bytes:
            self._flush()

    def _put(self, data: bytes) -> int:
        at, self.at = self.at, self.at + len(data)
        self.sink.write(data)
        return at

    def _flush(self) -> None:
        if self.n:
            raw = bytes(self.block) + struct.pack(f"<{len(self.restarts)}I", *self.restarts) + struct.pack("<I", len(self.restarts))
            data = self.pack.compress(raw)
            self.index.append((self.first, self._put(data + struct.pack("<I", zlib.crc32(data))), len(data) + 4))
            self._open()

    def close(self) -> tuple[int, int]:
        self._flush()
        bits = max(64, self.bits_a_key * self.docs)
        h = np.frombuffer(bytes(self.hashes), "<u4").astype(np.uint64).reshape(-1, 2)
        on = np.zeros((bits + 7) // 8, np.uint8)
        for i in range(7):
            p = (h[:, 0] + np.uint64(i) * h[:, 1]) % np.uint64(bits)
            np.bitwise_or.at(on, (p >> np.uint64(3)).astype(np.int64), (1 << (p & np.uint64(7))).astype(np.uint8))
        bloom = self._put(on.tobytes())
        body = b"".join(struct.pack("<HQI", len(k), at, n) + k for k, at, n in self.index)
        index = self._put(body)
        self._put(_FOOTER.pack(bloom, bits, index, len(body), self.docs, self.ids, MAGIC))
        return self.docs, self.ids


class ShardReader:
    """Reads a shard from anything with seek, read and a size."""

    def __init__(self, source, size: int):
        self.source = source
        source.seek(size - _FOOTER.size)
        bloom, self.bits, index, n, self.docs, self.ids, magic = _FOOTER.unpack(source.read(_FOOTER.size))
        if magic != MAGIC:
            raise ValueError("not a shard, or cut off")
        source.seek(bloom)
        self.bloom = source.read((self.bits + 7) // 8)
        source.seek(index)
        body, at, self.index = source.read(n), 0, []
        while at < n:
            k, off, length = struct.unpack_from("<HQI", body, at)
            self.index.append((body[at + 14 : at + 14 + k], off, length))
            at += 14 + k
        self.unpack = zstandard.ZstdDecompressor()

    def may_have(self, key: bytes) -> bool:
        return all(self.bloom[b >> 3] >> (b & 7) & 1 for b in _bloom_bits(key, self.bits, 7))

    def _block(self, i: int) -> tuple[bytes, list[int], int]:
        _, off, n = self.index[i]
        self.source.seek(off)
        data = self.source.read(n)
        if zlib.crc32(data[:-4]) != struct.unpack("<I", data[-4:])[0]:
            raise ValueError("block checksum differs")
        raw = self.unpack.decompress(data[:-4])
        k = struct.unpack("<I", raw[-4:])[0]
        end = len(raw) - 4 - 4 * k
        return raw, list(struct.unpack(f"<{k}I", raw[end:-4])), end

    @staticmethod
    def _entries(raw: bytes, at: int, end: int) -> Iterator[tuple[bytes, bytes]]:
        key = b""
        while at < end:
            shared, own, n = _ENTRY.unpack_from(raw, at)
            at += _ENTRY.size
            key = key[:shared] + raw[at : at + own]
            value = raw[at + own : at + own + n]
            at += own + n
            yield key, value[1:] if value[:1] == b"\x04" else np.frombuffer(value, "<u2", offset=1).astype("<u4").tobytes()

    def __iter__(self) -> Iterator[tuple[bytes, bytes]]:
        for i in range(len(self.index)):
            raw, _, end = self._block(i)
            yield from self._entries(raw, 0, end)

    def get(self, doc_id: int | None) -> list[bytes]:
        """Ids (as bytes) of every row with this doc_id: filter, sparse index, then restart points."""
        key, out = key_of(doc_id), []
        if not self.may_have(key):
            return out
        firsts = [k for k, _, _ in self.index]
        i = max(0, bisect.bisect_left(firsts, key) - 1)
        while i < len(firsts) and firsts[i] <= key:
            raw, restarts, end = self._block(i)
            lo = bisect.bisect_left(range(len(restarts)), key, key=lambda j: next(self._entries(raw, restarts[j], end))[0])
            for k, v in self._entries(raw, restarts[max(0, lo - 1)], end):
                if k > key:
                    break
                if k == key:
                    out.append(v)
            i += 1
        return out


def _filesystem(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


_MANIFEST = pa.schema([("low", pa.binary()), ("path", pa.string()), ("docs", pa.int64()), ("ids", pa.int64())])


def write_shards(docs: DataFrame, folder: str, vocabulary_path: str, blanks: bool = False, end_id: int = 1, partitions: int | None = None) -> DataFrame:
    """Encode (doc_id, text) and write one shard for each range of doc_ids; returns the manifest (low, path, docs, ids).

    A shard gets a name of its own for each attempt and is renamed when it is
    whole, so a task that runs again never damages another's file.
    """
    folder = folder if "://" in folder else f"file://{folder.removeprefix('file:')}"

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, tail = encoder(vocabulary_path, blanks), np.uint32(end_id).tobytes()
        out = same = None
        waiting: list[bytes] = []
        for b in batches:
            ids, texts = b.column("doc_id").to_pylist(), b.column("text").to_pylist()
            for i, j in text_chunks(texts):
                for d, body in zip(ids[i:j], enc.encode(texts[i:j]), strict=True):
                    if out is None:
                        store, base = _filesystem(folder)
                        store.create_dir(base, recursive=True)
                        name = f"{base}/{uuid.uuid4().hex}.sst"
                        out = store.open_output_stream(f"{name}.part")
                        shard, low, same = ShardWriter(out), key_of(d), key_of(d)
                    if (key := key_of(d)) != same:
                        for x in sorted(waiting):
                            shard.add(same, x)
                        waiting, same = [], key
                    waiting.append(body + tail)
        if out is not None:
            for x in sorted(waiting):
                shard.add(same, x)
            n, k = shard.close()
            out.close()
            store.move(f"{name}.part", name)
            yield records(_MANIFEST, low=[low], path=[f"{folder}/{name.rpartition('/')[2]}"], docs=[n], ids=[k])

    by = docs.select("doc_id", "text")
    by = by.repartitionByRange(partitions, "doc_id") if partitions else by.repartitionByRange("doc_id")
    return arrow_map(by.sortWithinPartitions("doc_id"), write, "low binary, path string, docs long, ids long", uses="tokens")


_ROWS = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])


def read_shards(manifest: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of every document, from the shards' files; start counts on over the shards in key order."""
    before = F.coalesce(F.sum("ids").over(Window.orderBy("low").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, start in zip(b.column("path").to_pylist(), b.column("before").to_pylist(), strict=True):
                store, name = _filesystem(path)
                with store.open_input_file(name) as f:
                    rows = []
                    for key, ids in ShardReader(f, f.size()):
                        rows.append((id_of(key), start, len(ids) // 4, zlib.crc32(ids)))
                        start += len(ids) // 4
                        if len(rows) == 10_000:
                            yield records(_ROWS, **dict(zip(_ROWS.names, zip(*rows, strict=True), strict=True)))
                            rows = []
                    if rows:
                        yield records(_ROWS, **dict(zip(_ROWS.names, zip(*rows, strict=True), strict=True)))

    placed = manifest.withColumn("before", before).select("path", "before")
    return arrow_map(placed.repartition(max(1, min(manifest.count(), 10_000)), "path"), read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op6_token_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    manifest = cut(write_shards(docs, f"{shared_dir(spark)}/shards", vocabulary("word_bpe_49k.json")))
    return read_shards(manifest)
