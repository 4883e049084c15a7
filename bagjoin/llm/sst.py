"""Token-id output as sorted-string-table shards.

A shard holds documents in ascending key order:

    data blocks   entries [shared prefix][rest length][key rest][value bytes][value], then a CRC-32
    index         per block: first key, offset, length, entries, tokens before the block
    Bloom filter  over the keys
    footer        fixed size: offsets, counts, id width, magic

Numbers in entries are LEB128; a key is the document's 64-bit id, big-endian with the sign bit
flipped, so that byte order is id order. Keys share their prefix with the entry before; every 16th
entry and the first of a block start anew. A lookup asks the Bloom filter, finds the block by binary
search in the sparse index, and scans that one block.

Shards are written by the tasks that own a range of ids, to names no other attempt uses; the
returned manifest names the files that count, so a lost executor or a repeated task does no harm.
"""

from __future__ import annotations

import os
import struct
import uuid
import zlib
from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import chunks_of
from .common import WordTable, n_parts, new_folder, process_table, table, text_column

MAGIC = b"BJSST001"
FOOTER = struct.Struct("<QQQQQQII8s")  # index at, index bytes, bloom at, bloom bytes, docs, tokens, id width, hashes
BLOCK = 64 << 10
RESTART = 16
BLOOM_BITS, BLOOM_HASHES = 10, 7


def key_of(doc_id: int | None) -> bytes:
    """Order-keeping key; null sorts first, as the empty key."""
    return b"" if doc_id is None else struct.pack(">Q", (doc_id + (1 << 63)) & (1 << 64) - 1)


def id_of(key: bytes) -> int | None:
    return struct.unpack(">Q", key)[0] - (1 << 63) if key else None


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _number(b: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        x = b[at]
        at += 1
        n |= (x & 127) << shift
        if x < 128:
            return n, at
        shift += 7


def _probes(key: bytes, bits: int, k: int) -> list[int]:
    h = xxhash.xxh128_intdigest(key)
    a, b = h & (1 << 64) - 1, h >> 64 | 1
    return [(a + i * b) % bits for i in range(k)]


class ShardWriter:
    """Writes one shard to an open binary stream; keys must not fall."""

    def __init__(self, out, width: int):
        self.out, self.width, self.at = out, width, 0
        self.block, self.entries, self.last = bytearray(), 0, b""
        self.first, self.before = None, 0
        self.index: list[bytes] = []
        self.keys: list[bytes] = []
        self.tokens = 0
        self.top = b""

    def add(self, key: bytes, value: bytes) -> None:
        if key < self.top:
            raise ValueError("keys must come in ascending order")
        if self.first is None:
            self.first, self.before = key, self.tokens
        shared = 0 if self.entries % RESTART == 0 else len(os.path.commonprefix([self.last, key]))
        self.block += _varint(shared) + _varint(len(key) - shared) + key[shared:] + _varint(len(value)) + value
        self.entries += 1
        self.last = self.top = key
        self.keys.append(key)
        self.tokens += len(value) // self.width
        if len(self.block) >= BLOCK:
            self._flush()

    def _flush(self) -> None:
        if self.first is None:
            return
        body = bytes(self.block) + struct.pack("<I", zlib.crc32(self.block))
        self.out.write(body)
        self.index.append(_varint(len(self.first)) + self.first + struct.pack("<QIIQ", self.at, len(body), self.entries, self.before))
        self.at += len(body)
        self.block, self.entries, self.first, self.last = bytearray(), 0, None, b""

    def close(self) -> None:
        self._flush()
        index = b"".join(self.index)
        bits = max(64, BLOOM_BITS * len(self.keys))
        bloom = bytearray((bits + 7) // 8)
        for k in self.keys:
            for p in _probes(k, bits, BLOOM_HASHES):
                bloom[p >> 3] |= 1 << (p & 7)
        self.out.write(index + struct.pack("<I", zlib.crc32(index)))
        self.out.write(struct.pack("<Q", bits) + bytes(bloom))
        self.out.write(FOOTER.pack(self.at, len(index) + 4, self.at + len(index) + 4, 8 + len(bloom), len(self.keys), self.tokens, self.width, BLOOM_HASHES, MAGIC))


class ShardReader:
    """Reads a shard from a random-access file of pyarrow's file systems."""

    def __init__(self, file):
        self.file = file
        size = file.size()
        foot = self._read(size - FOOTER.size, FOOTER.size)
        (self.index_at, n, self.bloom_at, self.bloom_n, self.docs, self.tokens, self.width, self.k, magic) = FOOTER.unpack(foot)
        if magic != MAGIC:
            raise ValueError("not a shard")
        raw = self._read(self.index_at, n)
        if zlib.crc32(raw[:-4]) != struct.unpack("<I", raw[-4:])[0]:
            raise ValueError("index is damaged")
        self.blocks: list[tuple[bytes, int, int, int, int]] = []
        at = 0
        while at < n - 4:
            k, at = _number(raw, at)
            key = raw[at : at + k]
            self.blocks.append((key, *struct.unpack_from("<QIIQ", raw, at + k)))
            at += k + 24
        self._bloom: bytes | None = None

    def _read(self, at: int, n: int) -> bytes:
        self.file.seek(at)
        return self.file.read(n)

    def block(self, i: int) -> Iterator[tuple[bytes, bytes]]:
        _, at, n, entries, _ = self.blocks[i]
        raw = self._read(at, n)
        if zlib.crc32(raw[:-4]) != struct.unpack("<I", raw[-4:])[0]:
            raise ValueError(f"block {i} is damaged")
        p, key = 0, b""
        for _ in range(entries):
            s, p = _number(raw, p)
            r, p = _number(raw, p)
            key = key[:s] + raw[p : p + r]
            v, p = _number(raw, p + r)
            yield key, raw[p : p + v]
            p += v

    def ids(self, value: bytes) -> np.ndarray:
        return np.frombuffer(value, "<u2" if self.width == 2 else "<u4").astype("<u4")

    def __iter__(self) -> Iterator[tuple[int | None, np.ndarray]]:
        for i in range(len(self.blocks)):
            for k, v in self.block(i):
                yield id_of(k), self.ids(v)

    def may_hold(self, key: bytes) -> bool:
        if self._bloom is None:
            self._bloom = self._read(self.bloom_at, self.bloom_n)
        bits = struct.unpack("<Q", self._bloom[:8])[0]
        return all(self._bloom[8 + (p >> 3)] >> (p & 7) & 1 for p in _probes(key, bits, self.k))

    def get(self, doc_id: int | None) -> list[np.ndarray]:
        """Values of an id, in file order; empty if it is absent."""
        key = key_of(doc_id)
        if not self.blocks or not self.may_hold(key):
            return []
        first = [b[0] for b in self.blocks]
        i = max(0, bisect_right(first, key) - 1)
        while i > 0 and first[i] == key:  # repeated ids may begin in the block before
            i -= 1
        out = []
        for j in range(i, len(self.blocks)):
            if first[j] > key:
                break
            out += [self.ids(v) for k, v in self.block(j) if k == key]
        return out


def open_shard(path: str) -> ShardReader:
    f, p = pafs.FileSystem.from_uri(path)
    return ShardReader(f.open_input_file(p))


class LibraryEncoder:
    """The tokenizers library behind a bounded table of words.

    The file's pre-splitting never joins text across white space, so a document's ids are those of
    its white-space-free chunks in order. Chunks that are not in the table go through the library,
    many to a call, and its offsets tell which ids belong to which.
    """

    def __init__(self, path: str, dtype: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.lib, self.dtype, self.words = Tokenizer.from_file(path), dtype, WordTable(self._learn, 600_000)
        self.lib.no_truncation()
        self.lib.no_padding()

    def _learn(self, chunks: list[str]) -> list[bytes]:
        parts = [chunks[lo : lo + 200] for lo in range(0, len(chunks), 200)]
        out = []
        for some, got in zip(parts, self.lib.encode_batch([" ".join(p) for p in parts], add_special_tokens=False)):
            ids = np.array(got.ids, self.dtype)
            at = np.array(got.offsets, np.int64).reshape(-1, 2)[:, 0]
            cut = (np.searchsorted(at, np.cumsum([len(c) + 1 for c in some])) * ids.itemsize).tolist()
            raw = ids.tobytes()
            out += [raw[p:q] for p, q in zip([0, *cut], cut)]
        return out

    def encode(self, texts: list[str]) -> list[bytes]:
        return list(map(b"".join, self.words.lookup(list(map(chunks_of, texts)))))


def library_encoder(path: str, dtype: str) -> LibraryEncoder:
    """One encoder in a worker process, so that its table serves many tasks."""
    return process_table(("sst", path, dtype), lambda: LibraryEncoder(path, dtype))


def write_shards(docs: DataFrame, folder: str, tokenizer: str, key: str = "doc_id", text: str = "text", end_id: int = 2, parts: int | None = None, width: int = 2) -> list[dict]:
    """Encode ``docs`` and write shards in ascending ``key`` order; returns the manifest.

    The manifest has one entry a file (path, docs, tokens, start), ordered by key; only it reaches
    the driver. Null text counts as empty (the end id alone). Rows that repeat a key are all kept,
    ordered by text; null keys come first. An empty table gives no shard. ``width`` is 2 for
    vocabularies under 65,536 ids, else 4.
    """
    dtype = {2: "<u2", 4: "<u4"}[width]
    src = docs.select(docs[key].cast("long").alias("k"), docs[text].alias("t"))
    src = src.repartitionByRange(parts or n_parts(docs.sparkSession), "k").sortWithinPartitions(F.col("k").asc_nulls_first(), "t")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, end = library_encoder(tokenizer, dtype), np.array([end_id], dtype).tobytes()
        store, base = pafs.FileSystem.from_uri(folder)
        store.create_dir(base, recursive=True)
        name = f"{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex}.sst"
        out = w = None
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                for k, v in zip(part.column("k").to_pylist(), enc.encode(text_column(part, "t"))):
                    if w is None:
                        out = store.open_output_stream(f"{base}/{name}", buffer_size=1 << 20)
                        w = ShardWriter(out, width)
                    w.add(key_of(k), v + end)
        if w is not None:
            w.close()
            out.close()
            yield pa.RecordBatch.from_pydict({"part": [TaskContext.get().partitionId()], "path": [f"{folder}/{name}"], "docs": [len(w.keys)], "tokens": [w.tokens]})

    rows = sorted(src.mapInArrow(run, "part long, path string, docs long, tokens long").collect())
    out, start = [], 0
    for r in rows:
        out.append({"path": r.path, "docs": r.docs, "tokens": r.tokens, "start": start})
        start += r.tokens
    return out


def read_shards(spark: SparkSession, manifest: list[dict]) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, from the files of a manifest."""
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long"
    if not manifest:
        return spark.createDataFrame([], schema)
    files = spark.createDataFrame([(m["path"], m["start"]) for m in manifest], "path string, start long").repartition(len(manifest))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, start in zip(batch.column("path").to_pylist(), batch.column("start").to_pylist()):
                reader = open_shard(path)
                for i, b in enumerate(reader.blocks):
                    at = start + b[4]
                    rows = []
                    for k, v in reader.block(i):
                        ids = reader.ids(v)
                        rows.append((id_of(k), at, len(ids), zlib.crc32(ids.tobytes())))
                        at += len(ids)
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return files.mapInArrow(run, schema)


def op4_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encode all ``documents`` into shards in the shared folder and read them back."""
    import public_tokenizers

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    manifest = write_shards(docs, new_folder(spark, "token-shards"), public_tokenizers.path("word_bpe_49k.json"))
    return read_shards(spark, manifest)
