"""Sorted-string-table shards of token ids, keyed by document identifier.

A shard holds entries in ascending key order in compressed blocks whose keys share prefixes, then a
sparse index (first key of each block), a Bloom filter and a footer of fixed size. A lookup reads
the footer, asks the filter, finds the block by binary search and scans that block alone.

Keys: one byte (0 for a null identifier, else 1) and the identifier as 8 big-endian bytes with the
sign bit flipped, so byte order is numeric order with null first. Rows of one identifier are entries of
their own, in order of their texts. An empty table writes no shard.
"""

from __future__ import annotations

import re
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Cut

MAGIC = b"KBSST001"
_FOOTER, _FOOTER_SIZE = "<QQQQQQB7x8s", 64
BLOCK_BYTES, RESTART, BITS_PER_KEY, HASHES = 64 << 10, 16, 10, 7
SHARD_BYTES = 64 << 20


def encode_key(doc_id: int | None) -> bytes:
    return b"\0" if doc_id is None else b"\1" + struct.pack(">Q", (doc_id + (1 << 63)) & ((1 << 64) - 1))


def decode_key(key: bytes) -> int | None:
    return None if key[0] == 0 else struct.unpack(">Q", key[1:])[0] - (1 << 63)


def _varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _read_varint(b: bytes, at: int) -> tuple[int, int]:
    n = shift = 0
    while True:
        c = b[at]
        at += 1
        n |= (c & 127) << shift
        if c < 128:
            return n, at
        shift += 7


def _bloom_bits(key: bytes, n_bits: int) -> list[int]:
    import xxhash

    h = xxhash.xxh64_intdigest(key)
    step = (h >> 33) | 1
    return [(h + k * step) % n_bits for k in range(HASHES)]


class ShardWriter:
    """Writes one shard to a binary file object; keys must come in ascending order."""

    def __init__(self, out, width: int):
        import zstandard

        self.out, self.width, self.zstd = out, width, zstandard.ZstdCompressor(level=1)
        self.index, self.keys, self.offset, self.n_ids = [], [], 0, 0
        self._clear()

    def _clear(self) -> None:
        self.block, self.n, self.first, self.last = bytearray(), 0, None, b""

    def add(self, key: bytes, value: bytes) -> None:
        """``value``: the ids as little-endian integers of ``width`` bytes."""
        shared = 0
        if self.n % RESTART:
            most = min(len(key), len(self.last))
            while shared < most and key[shared] == self.last[shared]:
                shared += 1
        self.block += _varint(shared) + _varint(len(key) - shared) + _varint(len(value)) + key[shared:] + value
        self.first = key if self.first is None else self.first
        self.last, self.n = key, self.n + 1
        self.keys.append(key)
        self.n_ids += len(value) // self.width
        if len(self.block) >= BLOCK_BYTES:
            self._flush()

    def _write(self, b: bytes) -> tuple[int, int]:
        at = self.offset
        self.out.write(b)
        self.offset += len(b)
        return at, len(b)

    def _flush(self) -> None:
        if self.n:
            packed = self.zstd.compress(bytes(self.block))
            at, size = self._write(struct.pack("<I", zlib.crc32(packed)) + packed)
            self.index.append((self.first, at, size))
            self._clear()

    def close(self) -> None:
        self._flush()
        index = b"".join(_varint(len(k)) + k + struct.pack("<QI", at, size) for k, at, size in self.index)
        n_bits = max(64, len(self.keys) * BITS_PER_KEY)
        bits = np.zeros(n_bits, bool)
        for k in self.keys:
            bits[_bloom_bits(k, n_bits)] = True
        i_at, i_size = self._write(index)
        b_at, _ = self._write(np.packbits(bits, bitorder="little").tobytes())
        self._write(struct.pack(_FOOTER, i_at, i_size, b_at, n_bits, len(self.keys), self.n_ids, self.width, MAGIC))


class ShardReader:
    """Reads a shard from a seekable binary file object."""

    def __init__(self, f, size: int):
        self.f = f
        f.seek(size - _FOOTER_SIZE)
        i_at, i_size, self.b_at, self.n_bits, self.n_keys, self.n_ids, self.width, magic = struct.unpack(_FOOTER, f.read(_FOOTER_SIZE))
        if magic != MAGIC:
            raise ValueError("not a shard of this format")
        f.seek(i_at)
        raw, at, self.index = f.read(i_size), 0, []
        while at < i_size:
            n, at = _read_varint(raw, at)
            key = raw[at : at + n]
            offset, length = struct.unpack_from("<QI", raw, at + n)
            self.index.append((key, offset, length))
            at += n + 12

    def _block(self, k: int) -> Iterator[tuple[bytes, bytes]]:
        import zstandard

        _, offset, length = self.index[k]
        self.f.seek(offset)
        raw = self.f.read(length)
        if struct.unpack_from("<I", raw)[0] != zlib.crc32(raw[4:]):
            raise ValueError(f"block {k} is damaged")
        b, at, key = zstandard.ZstdDecompressor().decompress(raw[4:]), 0, b""
        while at < len(b):
            shared, at = _read_varint(b, at)
            n, at = _read_varint(b, at)
            size, at = _read_varint(b, at)
            key = key[:shared] + b[at : at + n]
            at += n
            yield key, b[at : at + size]
            at += size

    def __iter__(self) -> Iterator[tuple[bytes, bytes]]:
        for k in range(len(self.index)):
            yield from self._block(k)

    def may_hold(self, key: bytes) -> bool:
        for bit in _bloom_bits(key, self.n_bits):
            self.f.seek(self.b_at + bit // 8)
            if not self.f.read(1)[0] >> bit % 8 & 1:
                return False
        return True

    def get(self, key: bytes) -> list[bytes]:
        """The values of all entries with that key."""
        if not self.index or not self.may_hold(key):
            return []
        lo, hi = 0, len(self.index)
        while lo < hi:  # the first block that begins with the key or after it
            mid = (lo + hi) // 2
            lo, hi = (mid + 1, hi) if self.index[mid][0] < key else (lo, mid)
        out = []
        for k in range(max(0, lo - 1), len(self.index)):
            if self.index[k][0] > key:
                break
            out += [v for x, v in self._block(k) if x == key]
        return out

    def ids(self, value: bytes) -> np.ndarray:
        return np.frombuffer(value, f"<u{self.width}")


# --- token ids -------------------------------------------------------------------------------------------


class WordEncoder:
    """Ids of a text by a tokenizers file whose pre-tokenizer never joins text across white space.

    Ids of white-space-separated chunks are remembered (a bounded number of them); letters that end a
    chunk's plain form are lower-cased before the look-up, as the file's normaliser would do. Every other chunk
    goes through the library's whole pipeline.
    """

    PLAIN = re.compile(r"([A-Za-zÀ-ÖØ-öø-ÿ]+)([!-&(-/:-@\[-`{-~]*)\Z")
    CUT = re.compile(r"[\t-\r ]+")

    def __init__(self, path: str, width: int, most: int = 400_000):
        from tokenizers import Tokenizer

        self.tok, self.width, self.most = Tokenizer.from_file(path), width, most
        self.model, self.cache, self.parts = self.tok.model, {}, {}
        visible = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
        rest = [b for b in range(256) if b not in visible]
        self.bytes = {b: chr(b) for b in visible} | {b: chr(256 + k) for k, b in enumerate(rest)}  # the byte-level alphabet

    def _pack(self, ids) -> bytes:
        return np.asarray(ids, f"<u{self.width}").tobytes()

    def _part(self, s: str) -> bytes:
        got = self.parts.get(s)
        if got is None:
            if len(self.parts) >= self.most:
                self.parts.clear()
            plain = s if s.isascii() else "".join(map(self.bytes.__getitem__, s.encode()))
            got = self.parts[s] = self._pack([t.id for t in self.model.tokenize(plain)])
        return got

    def _chunk(self, w: str) -> bytes:
        m = self.PLAIN.match(w) if len(w) < 200 else None
        if m:
            return self._part(m[1].lower()) + (self._part(m[2]) if m[2] else b"")
        return self._pack(self.tok.encode_batch_fast([w], add_special_tokens=False)[0].ids) if w else b""

    def __call__(self, text: str | None) -> bytes:
        chunks = self.CUT.split(text or "")
        cache = self.cache
        for w in chunks:
            if w not in cache:
                if len(cache) >= self.most and len(w) < 200:
                    cache.clear()
                    return b"".join([self._chunk(x) for x in chunks])
                cache[w] = self._chunk(w)
        return b"".join(map(cache.__getitem__, chunks))


def _open(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write_shards(docs: DataFrame, folder: str, tokenizer: str, end_id: int = 2, width: int = 2) -> DataFrame:
    """Encode every text, append ``end_id`` and write shards below ``folder`` in ascending doc_id order.

    Returns the manifest (part, seq, path, n_docs, n_ids), whose order by part and seq is that of the
    identifiers. A task that is run again writes new files; only those of the run that counts are listed.
    """
    schema = "part int, seq int, path string, n_docs long, n_ids long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, seq, writer, encoder, out = TaskContext.get().partitionId(), 0, None, None, None
        end = np.asarray([end_id], f"<u{width}").tobytes()

        def close():
            writer.close()
            out.close()
            return pa.RecordBatch.from_pylist(
                [{"part": part, "seq": seq, "path": path, "n_docs": len(writer.keys), "n_ids": writer.n_ids}],
                pa.schema([("part", pa.int32()), ("seq", pa.int32()), ("path", pa.string()), ("n_docs", pa.int64()), ("n_ids", pa.int64())]),
            )

        for b in batches:
            encoder = encoder or WordEncoder(tokenizer, width)
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1)):
                if writer is None:
                    path = f"{folder}/{part:06d}-{seq:04d}-{uuid.uuid4().hex}.sst"
                    system, name = _open(path)
                    system.create_dir(name.rpartition("/")[0], recursive=True)
                    out = system.open_output_stream(name)
                    writer = ShardWriter(out, width)
                writer.add(encode_key(doc_id), encoder(text.as_py()) + end)
                if writer.offset >= SHARD_BYTES:
                    yield close()
                    writer, seq = None, seq + 1
        if writer is not None:
            yield close()

    ordered = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    return ordered.mapInArrow(run, schema)


def read_shards(manifest: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every entry, decoded from the shards' blocks.

    ``start`` is the number of ids in all entries before; a shard's own start is summed over the
    manifest, which has one row per shard.
    """
    before = F.coalesce(F.sum("n_ids").over(W.orderBy("part", "seq").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    shards = manifest.withColumn("base", before.cast("long"))
    n = max(1, min(10_000, manifest.count()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, base in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                system, name = _open(path)
                rows = []
                with system.open_input_file(name) as f:
                    reader = ShardReader(f, f.size())
                    for key, value in reader:
                        ids = reader.ids(value)
                        rows.append((decode_key(key), base, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                        base += len(ids)
                columns = [pa.array(c, pa.int64()) for c in zip(*rows)] if rows else [pa.array([], pa.int64())] * 4
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "start", "n_tokens", "ids_crc32"])

    return shards.select("path", "base").repartition(n, "path").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, tokenizer: str, end_id: int = 2) -> DataFrame:
    """Write shards to the shared folder and read them back."""
    cut = Cut(docs.sparkSession)
    return read_shards(cut(write_shards(docs, cut.path("shards"), tokenizer, end_id)))


def lookup(paths: list[str], doc_id: int | None) -> list[np.ndarray]:
    """The ids of a document, from the shards that may hold it."""
    found = []
    for path in paths:
        system, name = _open(path)
        with system.open_input_file(name) as f:
            reader = ShardReader(f, f.size())
            found += [reader.ids(v) for v in reader.get(encode_key(doc_id))]
    return found
