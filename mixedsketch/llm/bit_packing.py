"""Token ids in the fewest bits the vocabulary allows, in files with block offsets.

File layout (all numbers little-endian)::

    "MSBP" | version u16 | bits u16 | ids per block u32
    block 0 | block 1 | ...            each block: ids, `bits` bits apiece, low bits first
    doc ids i64[n] | null flags u8[n] | first id u64[n+1] | block offsets u64[blocks+1]
    docs u64 | ids u64 | footer bytes u64 | "MSBP"

A block is a multiple of 64 ids, so blocks start on whole bytes and 64-id lanes
unpack with numpy shifts.  Any range of ids is read by seeking to its blocks.

Shards are written by executors through ``pyarrow.fs`` into the shared folder,
under a name no other attempt uses; only the shards of attempts that succeed
are in the manifest, so a lost executor or a speculative copy leaves no trace.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernel
from .token_cache import token_cache
from .workspace import Workspace, ship

MAGIC = b"MSBP"
BLOCK = 4096
SHARD_IDS, SHARD_DOCS = 64 << 20, 1 << 20  # a shard ends after as many ids or documents
READ_IDS = 1 << 20


def bits_for(vocabulary: int) -> int:
    """Bits of the largest id, one at least."""
    return max(1, (vocabulary - 1).bit_length())


def pack(ids: np.ndarray, bits: int) -> bytes:
    """Fixed-width little-endian bit stream; the count is filled up to a multiple of 64 with zeros."""
    full = np.zeros(-(-len(ids) // 64) * 64, dtype=np.uint64)
    full[: len(ids)] = ids
    if bits in (8, 16, 32):
        return full.astype(f"<u{bits // 8}").tobytes()
    lanes = full.reshape(-1, 64)
    out = np.zeros((len(lanes), bits), dtype=np.uint64)
    for j in range(64):
        word, shift = divmod(j * bits, 64)
        out[:, word] |= lanes[:, j] << np.uint64(shift)
        if shift + bits > 64:
            out[:, word + 1] |= lanes[:, j] >> np.uint64(64 - shift)
    return out.astype("<u8").tobytes()


def unpack(data: bytes, bits: int) -> np.ndarray:
    """All ids of a packed byte string (a multiple of 64) as uint32."""
    if bits in (8, 16, 32):
        return np.frombuffer(data, dtype=f"<u{bits // 8}").astype(np.uint32)
    words = np.frombuffer(data, dtype="<u8").reshape(-1, bits)
    out = np.empty((len(words), 64), dtype=np.uint32)
    mask = np.uint64((1 << bits) - 1)
    for j in range(64):
        word, shift = divmod(j * bits, 64)
        v = words[:, word] >> np.uint64(shift)
        if shift + bits > 64:
            v = v | (words[:, word + 1] << np.uint64(64 - shift))
        out[:, j] = v & mask
    return out.reshape(-1)


class ShardWriter:
    """Streams documents into one shard; holds less than a block of ids besides the document table."""

    def __init__(self, stream, bits: int, block: int = BLOCK):
        self.stream, self.bits, self.block = stream, bits, block
        self.rest: list[np.ndarray] = []
        self.held = self.ids = 0
        self.docs: list[int] = []
        self.nulls: list[bool] = []
        self.first: list[np.ndarray] = [np.zeros(1, dtype=np.uint64)]
        head = MAGIC + struct.pack("<HHI", 1, bits, block)
        stream.write(head)
        self.offsets = [len(head)]

    def add(self, doc_ids: list, ids: np.ndarray, sizes: np.ndarray) -> None:
        self.docs += [0 if d is None else d for d in doc_ids]
        self.nulls += [d is None for d in doc_ids]
        self.first.append((self.ids + np.cumsum(sizes)).astype(np.uint64))
        self.ids += len(ids)
        self.rest.append(ids)
        self.held += len(ids)
        if self.held >= self.block:
            flat = np.concatenate(self.rest)
            whole = len(flat) // self.block * self.block
            self._put(flat[:whole])
            self.rest, self.held = [flat[whole:]], len(flat) - whole

    def _put(self, ids: np.ndarray) -> None:
        data = pack(ids, self.bits)
        self.stream.write(data)
        step, at = self.block * self.bits // 8, self.offsets[-1]
        self.offsets += [min(at + step * (i + 1), at + len(data)) for i in range(-(-len(ids) // self.block))]

    def close(self) -> None:
        if self.held:
            self._put(np.concatenate(self.rest))
        foot = np.array(self.docs, dtype="<i8").tobytes() + np.array(self.nulls, dtype=np.uint8).tobytes() + np.concatenate(self.first).astype("<u8").tobytes() + np.array(self.offsets, dtype="<u8").tobytes()
        self.stream.write(foot + struct.pack("<QQQ", len(self.docs), self.ids, len(foot)) + MAGIC)
        self.stream.close()


class ShardReader:
    """Random access to a shard through any object with ``read_at(size, offset)`` and ``size()``."""

    def __init__(self, file):
        self.file = file
        if file.read_at(4, 0) != MAGIC:
            raise ValueError("not a packed shard")
        _, self.bits, self.block = struct.unpack("<HHI", file.read_at(8, 4))
        end = file.size()
        n, self.ids, foot = struct.unpack("<QQQ", file.read_at(24, end - 28))
        raw = file.read_at(foot, end - 28 - foot)
        self.doc_ids = np.frombuffer(raw, dtype="<i8", count=n)
        self.nulls = np.frombuffer(raw, dtype=np.uint8, count=n, offset=8 * n).astype(bool)
        self.first = np.frombuffer(raw, dtype="<u8", count=n + 1, offset=9 * n).astype(np.int64)
        self.offsets = np.frombuffer(raw, dtype="<u8", offset=9 * n + 8 * (n + 1)).astype(np.int64)

    def read(self, lo: int, hi: int) -> np.ndarray:
        """Ids lo..hi of the shard; only the blocks that hold them are read."""
        if hi <= lo:
            return np.zeros(0, dtype=np.uint32)
        a, b = lo // self.block, -(-hi // self.block)
        data = self.file.read_at(int(self.offsets[b] - self.offsets[a]), int(self.offsets[a]))
        return unpack(data, self.bits)[lo - a * self.block : hi - a * self.block]

    def document(self, i: int) -> np.ndarray:
        return self.read(int(self.first[i]), int(self.first[i + 1]))

    def digests(self) -> Iterator[tuple[int, int]]:
        """(document, crc32 of its ids as little-endian u32), reading ahead in large pieces."""
        lo = hi = 0
        piece = np.zeros(0, dtype="<u4")
        for i in range(len(self.doc_ids)):
            at, end, crc = int(self.first[i]), int(self.first[i + 1]), 0
            while at < end:
                if at >= hi:
                    lo, hi = at, min(self.ids, at + READ_IDS)
                    piece = self.read(lo, hi).astype("<u4")
                to = min(end, hi)
                crc = zlib.crc32(piece[at - lo : to - lo].tobytes(), crc)
                at = to
            yield i, crc


def _with_end(ids: np.ndarray, sizes: np.ndarray, end_id: int) -> np.ndarray:
    out = np.full(len(ids) + len(sizes), end_id, dtype=np.int64)
    keep = np.ones(len(out), dtype=bool)
    keep[np.cumsum(sizes + 1) - 1] = False
    out[keep] = ids
    return out


def _write(folder: str, vocabulary: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        files, path = pafs.FileSystem.from_uri(folder)
        files.create_dir(path, recursive=True)
        part, seq, writer, name, done = TaskContext.get().partitionId(), 0, None, "", []
        cache = token_cache(vocabulary)
        bits = bits_for(max(cache.vocabulary, end_id + 1))
        for batch in batches:
            ids = batch.column("doc_id")
            for lo, hi, flat, sizes in cache.encode(batch.column("text")):
                if writer is None:
                    name = f"part-{part:06d}-{seq:04d}-{uuid.uuid4().hex}.msbp"
                    writer = ShardWriter(files.open_output_stream(f"{path}/{name}"), bits)
                writer.add(ids.slice(lo, hi - lo).to_pylist(), _with_end(flat, sizes, end_id), sizes + 1)
                if writer.ids >= SHARD_IDS or len(writer.docs) >= SHARD_DOCS:
                    writer.close()
                    done.append((seq, name, len(writer.docs), writer.ids))
                    writer, seq = None, seq + 1
        if writer is not None:
            writer.close()
            done.append((seq, name, len(writer.docs), writer.ids))
        for seq, name, docs, n in done:
            yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "seq": pa.array([seq], pa.int32()), "path": [f"{folder}/{name}"], "docs": pa.array([docs], pa.int64()), "ids": pa.array([n], pa.int64())})

    return run


def write_packed(docs: DataFrame, work: Workspace, vocabulary: str = "word_bpe_49k.json", end_id: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode whole texts and write shards in ascending id order; the manifest (part, seq, path, docs, ids) is returned.

    Null texts are empty (their only id is ``end_id``); null ids come first;
    rows of one id lie side by side.  An empty table gives an empty manifest.
    """
    spark = docs.sparkSession
    ship(spark)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    tie = F.xxhash64("text")
    ordered = docs.repartitionByRange(parts, F.col("doc_id"), tie).sortWithinPartitions(F.col("doc_id"), tie)
    return work.save(ordered.mapInArrow(kernel.tidy(_write(work.path("shards"), vocabulary, end_id)), "part int, seq int, path string, docs long, ids long"), "manifest")


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for path, base in zip(batch.column("path").to_pylist(), batch.column("base").to_pylist(), strict=True):
            files, name = pafs.FileSystem.from_uri(path)
            with files.open_input_file(name) as file:
                shard = ShardReader(file)
                crc = np.fromiter((c for _, c in shard.digests()), dtype=np.int64, count=len(shard.doc_ids))
                cols = [pa.array(shard.doc_ids, mask=shard.nulls), pa.array(base + shard.first[:-1]), pa.array(np.diff(shard.first)), pa.array(crc)]
                for lo in range(0, len(crc), 10_000):
                    yield pa.RecordBatch.from_arrays([c.slice(lo, 10_000) for c in cols], names=["doc_id", "start", "n_tokens", "ids_crc32"])


def read_packed(manifest: DataFrame) -> DataFrame:
    """Per document, from the shards: (doc_id, start, n_tokens, ids_crc32); shards are read side by side."""
    order = Window.orderBy("part", "seq").rowsBetween(Window.unboundedPreceding, -1)  # one small row a shard
    based = manifest.select("path", F.coalesce(F.sum("ids").over(order), F.lit(0)).alias("base"))
    return based.repartition(max(1, manifest.count())).mapInArrow(kernel.tidy(_read), "doc_id long, start long, n_tokens long, ids_crc32 long")


def op3_bit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents`` written as 16-bit ids and read back."""
    return read_packed(write_packed(spark.read.parquet(f"{sf_dir}/documents.parquet"), Workspace(spark, "packed")))
