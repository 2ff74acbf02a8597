"""Token ids in a bit-plane-shuffled binary format, written and read back through Spark.

A chunk is a run of whole documents with at least ``CHUNK_IDS`` ids (but for a shard's last).  Its
payload cuts the ids into fixed-size blocks, transposes each block into byte or bit planes,
compresses every plane with zstandard and starts with an index of the planes' sizes, so one block
can be read alone.  Chunks are rows of a dataset that Spark writes, which gives atomic commits,
retries on lost executors and any store that Spark reaches; a shard is the ordered output of one
task over a range of doc_ids.

Defined results: null and empty texts are the end id alone; rows that share a doc_id are ordered
by text; a null doc_id comes first; an empty table gives an empty store.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from narrative_engine.llm.common import staged, table
from narrative_engine.llm.tokens import as_ids, encoder, vocabulary_path
from narrative_engine.shipping import ship

END = 2
CHUNK_IDS = 1 << 16
BLOCK_IDS = 1 << 14
LEVEL = 1
MAGIC = b"PLN1"
KINDS = ("byte", "bit")
HEAD = struct.Struct("<4sBBII")  # magic, kind, planes, ids, ids of a block

CHUNK = "shard int, chunk int, first long, n_ids long, doc_ids array<long>, counts array<long>, payload binary"


def split_planes(block: np.ndarray, kind: str) -> list[bytes]:
    """Plane ``p`` holds byte (or bit) ``p`` of every id, lowest first."""
    cells = block.astype("<u4").view(np.uint8).reshape(-1, 4)
    if kind == "byte":
        return [np.ascontiguousarray(cells[:, p]).tobytes() for p in range(4)]
    bits = np.unpackbits(cells, axis=1, bitorder="little")
    return [np.packbits(bits[:, p], bitorder="little").tobytes() for p in range(32)]


def join_planes(planes: list[bytes], n: int, kind: str) -> np.ndarray:
    if kind == "byte":
        cells = np.empty((n, 4), dtype=np.uint8)
        for p, raw in enumerate(planes):
            cells[:, p] = np.frombuffer(raw, dtype=np.uint8)
        return cells.reshape(-1).view("<u4")
    bits = np.empty((n, 32), dtype=np.uint8)
    for p, raw in enumerate(planes):
        bits[:, p] = np.unpackbits(np.frombuffer(raw, dtype=np.uint8), count=n, bitorder="little")
    return np.packbits(bits, axis=1, bitorder="little").reshape(-1).view("<u4")


def encode_chunk(ids: np.ndarray, kind: str = "byte", block_ids: int = BLOCK_IDS, level: int = LEVEL) -> bytes:
    packer = zstandard.ZstdCompressor(level=level)
    planes = [packer.compress(p) for at in range(0, len(ids), block_ids) for p in split_planes(ids[at : at + block_ids], kind)]
    width = 4 if kind == "byte" else 32
    index = np.array([len(p) for p in planes], dtype="<u4").tobytes()
    return HEAD.pack(MAGIC, KINDS.index(kind), width, len(ids), block_ids) + index + b"".join(planes)


def decode_chunk(raw: bytes, block: int | None = None) -> np.ndarray:
    """All ids of a chunk, or those of one of its blocks."""
    magic, kind, width, n, block_ids = HEAD.unpack_from(raw)
    if magic != MAGIC:
        raise ValueError("not a chunk of this format")
    blocks = -(-n // block_ids)
    sizes = np.frombuffer(raw, dtype="<u4", count=blocks * width, offset=HEAD.size)
    ends = HEAD.size + 4 * blocks * width + np.cumsum(sizes, dtype=np.int64)
    unpack = zstandard.ZstdDecompressor()
    out = []
    for b in range(blocks) if block is None else [block]:
        planes = [unpack.decompress(raw[ends[k] - sizes[k] : ends[k]]) for k in range(b * width, (b + 1) * width)]
        out.append(join_planes(planes, min(block_ids, n - b * block_ids), KINDS[kind]))
    return np.concatenate(out) if out else np.empty(0, dtype="<u4")


def chunks(docs: DataFrame, path: str | None = None, kind: str = "byte", end: int = END) -> DataFrame:
    """Documents by ranges of doc_id, tokenized in order, as chunk rows."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, shard = encoder(path or vocabulary_path()), TaskContext.get().partitionId()
        chunk, first, held, ids = 0, 0, 0, []
        doc_ids: list[int | None] = []

        def close() -> pa.RecordBatch:
            nonlocal chunk, first, held, ids, doc_ids
            whole = np.concatenate(ids)
            row = [[shard], [chunk], [first], [len(whole)], [doc_ids], [[len(x) for x in ids]], [encode_chunk(whole, kind)]]
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary()]
            chunk, first, held, ids, doc_ids = chunk + 1, first + len(whole), 0, [], []
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(row, kinds)], names=[c.split()[0] for c in CHUNK.split(", ")])

        for batch in batches:
            for doc_id, own_ids in zip(batch.column(0).to_pylist(), own.encode(batch.column(1))):
                doc_ids.append(doc_id)
                ids.append(as_ids(own_ids, end))
                held += len(ids[-1])
                if held >= CHUNK_IDS:
                    yield close()
        if ids:
            yield close()

    ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long"), "text").repartitionByRange("doc_id")
    return rows.sortWithinPartitions("doc_id", "text").mapInArrow(write, CHUNK)


def read_documents(store: DataFrame) -> DataFrame:
    """One row per document of a written store: its place, length and checksum, from the payloads."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for shard, first, doc_ids, counts, raw in zip(*[b.column(k).to_pylist() for k in ("shard", "first", "doc_ids", "counts", "payload")]):
                ids, n = decode_chunk(raw), np.array(counts, dtype=np.int64)
                ends = np.cumsum(n)
                crc = [zlib.crc32(ids[e - k : e].tobytes()) for e, k in zip(ends, n)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([shard] * len(n), pa.int32()), pa.array(doc_ids, pa.int64()), pa.array(first + ends - n), pa.array(n), pa.array(crc, pa.int64())],
                    names=["shard", "doc_id", "own", "n_tokens", "ids_crc32"],
                )

    # one total per shard; their running sum is over as many rows as there were tasks
    sums = store.groupBy("shard").agg(F.sum("n_ids").alias("n"))
    bases = sums.select(F.col("shard").alias("_s"), (F.sum("n").over(Window.orderBy("shard")) - F.col("n")).alias("base"))
    rows = store.mapInArrow(read, "shard int, doc_id long, own long, n_tokens long, ids_crc32 long")
    return rows.join(F.broadcast(bases), F.col("shard") == F.col("_s")).select(
        "doc_id", (F.col("base") + F.col("own")).alias("start"), "n_tokens", "ids_crc32", "shard"
    )


def op3_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_documents(staged(chunks(table(spark, sf_dir, "documents"))))


ORACLE = None
