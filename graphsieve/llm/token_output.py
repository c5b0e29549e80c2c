"""Token ids in a bit-packed binary format (fixed width, block offsets).

A segment is a byte string: header, document table, block offsets, payload. Every id takes the bits that the largest
id of the vocabulary needs, lowest bit first; blocks of BLOCK ids start at a byte and their offsets are listed, so any
range of ids is unpacked by numpy from its blocks alone. Segments are held in Parquet files, one row each: Spark's
commit protocol then covers task retries, lost executors and any store that Spark can write.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsieve.llm.common import PieceEncoder, new_path

MAGIC = b"GSBITS01"
BLOCK = 4096
HEAD = "<8sBxxxIQII"  # magic, bits an id, ids a block, ids, blocks, documents
SCHEMA = "shard int, segment int, shard_start long, n_ids long, blob binary"


def bits_for(vocabulary: int) -> int:
    """Bits that hold every id below ``vocabulary``."""
    return max(1, (max(vocabulary, 1) - 1).bit_length())


def pack(ids: np.ndarray, width: int) -> bytes:
    if ids.size and int(ids.max()) >> width:
        raise ValueError(f"an id needs more than {width} bits")
    if width in (8, 16, 32):
        return ids.astype(f"<u{width // 8}").tobytes()
    bits = (ids.astype(np.uint64)[:, None] >> np.arange(width, dtype=np.uint64)) & 1
    return np.packbits(bits.astype(np.uint8).ravel(), bitorder="little").tobytes()


def unpack(data: bytes, n: int, width: int) -> np.ndarray:
    if width in (8, 16, 32):
        return np.frombuffer(data, f"<u{width // 8}", n).astype("<u4")
    bits = np.unpackbits(np.frombuffer(data, np.uint8), bitorder="little")[: n * width].reshape(n, width)
    return (bits.astype(np.uint64) << np.arange(width, dtype=np.uint64)).sum(1).astype("<u4")


def write_segment(doc_ids: list[int | None], counts: list[int], ids: np.ndarray, width: int) -> bytes:
    blocks = [pack(ids[i : i + BLOCK], width) for i in range(0, len(ids), BLOCK)]
    table = np.array([0 if d is None else d for d in doc_ids], "<i8").tobytes() + np.array([d is None for d in doc_ids], "u1").tobytes() + np.array(counts, "<u8").tobytes()
    offsets = np.concatenate([[0], np.cumsum([len(b) for b in blocks], dtype=np.int64)]).astype("<u8").tobytes()
    return struct.pack(HEAD, MAGIC, width, BLOCK, len(ids), len(blocks), len(doc_ids)) + table + offsets + b"".join(blocks)


class Segment:
    """Reader of one segment, with random access to its ids."""

    def __init__(self, blob: bytes):
        magic, self.width, self.block, self.n_ids, n_blocks, n_docs = struct.unpack_from(HEAD, blob)
        if magic != MAGIC:
            raise ValueError("not a segment of packed ids")
        at = struct.calcsize(HEAD)
        docs = np.frombuffer(blob, "<i8", n_docs, at)
        null = np.frombuffer(blob, "u1", n_docs, at + 8 * n_docs)
        self.doc_ids = [None if x else int(d) for d, x in zip(docs, null)]
        self.counts = np.frombuffer(blob, "<u8", n_docs, at + 9 * n_docs).astype(np.int64)
        self.offsets = np.frombuffer(blob, "<u8", n_blocks + 1, at + 17 * n_docs).astype(np.int64)
        self.blob, self.base = blob, at + 17 * n_docs + 8 * (n_blocks + 1)

    def ids(self, start: int = 0, stop: int | None = None) -> np.ndarray:
        """Ids from start to stop; only the blocks that hold them are read."""
        stop = self.n_ids if stop is None else min(stop, self.n_ids)
        if start >= stop:
            return np.empty(0, "<u4")
        first, last = start // self.block, (stop - 1) // self.block
        parts = [unpack(self.blob[self.base + self.offsets[b] : self.base + self.offsets[b + 1]], min(self.block, self.n_ids - b * self.block), self.width) for b in range(first, last + 1)]
        return np.concatenate(parts)[start - first * self.block : stop - first * self.block]


def write_token_files(docs: DataFrame, path: str, tokenizer: str, kind: str = "byte", vocabulary: int = 50_257, end_id: int | None = 0, segment_ids: int = 1 << 20) -> None:
    """Encode ``docs(doc_id, text)`` and write the packed ids in ascending order of doc_id below ``path``.

    Ranges of doc_id go to shards, each written by one task; repeated ids are ordered by a hash of the text, null ids
    come first, null texts are empty. A segment closes when it holds ``segment_ids`` ids; a longer document makes a
    longer segment. An empty table writes no segment. Extra columns are ignored.
    """
    width = bits_for(vocabulary)

    def packed(batches):
        from pyspark import TaskContext

        encoder, shard = PieceEncoder.get(tokenizer, kind), TaskContext.get().partitionId()
        tail = b"" if end_id is None else struct.pack("<I", end_id)
        doc_ids, counts, parts, held, segment, before = [], [], [], 0, 0, 0

        def closed():
            blob = write_segment(doc_ids, counts, np.frombuffer(b"".join(parts), "<u4"), width)
            return pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int32()), "segment": pa.array([segment], pa.int32()), "shard_start": pa.array([before]), "n_ids": pa.array([held]), "blob": pa.array([blob], pa.binary())})

        for batch in batches:
            for d, text in zip(batch["doc_id"].to_pylist(), batch["text"]):
                ids = encoder.encode(text.as_py()) + tail
                doc_ids.append(d), counts.append(len(ids) // 4), parts.append(ids)
                held += len(ids) // 4
                if held >= segment_ids:
                    yield closed()
                    segment, before, held = segment + 1, before + held, 0
                    doc_ids, counts, parts = [], [], []
        if doc_ids:
            yield closed()

    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    order = [F.col("doc_id"), F.xxhash64("text")]
    rows.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(packed, SCHEMA).write.parquet(path)


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """Rows ``(doc_id, start, n_tokens, ids_crc32)`` of all documents, from the files alone.

    The number of ids before a shard comes from one row per shard, which the driver adds up; shards are tasks, never
    documents.
    """
    held = spark.read.schema(SCHEMA).parquet(path)
    before, starts = 0, []
    for shard, n in sorted(held.groupBy("shard").agg(F.sum("n_ids")).collect()):
        starts.append((shard, before))
        before += n
    starts = spark.createDataFrame(starts, "shard int, before long")

    def read(batches):
        for batch in batches:
            for before, start, blob in zip(batch["before"].to_pylist(), batch["shard_start"].to_pylist(), batch["blob"]):
                s = Segment(blob.as_py())
                data, ends = memoryview(s.ids().tobytes()), np.cumsum(s.counts)
                firsts = ends - s.counts
                yield pa.RecordBatch.from_pydict({
                    "doc_id": pa.array(s.doc_ids, pa.int64()),
                    "start": pa.array(firsts + before + start),
                    "n_tokens": pa.array(s.counts),
                    "ids_crc32": pa.array([zlib.crc32(data[4 * a : 4 * b]) for a, b in zip(firsts.tolist(), ends.tolist())], pa.int64()),
                })

    return held.join(F.broadcast(starts), "shard").select("before", "shard_start", "blob").mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_output(docs: DataFrame, tokenizer: str, kind: str = "byte", vocabulary: int = 50_257, path: str | None = None) -> DataFrame:
    """Write the files (in the shared folder unless a path is given) and read them back."""
    spark = docs.sparkSession
    path = path or new_path(spark, "token-files")
    write_token_files(docs, path, tokenizer, kind, vocabulary)
    return read_token_files(spark, path)
