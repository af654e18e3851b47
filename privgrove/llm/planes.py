"""Token-id files by bit-plane shuffling.

A chunk holds the ids of consecutive whole documents, in blocks of a fixed number of ids. Each block is transposed into
byte planes (or bit planes), each plane is compressed with zstandard on its own, and the chunk begins with an index of
all planes:

    4 bytes PGID, then little-endian unsigned 32-bit: version (1), plane bits (8 or 1), ids a block, blocks, ids in all;
    then for each block and plane its compressed length; then the planes.

Chunks are rows of a Parquet dataset in the shared folder, beside their documents' ids and counts: the Parquet commit
makes a lost task's output vanish whole, and any store that Spark writes to will do.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from privgrove.llm.textio import gathered, shared_dir, texts_of
from privgrove.llm.tokenids import TEXT_BYTES, encoder, with_end

MAGIC, VERSION, WIDTH = b"PGID", 1, 32
BLOCK_IDS = 1 << 16
RANGE_BYTES = 24 << 20


def to_planes(block: np.ndarray, bits: int) -> list[bytes]:
    """Byte planes (bits=8) or bit planes (bits=1) of 32-bit ids, lowest first."""
    raw = np.ascontiguousarray(block, "<u4").view(np.uint8).reshape(-1, 4)
    if bits == 8:
        return [raw[:, k].tobytes() for k in range(4)]
    return [p.tobytes() for p in np.packbits(np.unpackbits(raw, axis=1, bitorder="little").T, axis=1, bitorder="little")]


def from_planes(planes: list[bytes], n: int, bits: int) -> np.ndarray:
    """The inverse of to_planes for n ids."""
    if bits == 8:
        return np.stack([np.frombuffer(p, np.uint8) for p in planes], axis=1).reshape(-1).view("<u4")
    rows = np.stack([np.unpackbits(np.frombuffer(p, np.uint8), count=n, bitorder="little") for p in planes])
    return np.packbits(rows.T, axis=1, bitorder="little").reshape(-1).view("<u4")


def write_chunk(ids: np.ndarray, bits: int = 8, block: int = BLOCK_IDS, level: int = 1) -> bytes:
    """Encode ids as one chunk."""
    pack = zstandard.ZstdCompressor(level=level).compress
    planes = [pack(p) for at in range(0, len(ids), block) for p in to_planes(ids[at : at + block], bits)]
    head = struct.pack("<5I", VERSION, bits, block, -(-len(ids) // block), len(ids))
    return b"".join([MAGIC, head, np.array([len(p) for p in planes], "<u4").tobytes(), *planes])


def read_chunk(chunk: bytes) -> np.ndarray:
    """Decode a chunk; raises ValueError on anything that is not one."""
    if chunk[:4] != MAGIC:
        raise ValueError("not a chunk of token ids")
    version, bits, block, blocks, n = struct.unpack_from("<5I", chunk, 4)
    if version != VERSION or bits not in (1, 8):
        raise ValueError("unknown chunk version")
    each = WIDTH // bits
    sizes = np.frombuffer(chunk, "<u4", blocks * each, 24)
    ends = 24 + 4 * len(sizes) + np.cumsum(sizes.astype(np.int64))
    open_ = zstandard.ZstdDecompressor().decompress
    out = []
    for b in range(blocks):
        planes = [open_(chunk[ends[k] - sizes[k] : ends[k]]) for k in range(b * each, (b + 1) * each)]
        out.append(from_planes(planes, min(block, n - b * block), bits))
    return np.concatenate(out) if out else np.zeros(0, "<u4")


def write_ids(docs: DataFrame, path: str, vocabulary: str, end_id: int, id_col: str = "doc_id", text_col: str = "text", bits: int = 8, block: int = BLOCK_IDS, range_bytes: int = RANGE_BYTES) -> None:
    """Encode every whole text and write chunks in ascending order of the id.

    Null texts are empty: their end id alone. Null ids come first; rows with equal ids are ordered by a hash of the text
    and then the text. An empty table gives an empty dataset. Extra columns are ignored.
    """
    rows = texts_of(docs, id_col, text_col)
    size = rows.agg(F.sum(F.octet_length("text") + 8)).first()[0] or 0
    ranges = max(1, -(-size // range_bytes))

    def encode_range(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, number, at = encoder(vocabulary).encode, 0, TaskContext.get().partitionId()
        for batch in gathered(batches, most=TEXT_BYTES):
            ids, offsets = with_end(*encode(batch.column("text")), end_id)
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([at], pa.int32()),
                    pa.array([number], pa.int32()),
                    pa.array([len(ids)], pa.int64()),
                    pa.array([batch.column("doc_id").to_pylist()], pa.list_(pa.int64())),
                    pa.array([np.diff(offsets)], pa.list_(pa.int64())),
                    pa.array([write_chunk(ids, bits, block)], pa.binary()),
                ],
                names=["range_no", "chunk_no", "n_ids", "doc_ids", "counts", "chunk"],
            )
            number += 1

    ordered = rows.withColumn("tie", F.xxhash64("text")).repartitionByRange(ranges, F.col("doc_id").asc_nulls_first(), "tie")
    ordered = ordered.sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "tie", "text").select("doc_id", "text")
    chunks = ordered.mapInArrow(encode_range, "range_no int, chunk_no int, n_ids long, doc_ids array<long>, counts array<long>, chunk binary")
    chunks.write.mode("overwrite").option("compression", "none").parquet(path)


def read_ids(spark, path: str) -> DataFrame:
    """Per document, from the files: doc_id, start, n_tokens, ids_crc32."""
    chunks = spark.read.parquet(path)
    order = Window.orderBy("range_no", "chunk_no").rowsBetween(Window.unboundedPreceding, -1)
    starts = chunks.select("range_no", "chunk_no", F.coalesce(F.sum("n_ids").over(order), F.lit(0)).alias("chunk_start"))

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                one = {name: batch.column(name)[row] for name in batch.schema.names}
                raw = memoryview(read_chunk(one["chunk"].as_py()).tobytes())
                counts = one["counts"].values.to_numpy()
                begin = np.cumsum(counts) - counts
                n = len(counts)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.full(n, one["range_no"].as_py(), np.int32)),
                        pa.array(np.full(n, one["chunk_no"].as_py(), np.int32)),
                        one["doc_ids"].values,
                        pa.array(begin),
                        pa.array(counts),
                        pa.array([zlib.crc32(raw[4 * a : 4 * (a + c)]) for a, c in zip(begin.tolist(), counts.tolist())], pa.int64()),
                    ],
                    names=["range_no", "chunk_no", "doc_id", "begin", "n_tokens", "ids_crc32"],
                )

    found = chunks.select("range_no", "chunk_no", "doc_ids", "counts", "chunk").mapInArrow(decode, "range_no int, chunk_no int, doc_id long, begin long, n_tokens long, ids_crc32 long")
    return found.join(starts, ["range_no", "chunk_no"]).select("doc_id", (F.col("chunk_start") + F.col("begin")).alias("start"), "n_tokens", "ids_crc32")


def token_files(docs: DataFrame, vocabulary: str, end_id: int, path: str | None = None, **options) -> DataFrame:
    """Write the token files of all documents, read them back, and give one row per document."""
    path = path or f"{shared_dir(docs.sparkSession)}/token_ids"
    write_ids(docs, path, vocabulary, end_id, **options)
    return read_ids(docs.sparkSession, path)
