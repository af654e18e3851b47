"""Best-fit packing of tokenised documents into sequences of a fixed length.

Bounded-space online best-fit: each packer keeps a fixed number of open bins. A bitset has bit f set while some open bin
has f free places, so the tightest bin that still fits is the lowest set bit at or above the piece's length, and the
fullest bin, which closes first when a new one is needed, is the lowest set bit of all.

Documents are tokenised where they are read; only piece lengths are shuffled. Pieces reach a packer by falling length.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from privgrove.llm.textio import gathered, stored, texts_of
from privgrove.llm.tokenids import TEXT_BYTES, encoder, with_end

#: Tokens that one packer handles.
PACKER_TOKENS = 8 << 20
OPEN_BINS = 8192
#: Parts that rows equal in every key are dealt out to.
SALTS = 64


class OpenBins:
    """Open bins of `size` places, at most `most` of them."""

    def __init__(self, size: int, most: int):
        self.size, self.most = size, most
        self.bits, self.count, self.made = 0, 0, 0
        self.by_free: list[list[int]] = [[] for _ in range(size + 1)]

    def take(self, free: int) -> int:
        bins = self.by_free[free]
        found = bins.pop()
        self.count -= 1
        if not bins:
            self.bits &= ~(1 << free)
        return found

    def put(self, length: int) -> tuple[int, int]:
        """Place a piece; gives the bin's number and the place in it."""
        fitting = self.bits >> length
        if fitting:
            free = length + (fitting & -fitting).bit_length() - 1
            found = self.take(free)
        else:
            free, found = self.size, self.made
            self.made += 1
            if self.count >= self.most:
                self.take((self.bits & -self.bits).bit_length() - 1)
        left = free - length
        if left:
            self.by_free[left].append(found)
            self.bits |= 1 << left
            self.count += 1
        return found, self.size - free


def piece_table(docs: DataFrame, vocabulary: str, size: int, end_id: int, id_col: str, text_col: str) -> DataFrame:
    """One row per piece of each document: doc_id, piece, start, length, ids_crc32."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary).encode
        for batch in gathered(batches, most=TEXT_BYTES):
            ids, offsets = with_end(*encode(batch.column("text")), end_id)
            lengths = np.diff(offsets)
            pieces = (lengths + size - 1) // size
            row = np.repeat(np.arange(len(lengths)), pieces)
            number = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
            start = number * size
            length = np.minimum(size, lengths[row] - start)
            raw, at = memoryview(ids.astype("<u4").tobytes()), (offsets[row] + start) * 4
            crc = [zlib.crc32(raw[a : a + 4 * n]) for a, n in zip(at.tolist(), length.tolist())]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").take(pa.array(row)), pa.array(number.astype(np.int32)), pa.array(start), pa.array(length), pa.array(crc, pa.int64())],
                names=["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    return texts_of(docs, id_col, text_col).mapInArrow(cut, "doc_id long, piece int, start long, length long, ids_crc32 long")


def pack(pieces: DataFrame, size: int, open_bins: int = OPEN_BINS, packer_tokens: int = PACKER_TOKENS) -> DataFrame:
    """Add sequence_id and offset to rows that have a `length` of 1 to `size`.

    Every row is placed. Packers get their rows by hash and in a total order, so a task that is run again gives the same
    sequences. Rows equal in every key, however many there are, are dealt out over SALTS packers by their place in the
    table; which of them goes where makes no difference.
    """
    total = pieces.agg(F.sum("length")).first()[0] or 0
    packers = max(1, -(-total // packer_tokens))
    schema = pieces.select("*", F.lit(0).cast("long").alias("sequence_id"), F.lit(0).cast("long").alias("offset")).schema

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bins, base = OpenBins(size, open_bins), TaskContext.get().partitionId() << 36
        for batch in batches:
            placed = [bins.put(n) for n in batch.column("length").to_pylist()]
            spots = np.array(placed, np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(spots[:, 0] + base), pa.array(spots[:, 1])], names=[*batch.schema.names, "sequence_id", "offset"])

    keys, salt = ["doc_id", "piece", "ids_crc32"], F.pmod(F.monotonically_increasing_id(), F.lit(SALTS))
    spread = pieces.repartition(packers, *keys, salt) if has_repeats(pieces, keys) else pieces.repartition(packers, *keys)
    return spread.sortWithinPartitions(F.desc("length"), *keys).mapInArrow(place, schema)


def has_repeats(pieces: DataFrame, keys: list[str]) -> bool:
    """Whether some rows are equal in all keys more than SALTS times over."""
    return not pieces.groupBy(*keys).agg(F.count(F.lit(1)).alias("held")).where(F.col("held") > SALTS).isEmpty()


def pack_documents(docs: DataFrame, vocabulary: str, size: int = 2048, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text", open_bins: int = OPEN_BINS, packer_tokens: int = PACKER_TOKENS) -> DataFrame:
    """Pack documents into sequences of at most `size` tokens; gives one row per piece.

    Null and empty texts are a single end id. Null or repeated ids stay apart as rows of their own; rows equal in every
    column get separate places. An empty table gives no rows. Extra columns are ignored. Only documents longer than
    `size` are cut: into full pieces and a last one that may be shorter.
    """
    pieces = stored(piece_table(docs, vocabulary, size, end_id, id_col, text_col), "pieces")
    return pack(pieces, size, open_bins, packer_tokens)
