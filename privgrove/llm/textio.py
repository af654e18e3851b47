"""Helpers shared by the text operators: bounded slices, chunk dictionaries, shared tables."""

from __future__ import annotations

import ctypes
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text bytes that one vectorised step handles at once; a longer single text forms a step of its own.
SLICE_BYTES = 6 << 20


def shared_dir(spark: SparkSession) -> str:
    """A new folder that the driver and every executor reach: below spark.checkpoint.dir.

    Where a local session names none (tests), /tmp/checkpoints serves; on a cluster that is an error.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        root = "/tmp/checkpoints"
    return f"{root.rstrip('/')}/privgrove-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str, at: str | None = None, level: int = 3) -> DataFrame:
    """Write df as Parquet in the shared folder and read it back: cuts lineage, survives lost executors.

    A higher level of zstandard is for wide binary columns: slower to write, smaller on disk, the same bytes.
    """
    spark = df.sparkSession
    path = f"{at or shared_dir(spark)}/{name}"
    df.write.mode("overwrite").option("compression", "zstd").option("parquet.compression.codec.zstd.level", level).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def free_names(taken: list[str], *wanted: str) -> list[str]:
    """The names wanted, with lines before them where columns of that name are there already (upper or lower case)."""
    held = {t.lower() for t in taken}
    out = []
    for name in wanted:
        while name.lower() in held:
            name = f"_{name}"
        held.add(name.lower())
        out.append(name)
    return out


def texts_of(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc_id, text) with null texts as empty strings; extra columns are dropped before any Python step."""
    return df.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"),
    )


def plain(array: pa.Array | pa.ChunkedArray, kind: pa.DataType) -> pa.Array:
    """One array of the type given."""
    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks() if array.num_chunks != 1 else array.chunk(0)
    return array if array.type == kind else array.cast(kind)


def trimmed() -> None:
    """Give freed memory back to the system: a worker shares its executor's limit with the JVM."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Split batches so that each has at most `most` bytes in column, or one row; at the end, memory is given back."""
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        size = np.cumsum(pc.binary_length(batch.column(column)).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while at < n:
            base = size[at - 1] if at else 0
            end = max(at + 1, int(np.searchsorted(size, base + most, "right")))
            yield batch.slice(at, end - at)
            at = end
    trimmed()


def gathered(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Slices of about `most` bytes: small batches are joined, large ones split."""
    held, size = [], 0
    for part in slices(batches, column, most):
        n = pc.sum(pc.binary_length(part.column(column))).as_py() or 0
        if held and size + n > most:
            yield joined(held)
            held, size = [], 0
            trimmed()
        held.append(part)
        size += n
    if held:
        yield joined(held)
    trimmed()


def joined(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
    return parts[0] if len(parts) == 1 else pa.Table.from_batches(parts).combine_chunks().to_batches()[0]


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Flat indices of the ranges [start, start + length), one range after another."""
    lengths = lengths.astype(np.int64)
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    out = np.ones(total, np.int64)
    full = np.flatnonzero(lengths)
    begin = starts[full].astype(np.int64)
    at = np.concatenate(([0], np.cumsum(lengths[full])[:-1]))
    out[at] = begin
    out[at[1:]] -= begin[:-1] + lengths[full][:-1] - 1
    return np.cumsum(out)


def segment_sums(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Sum of values[offsets[i]:offsets[i+1]] for every i, empty ranges included."""
    total = np.concatenate((np.zeros(1, values.dtype if values.dtype.kind == "f" else np.int64), np.cumsum(values)))
    return total[offsets[1:]] - total[offsets[:-1]]


def summed(parts: DataFrame, column: str, dtype: str, size: int, combine=np.add, ways: int = 16) -> np.ndarray:
    """Combine the fixed-size arrays in column; a few tasks do most of it, the driver the rest."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, dtype)
        for batch in batches:
            for value in batch.column(0):
                combine(total, np.frombuffer(value.as_py(), dtype), out=total)
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=[column])

    total = np.zeros(size, dtype)
    for row in parts.select(column).coalesce(ways).mapInArrow(run, f"{column} binary").toLocalIterator():
        combine(total, np.frombuffer(row[0], dtype), out=total)
    return total


class Chunks:
    """Texts as codes into a dictionary of space-separated chunks.

    offsets[i]:offsets[i+1] are the codes of text i; `words` has each distinct chunk, without its leading space.
    """

    def __init__(self, texts: pa.Array):
        parts = pc.split_pattern(texts, " ")
        encoded = parts.flatten().dictionary_encode()
        self.offsets = parts.offsets.to_numpy().astype(np.int64)
        self.offsets -= self.offsets[0]
        self.codes = encoded.indices.to_numpy(zero_copy_only=False)
        self.words = encoded.dictionary
