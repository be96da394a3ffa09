"""What the training-data operators share: scratch tables, Arrow text buffers, samples.

Tables that cut lineage are Parquet files in the folder that the cluster names in
``spark.checkpoint.dir``, so they outlive any executor.  Only where that setting is
absent (tests) a temporary folder is made.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..scratch import drop, store  # noqa: F401

#: Bytes of text and rows that a kernel works on at a time; they bound its arrays whatever the batch holds.
CHUNK_BYTES, CHUNK_ROWS = 1 << 20, 512


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold_of(id_col: str, mod: int) -> Column:
    """crc32 of the id's text modulo ``mod``; -1 for a null id."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % mod, F.lit(-1))


def text_buffer(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and the offsets of its rows; null counts as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    col = pc.fill_null(col, "").cast(pa.large_string())
    off = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + len(col) + 1] if len(col) else np.zeros(1, np.int64)
    data = col.buffers()[2]
    return (np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)), off


def lean(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """run, and at the end of its task the free memory goes back: workers stay, beside an executor that has its own."""

    def out(batches: Iterator) -> Iterator:
        yield from run(batches)
        gc.collect()
        pa.default_memory_pool().release_unused()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc
        if trim:
            trim(0)

    return out


def chunks(off: np.ndarray, most: int = CHUNK_BYTES, rows: int = CHUNK_ROWS) -> Iterator[tuple[int, int]]:
    """Runs of at most ``rows`` rows of about ``most`` bytes; a longer row is a run of its own."""
    i, n = 0, len(off) - 1
    while i < n:
        j = max(i + 1, min(i + rows, int(np.searchsorted(off, off[i] + most, side="right")) - 1))
        yield i, j
        i = j


def rows_of(data: np.ndarray, off: np.ndarray, i: int, j: int) -> Iterator[bytes]:
    raw = data[off[i] : off[j]].tobytes()
    at = (off[i : j + 1] - off[i]).tolist()
    for a, b in zip(at, at[1:]):
        yield raw[a:b]


def byte_table(keep: bytes, *, lower: bool = True, high: bool = True, other: bytes = b" ") -> bytes:
    """256-entry map: A-Z to a-z, ``keep`` and (``high``) bytes of non-ASCII letters as they are, the rest to ``other``."""
    out = bytearray(other * 256)
    for c in keep:
        out[c] = c
    if high:
        out[128:256] = bytes(range(128, 256))
    if lower:
        for c in range(65, 91):
            out[c] = c + 32
    return bytes(out)


LETTERS = bytes(range(97, 123))
#: ASCII letters and digits and everything beyond ASCII, lower-cased; the rest is a blank.
WORD_BYTES = byte_table(LETTERS + b"0123456789")
#: The same without digits.
LETTER_BYTES = byte_table(LETTERS)
#: Lower-cases A-Z only.
LOWER_BYTES = byte_table(bytes(range(128)), lower=True)


def trigram_counts(data: np.ndarray, off: np.ndarray, i: int, j: int, dims: int) -> np.ndarray:
    """Hashed counts of byte trigrams (letters, runs of other bytes as blanks) of rows i..j-1; dims is a power of two."""
    n, lens = j - i, np.diff(off[i : j + 1])
    d = np.frombuffer(LETTER_BYTES, np.uint8)[data[off[i] : off[j]]].astype(np.uint32)
    if len(d) < 3:
        return np.zeros((n, dims), np.float32)
    h = d[:-2] * np.uint32(0x9E3779B1) ^ d[1:-1] * np.uint32(0x85EBCA6B) ^ d[2:] * np.uint32(0xC2B2AE35)
    h ^= h >> np.uint32(15)
    h *= np.uint32(0x2C1B3C6D)
    h >>= np.uint32(32 - dims.bit_length() + 1)
    key = h.astype(np.int64)
    doc = np.repeat(np.arange(n, dtype=np.int64), lens)[: len(key)]
    key += doc * dims
    ends = np.cumsum(lens)
    for back in (1, 2):  # a trigram that runs into the next row doesn't count
        at = (ends - back)[lens >= back]
        key[at[at < len(key)]] = n * dims
    return np.bincount(key, minlength=n * dims + 1)[: n * dims].reshape(n, dims).astype(np.float32)


def unit_roots(counts: np.ndarray) -> np.ndarray:
    """Square roots of relative counts: rows of length 1 (or 0)."""
    total = counts.sum(1, keepdims=True)
    return np.sqrt(counts / np.maximum(total, 1), dtype=np.float32)


def sample_ids(rows: DataFrame, id_col: str, label_col: str, most: int) -> DataFrame:
    """Ids of at most ``most`` rows, shared evenly among labels, chosen by a hash of the id.

    Only ids and labels are read.  Labels are counted over all rows first; a threshold on the
    hash then leaves about twice the quota of each label, however hot, before the ranking."""
    ids = rows.select(F.col(id_col).alias("__id"), F.col(label_col).alias("__label")).filter("__id is not null")
    counts = ids.groupBy("__label").count().orderBy(F.desc("count"), "__label").limit(most).collect()
    quota = max(1, most // max(1, len(counts)))
    share = ids.sparkSession.createDataFrame([(r[0], min(1.0, (2 * quota + 50) / r[1])) for r in counts], "__label string, __share double")
    draw = F.pmod(F.xxhash64("__id"), F.lit(1 << 30)) / float(1 << 30)
    ids = ids.withColumn("__label", F.col("__label").cast("string")).join(F.broadcast(share), "__label").filter(draw < F.col("__share"))
    w = Window.partitionBy("__label").orderBy(F.xxhash64("__id"), "__id")
    return ids.withColumn("__rank", F.row_number().over(w)).filter(F.col("__rank") <= quota).select("__id", "__label").dropDuplicates(["__id"])
