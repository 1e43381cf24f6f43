"""Helpers of the text operators: shared storage, Arrow text buffers, words and hashes over byte arrays.

Word hashes are 64-bit; two different words, shingles or n-grams that share a hash count as one
(about one expected pair in five billion distinct values).
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsummary.sources.storage import discard, read, shared_dir, small, store

__all__ = ["discard", "read", "shared_dir", "small", "store"]  # and all that stands below

#: Bytes of text that a Python worker turns into arrays at once; one longer text is handled alone.
SLICE_BYTES = 4 << 20

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_K1, _K2, _K3 = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB))
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def fold_of(doc_id: str = "doc_id", folds: int = 5) -> Column:
    """crc32 of the id as text, modulo folds; a null id falls in fold 0."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % folds, F.lit(0)).cast("int")


# ---------------------------------------------------------------- hashing
def mix(h: np.ndarray) -> np.ndarray:
    """Scramble 64-bit values (a fixed bijection)."""
    h = h ^ (h >> np.uint64(30))
    h *= _K2
    h ^= h >> np.uint64(27)
    h *= _K3
    h ^= h >> np.uint64(31)
    return h


def _cell(i: np.ndarray, b: np.ndarray) -> np.ndarray:
    return mix((i.astype(np.uint64) << np.uint64(8) | b.astype(np.uint64)) * _K1 + _K3)


_NEAR = 64
_TABLE = _cell(np.repeat(np.arange(_NEAR), 256), np.tile(np.arange(256, dtype=np.uint8), _NEAR))


def hash_runs(data: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """A hash for each run of bytes: data is the runs' bytes joined, every length is positive."""
    if not len(lens):
        return np.zeros(0, np.uint64)
    first = np.cumsum(lens) - lens
    at = np.arange(len(data), dtype=np.int64) - np.repeat(first, lens)
    v = _TABLE[np.minimum(at, _NEAR - 1) << 8 | data]
    far = np.flatnonzero(at >= _NEAR)
    if len(far):
        v[far] = _cell(at[far], data[far])
    h = np.add.reduceat(v, first)
    return mix(h + lens.astype(np.uint64) * _K1)


# ---------------------------------------------------------------- text buffers
def buffers(col: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts joined, and their offsets; null is the empty text."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    col = col.cast(pa.large_binary()).fill_null(b"")
    if not len(col):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, at, raw = col.buffers()
    offsets = np.frombuffer(at, np.int64)[col.offset : col.offset + len(col) + 1]
    data = np.frombuffer(raw, np.uint8)[offsets[0] : offsets[-1]] if raw is not None else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def give_back() -> None:
    """Return freed memory to the machine: a worker stays after its stage, beside those of the stages that follow."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


def slices(batches: Iterator[pa.RecordBatch], text: str, limit: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Pieces of the batches with about limit bytes of text, each with its text's bytes and offsets."""
    for batch in batches:
        if not batch.num_rows:
            continue
        data, offsets = buffers(batch.column(batch.schema.get_field_index(text)))
        lo, n = 0, batch.num_rows
        while lo < n:
            hi = min(n, max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1))
            yield batch.slice(lo, hi - lo), data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
            lo = hi
        del batch, data, offsets
        give_back()


def runs(solid: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and lengths of the runs of solid bytes, no run crossing into another text, and the texts' offsets among them."""
    edge = offsets[:-1][offsets[:-1] < len(solid)]
    before = np.empty_like(solid)
    before[:1], before[1:] = False, solid[:-1]
    before[edge] = False
    starts = np.flatnonzero(solid & ~before)
    after = np.empty_like(solid)
    after[-1:], after[:-1] = False, solid[1:]
    after[edge[edge > 0] - 1] = False
    return starts, np.flatnonzero(solid & ~after) + 1 - starts, np.searchsorted(starts, offsets)


def words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the lower-cased words ([^ \\t-\\r]+) in order, and each text's offsets among them."""
    solid = ~_SPACE[data]
    _, lens, at = runs(solid, offsets)
    return hash_runs(_LOWER[data[solid]], lens), at


def lowered(data: np.ndarray) -> np.ndarray:
    return _LOWER[data]


def as_long(h: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(h).view(np.int64)
