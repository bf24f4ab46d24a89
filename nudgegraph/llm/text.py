"""Shared pieces of the text kernels: column checks and word hashing."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame

_MUL = np.uint64(0x9E3779B97F4A7C15)
_MIX = np.uint64(0xBF58476D1CE4E5B9)
_S29, _S32 = np.uint64(29), np.uint64(32)


def need(df: DataFrame, *columns: str) -> DataFrame:
    """The named columns alone, so that other columns can't clash with ours."""
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns {missing}; there are {df.columns}")
    return df.select(*[df[c] for c in columns])


def trimmed(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The kernel; when its task ends, the worker, which others use after it, gives unused memory back."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        pa.default_memory_pool().release_unused()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # not every C library has it
        if trim is not None:
            trim(0)

    return kernel


def words_of(text: str | None) -> list[bytes]:
    """Words between ASCII white space, A-Z lower-cased."""
    return [] if text is None else text.encode("utf-8", "surrogatepass").lower().split()


def shingle_set(words: list[bytes], width: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of ``width``-word shingles.

    Fewer words than ``width`` make one shingle; no words make none.
    """
    if not words:
        return np.empty(0, np.uint64)
    width = min(width, len(words))
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
    n = len(words) - width + 1
    with np.errstate(over="ignore"):
        x = np.full(n, np.uint64(width), np.uint64)
        for j in range(width):
            x = (x ^ (x >> _S29)) * _MUL + h[j : j + n]
        x ^= x >> _S32
        x *= _MIX
        x ^= x >> _S29
    return np.unique(x)
