"""Shared helpers: durable intermediate tables, bounded caches, word splitting and hashing."""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.storage import discard, reclaim, scratch, shared_dir, written  # noqa: F401  (for the operators of this subpackage)

#: A side of a join is broadcast explicitly only up to this many rows of a few dozen bytes each.
BROADCAST_ROWS = 1_000_000


def small_side(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` marked for broadcast if its counted rows are within the limit; else unmarked, and the join shuffles."""
    return F.broadcast(df) if rows <= limit else df


def bucket_of(col: str, n: int):
    """crc32 of the id written as decimal text, modulo n; null ids give null."""
    return F.pmod(F.crc32(F.col(col).cast("string").cast("binary")), F.lit(n))


def _give_back() -> None:
    """Returns memory that earlier batches and tasks of this worker have freed to the system, which the allocators would keep."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def text_batches(spark, rows: int = 1000) -> None:
    """Arrow batches of ``rows`` at most from here on in the session (10,000 by default), as every row may be a long text."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= rows:
        spark.conf.set(key, rows)


def sliced(batches, rows: int = 256):
    """The Arrow batches in slices of few rows, so that a task holds few texts as Python strings at a time."""
    _give_back()
    for b in batches:
        for i in range(0, b.num_rows, rows):
            yield b.slice(i, rows)
    _give_back()


class Memo(dict):
    """Bounded memo of ``compute``: two generations, so what is used often stays when the older half goes."""

    def __init__(self, compute, cap: int = 400_000, longest: int = 64):
        super().__init__()
        self.compute, self.cap, self.longest, self.old = compute, cap, longest, {}

    def __missing__(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.compute(key)
            if len(key) > self.longest:
                return value
        if len(self) >= self.cap:
            self.old = dict(self)
            self.clear()
        self[key] = value
        return value


def word_hashes(words: list[bytes]) -> np.ndarray:
    """64-bit hash of each word."""
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


_MUL = np.uint64(0x9E3779B97F4A7C15)


def mixed(x: np.ndarray) -> np.ndarray:
    """Bijective finaliser on 64-bit values (splitmix64 constants, fixed values)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def window_hashes(h: np.ndarray, k: int) -> np.ndarray:
    """Order-sensitive 64-bit hash of every k consecutive word hashes (polynomial in an odd base, then mixed)."""
    n = len(h) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    # doubling: hash of 2^j words from two hashes of 2^(j-1) words
    acc, done, base, size, rest = None, 0, h, 1, k
    power = _MUL
    while rest:
        if rest & 1:
            part = base[done : done + n]
            acc = part.copy() if acc is None else acc * power + part
            done += size
        rest >>= 1
        if rest:
            base = base[:-size] * power + base[size:] if len(base) > size else base[:0]
            size *= 2
            power = np.uint64((int(power) ** 2 + 2) % (1 << 64))
    return mixed(acc)
