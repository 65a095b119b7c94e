"""Shared pieces of the text operators: word hashing, rolling n-gram hashes, scratch tables."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cellscrub.session import materialize, scratch_dir  # noqa: F401

_MASK = (1 << 64) - 1
_BASE = 0x9E3779B97F4A7C15
_UNBASE = pow(_BASE, -1, 1 << 64)

SPACE_CLASS = r"[\x20\x09-\x0D]+"


class WordHashes(dict):
    """Memo from a word's bytes to its 64-bit hash; cleared when it outgrows its bound."""

    def __init__(self, bound: int = 100_000):
        self.bound = bound

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.bound:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def _powers(base: int, size: int) -> np.ndarray:
    steps = np.full(size, base, np.uint64)
    steps[0] = 1
    return np.cumprod(steps, dtype=np.uint64)


class RollingHash:
    """Polynomial hashes of all k-grams of a sequence of 64-bit codes, each mixed to 64 bits."""

    def __init__(self):
        self.up = np.ones(1, np.uint64)
        self.down = np.ones(1, np.uint64)

    def _grow(self, n: int) -> None:
        if len(self.up) <= n:
            size = max(n + 1, 2 * len(self.up), 4096)
            self.up, self.down = (_powers(b, size) for b in (_BASE, _UNBASE))

    def grams(self, codes: np.ndarray, k: int, salt: int = 0) -> np.ndarray:
        n = len(codes)
        if n < k:
            return np.empty(0, np.uint64)
        self._grow(n)
        with np.errstate(over="ignore"):
            sums = np.zeros(n + 1, np.uint64)
            np.cumsum(codes * self.up[:n], out=sums[1:])
            return mix64((sums[k:] - sums[:-k]) * self.down[: n - k + 1] + np.uint64(salt))


def mix64(x: np.ndarray) -> np.ndarray:
    """Finalizer with full avalanche, so that any bits of the result can serve as a bucket."""
    with np.errstate(over="ignore"):
        x = x ^ (x >> np.uint64(30))
        x = x * np.uint64(0xBF58476D1CE4E5B9)
        x = x ^ (x >> np.uint64(27))
        x = x * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def byte_texts(column: pa.Array) -> list[bytes | None]:
    """The column's UTF-8 texts as bytes, without decoding them."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()).to_pylist()


def sliced(batches: Iterator[pa.RecordBatch], text_col: str = "text", rows: int = 500, budget: int = 1_000_000) -> Iterator[pa.RecordBatch]:
    """The batches in pieces of few rows and bytes of text (one row at least), so that what a task makes of one stays small."""
    for batch in batches:
        sizes = pc.fill_null(pc.binary_length(batch.column(text_col)), 0).to_numpy(zero_copy_only=False)
        ends = np.cumsum(sizes, dtype=np.int64)
        at = 0
        while at < len(ends):
            before = int(ends[at - 1]) if at else 0
            end = max(at + 1, min(at + rows, int(np.searchsorted(ends, before + budget, "right"))))
            yield batch.slice(at, end - at)
            at = end


#: Rows that go to a Python worker at once; very long texts make Spark's own 10,000 a lot of memory on both sides.
BATCH_ROWS = 1000


def bounded_batches(spark: SparkSession) -> None:
    """Lower the session's Arrow batch size (a runtime setting) to BATCH_ROWS where it is larger or unlimited."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def tidy(*shared: Broadcast) -> None:
    """At a task's end: drop the loaded values of broadcasts and hand freed memory back to the system. Idle workers
    outlive their tasks and share the executor's memory with later stages; a task that needs a value loads it again."""
    for one in shared:
        one.__dict__.pop("_value", None)
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def fresh(df: DataFrame, name: str) -> str:
    """name, with underscores added until no column of df is called so."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def word_array(text: Column) -> Column:
    """Words [^\\x20\\x09-\\x0D]+ of a text as an array; null and blank texts give an empty array."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), SPACE_CLASS), lambda w: w != "")


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def read_table(spark, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
