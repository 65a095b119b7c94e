"""A bitmap of fixed size that tells which 64-bit hashes were met in more than one place.

Tasks pack their hashes by leading bits, sorted and delta-coded in byte planes, so about two to three bytes per hash are
shuffled. It can say "repeated" of a hash that is not (its leading bits collide with a repeated one), never the reverse,
so callers may use it to drop or to order work but not to decide a result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

BITMAP_BITS = 28
BUCKET_BITS = 8
#: Bytes of text for each bucket beyond which buckets are halved, so that no task's share of hashes grows with the data.
BUCKET_BYTES = 64 << 20
FLUSH_AT = 1_000_000


def pack_sorted(codes: np.ndarray) -> bytes:
    steps = np.diff(codes, prepend=np.uint32(0)).astype("<u4")
    return steps.view(np.uint8).reshape(-1, 4).T.tobytes()


def unpack_sorted(blob: bytes) -> np.ndarray:
    steps = np.ascontiguousarray(np.frombuffer(blob, np.uint8).reshape(4, -1).T).view("<u4").ravel()
    return np.cumsum(steps, dtype=np.uint32)


def _packing(hashes_of: Callable[[], Callable[[bytes | None], np.ndarray]], bucket_bits: int, text_col: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from cellscrub.llm.common import byte_texts, sliced, tidy

        of = hashes_of()
        held: list[np.ndarray] = []
        size = 0

        def flush() -> pa.RecordBatch:
            every = np.sort(np.concatenate(held))
            buckets = (every >> np.uint64(64 - bucket_bits)).astype(np.int64)
            codes = ((every >> np.uint64(32 - bucket_bits)) & np.uint64(0xFFFFFFFF)).astype(np.uint32)
            cuts = np.flatnonzero(np.diff(buckets)) + 1
            firsts = buckets[np.concatenate(([0], cuts)).astype(np.int64)]
            return pa.RecordBatch.from_arrays([pa.array(firsts.astype(np.int32)), pa.array([pack_sorted(c) for c in np.split(codes, cuts)], pa.binary())], names=["bucket", "codes"])

        try:
            for batch in sliced(batches, text_col):
                for text in byte_texts(batch.column(text_col)):
                    found = of(text)
                    if len(found):
                        held.append(found)
                        size += len(found)
                    if size > FLUSH_AT:
                        yield flush()
                        held, size = [], 0
            if size:
                yield flush()
        finally:
            del of, held
            tidy()

    return run


def _slices(bitmap_bits: int, bucket_bits: int, levels: tuple[int, ...]):
    def run(key: tuple[pa.Scalar, ...], group: pa.Table) -> pa.Table:
        codes = np.sort(np.concatenate([unpack_sorted(b) for b in group.column("codes").to_pylist()]))
        change = np.ones(len(codes), bool)
        change[1:] = codes[1:] != codes[:-1]
        at = np.flatnonzero(change)
        counts = np.diff(at, append=len(codes))
        places = codes[at] >> np.uint32(32 - (bitmap_bits - bucket_bits))
        rows = []
        for level in levels:
            bits = np.zeros(1 << (bitmap_bits - bucket_bits), bool)
            bits[places[counts >= level]] = True
            rows.append(np.packbits(bits).tobytes())
        return pa.table({"bucket": pa.array([key[0].as_py()] * len(levels), pa.int32()), "level": pa.array(range(len(levels)), pa.int32()), "bits": pa.array(rows, pa.binary())})

    return run


def repetition_bitmaps(texts: DataFrame, hashes_of: Callable, text_col: str = "text", levels: tuple[int, ...] = (2,), bitmap_bits: int = BITMAP_BITS, bucket_bits: int | None = None) -> list[bytes]:
    """For each level a packed bitmap of 2**bitmap_bits bits over the hashes' leading bits: those met that often.

    hashes_of() is called once in each task and gives the function from a text's bytes to its 64-bit hashes. A bucket is
    one task's work; their number follows the input's size as Spark estimates it, up to one for each 4,096 bits.
    """
    if bucket_bits is None:
        estimate = int(texts._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
        bucket_bits = min(max(BUCKET_BITS, (estimate // BUCKET_BYTES).bit_length()), bitmap_bits - 12)
    packed = texts.select(text_col).mapInArrow(_packing(hashes_of, bucket_bits, text_col), "bucket int, codes binary")
    slices = packed.groupBy("bucket").applyInArrow(_slices(bitmap_bits, bucket_bits, levels), "bucket int, level int, bits binary").collect()
    step = (1 << (bitmap_bits - bucket_bits)) // 8
    out = [bytearray((1 << bitmap_bits) // 8) for _ in levels]
    for row in slices:
        out[row.level][row.bucket * step : (row.bucket + 1) * step] = row.bits
    return [bytes(b) for b in out]


def test_bits(bitmap: np.ndarray, hashes: np.ndarray, bitmap_bits: int = BITMAP_BITS) -> np.ndarray:
    at = (hashes >> np.uint64(64 - bitmap_bits)).astype(np.int64)
    return (bitmap[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1 == 1


test_bits.__test__ = False
