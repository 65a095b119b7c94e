"""Contiguous shards of near-equal bytes from global prefix sums.

Documents are ordered by id (then size, checksum and read order), range-partitioned and written once as (id, size,
checksum) without their texts. Each partition reports its total; the running sum of these totals gives every document
its global byte offset, and a document belongs to the shard in which its middle byte falls. Law: `bytes`.

Defined results: size is the text's UTF-8 bytes plus 1, so null and empty texts have size 1; text_crc32 of a null text
is that of the empty text; a null id sorts first; rows with equal id, size and checksum are interchangeable; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellscrub.llm.common import fresh, read_table
from cellscrub.session import scratch_dir

SHARDS = 8
SCHEMA = "doc_id long, size long, text_crc32 long, shard int, slot long"


def _totals(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    size = rows = 0
    for batch in batches:
        size += int(np.sum(batch.column("size").to_numpy(zero_copy_only=False)))
        rows += batch.num_rows
    if rows:
        yield pa.RecordBatch.from_pydict({"part": [TaskContext.get().partitionId()], "bytes": [size], "rows": [rows]}, pa.schema([("part", pa.int64()), ("bytes", pa.int64()), ("rows", pa.int64())]))


def _shard_of(before: np.ndarray, size: np.ndarray, total: int, shards: int) -> np.ndarray:
    return np.minimum((2 * before + size) * shards // (2 * total), shards - 1)


def assign_shards(docs: DataFrame, shards: int = SHARDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, shard, slot (gapless from 0 in each shard); what reaches the driver is one row for
    each partition, twice."""
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), (F.octet_length(text).cast("long") + 1).alias("size"), F.crc32(F.encode(text, "utf-8")).alias("text_crc32"))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    scratch_dir(spark)
    ordered = slim.withColumn("tie", F.monotonically_increasing_id()).repartitionByRange(parts, "doc_id", "size", "text_crc32", "tie").sortWithinPartitions("doc_id", "size", "text_crc32", "tie").drop("tie").checkpoint()
    totals = {r.part: (r.bytes, r.rows) for r in ordered.select("size").mapInArrow(_totals, "part long, bytes long, rows long").collect()}
    offsets: dict[int, tuple[int, int]] = {}
    total = rows = 0
    for part in sorted(totals):
        offsets[part] = (total, rows)
        total, rows = total + totals[part][0], rows + totals[part][1]

    def shard_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        before = offsets.get(part, (0, 0))[0]
        counts = np.zeros(shards, np.int64)
        for batch in batches:
            size = batch.column("size").to_numpy(zero_copy_only=False)
            ends = before + np.cumsum(size)
            counts += np.bincount(_shard_of(ends - size, size, total, shards), minlength=shards)
            before = int(ends[-1]) if len(ends) else before
        for s in np.flatnonzero(counts):
            yield pa.RecordBatch.from_pydict({"shard": [int(s)], "rows": [int(counts[s])]}, pa.schema([("shard", pa.int64()), ("rows", pa.int64())]))

    first = [0] * shards
    if total:
        in_shard = {r.shard: r.n for r in ordered.select("size").mapInArrow(shard_counts, "shard long, rows long").groupBy("shard").agg(F.sum("rows").alias("n")).collect()}
        for s in range(1, shards):
            first[s] = first[s - 1] + in_shard.get(s - 1, 0)
    starts = np.array(first, np.int64)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        before, row = offsets.get(TaskContext.get().partitionId(), (0, 0))
        for batch in batches:
            if not batch.num_rows:
                continue
            size = batch.column("size").to_numpy(zero_copy_only=False)
            ends = before + np.cumsum(size)
            shard = _shard_of(ends - size, size, total, shards)
            slot = row + np.arange(len(size)) - starts[shard]
            before, row = int(ends[-1]), row + len(size)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("size"), batch.column("text_crc32"), pa.array(shard.astype(np.int32)), pa.array(slot)], names=["doc_id", "size", "text_crc32", "shard", "slot"])

    return ordered.mapInArrow(place, SCHEMA)


def write_shards(docs: DataFrame, path: str, shards: int = SHARDS) -> DataFrame:
    """Write docs, all columns, to path/shard=k in slot order; rows of equal id and text take their places in any order.

    A text's size and checksum join with its id; an own column `shard` or `slot` is replaced.
    """
    kept = docs.drop("shard", "slot")
    own, size, crc, k = (fresh(kept, f"__{n}") for n in ("id", "size", "crc", "k"))
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    among = Window.partitionBy(own, size, crc)
    keyed = kept.withColumns({own: F.col("doc_id").cast("long"), size: F.octet_length(text).cast("long") + 1, crc: F.crc32(F.encode(text, "utf-8"))}).withColumn(k, F.row_number().over(among.orderBy(F.lit(0))))
    placed = assign_shards(kept, shards).select(F.col("doc_id").alias(own), F.col("size").alias(size), F.col("text_crc32").alias(crc), "shard", "slot").withColumn(k, F.row_number().over(among.orderBy("shard", "slot")))
    a, b = keyed.alias("a"), placed.alias("b")
    match = reduce(lambda x, y: x & y, (F.col(f"a.`{c}`").eqNullSafe(F.col(f"b.`{c}`")) for c in (own, size, crc, k)))
    joined = a.join(b, match).select("a.*", "b.shard", "b.slot").drop(own, size, crc, k)
    joined.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
    return docs.sparkSession.read.parquet(path)


def sharding_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = assign_shards(read_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


#: The checksum is CRC-32 byte by byte, with the table of its polynomial made by rule.
SHARDING_SQL = """
WITH steps AS (
  SELECT list(v ORDER BY n) AS t FROM (
    SELECT n, list_reduce(list_prepend(CAST(n AS BIGINT), range(8)), lambda x, i: CASE WHEN x & 1 = 1 THEN xor(x >> 1, 3988292384) ELSE x >> 1 END) AS v
    FROM (SELECT unnest(range(256)) AS n))
), sized AS (
  SELECT doc_id, CAST(strlen(coalesce(text, '')) + 1 AS BIGINT) AS size, hex(encode(coalesce(text, ''))) AS h FROM documents
), summed AS (
  SELECT doc_id, size, sum(size) OVER (ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) - size AS before, sum(size) OVER () AS total FROM sized
), placed AS (
  SELECT doc_id, size, CAST(least((2 * before + size) * 8 // (2 * total), 7) AS INTEGER) AS shard FROM summed
), sums AS (
  SELECT doc_id, xor(list_reduce(list_prepend(CAST(4294967295 AS BIGINT), list_transform(range(size - 1), lambda i: CAST('0x' || substr(h, 2 * i + 1, 2) AS BIGINT))), lambda crc, b: xor(crc >> 8, t[(xor(crc, b) & 255) + 1])), 4294967295) AS crc
  FROM sized, steps
)
SELECT doc_id, size, CAST(crc AS BIGINT) AS text_crc32, shard, CAST(row_number() OVER (PARTITION BY shard ORDER BY doc_id) - 1 AS BIGINT) AS slot, 'bytes' AS law, CAST(NULL AS INTEGER) AS grown_shard
FROM placed JOIN sums USING (doc_id)
"""
