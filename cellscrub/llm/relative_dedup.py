"""Substring dedup by relative Lempel-Ziv parsing of every document against reference blocks.

The reference is the corpus itself. Winnowing picks anchors (20-word hashes) so that two equal 35-word windows always
pick the same anchor at the same place. An anchor's hash names a reference block: all contexts of the anchor, each the
run of windows that picked it, with equal contexts held once and counted. So a document meets every block that can hold a
passage of it, and no other. A bounded bitmap of anchors seen more than once spares most documents the rest.

In a block, contexts are sequences of window symbols (one for each distinct 35-word window). The block is indexed by the
sorted order of all suffixes of its contexts, made by doubling; the longest stretch that a suffix shares with any other
place is its longest common prefix with a neighbour in that order. Every context is then parsed greedily from left to
right: where the block holds the current window at another place, the longest such stretch becomes a factor (of 35 words
at least) and the parse goes on behind it, otherwise one window is passed as a literal. As the symbols are whole windows, the first
window behind a factor, the one that crosses its end, is looked up anew at every factor boundary. So a window lies in
some factor exactly if it also starts elsewhere; a document's factors of all its blocks are laid over its words, and the
covered words go.

Equality of windows means equality of the 64-bit anchor hash and of an independent 64-bit window hash.

Defined results: a null, blank or short text (under 35 words) keeps all its words; repeated rows count as different
places, so both copies go; a null id is an id like any other; an empty table gives an empty result; other columns are
ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellscrub.llm.common import RollingHash, WordHashes, bounded_batches, byte_texts, materialize, mix64, read_table, sliced, tidy
from cellscrub.llm.sketches import BITMAP_BITS, repetition_bitmaps, test_bits

WINDOW = 35
ANCHOR = 20

_ANCHOR_SALT, _WINDOW_SALT = 0x51A7, 0xC0FFEE


def _anchors(codes: np.ndarray, rolling: RollingHash, window: int, anchor: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Anchor positions and hashes, and for each window the index of the anchor it picks (leftmost minimum)."""
    grams = rolling.grams(codes, anchor, _ANCHOR_SALT)
    span = window - anchor + 1
    picked = np.lib.stride_tricks.sliding_window_view(grams, span).argmin(1) + np.arange(len(grams) - span + 1)
    change = np.ones(len(picked), bool)
    change[1:] = picked[1:] != picked[:-1]
    # minima crowd at small values, so they are mixed again before their leading bits deal them out
    return picked[change], mix64(grams[picked[change]]), np.cumsum(change) - 1


def _digest(words: list[bytes]) -> str:
    return hashlib.sha256(b" ".join(words)).hexdigest()


class _Reader:
    def __init__(self):
        self.hashes, self.rolling = WordHashes(), RollingHash()


def _anchor_hasher(window: int, anchor: int):
    tools = _Reader()

    def of(text: bytes | None) -> np.ndarray:
        words = text.split() if text else ()
        if len(words) < window:
            return np.empty(0, np.uint64)
        return _anchors(tools.hashes.of(words), tools.rolling, window, anchor)[1]

    return of


_PARSED = "rid long, doc_id long, n_words long, digest string, text binary, contexts array<struct<anchor: long, first: int, windows: binary>>"
_CONTEXT = pa.list_(pa.struct([("anchor", pa.int64()), ("first", pa.int32()), ("windows", pa.binary())]))


def _parse_batches(bitmap, window: int, anchor: int, bitmap_bits: int):
    """Documents without a repeated anchor are finished; the others keep text and contexts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from parsed(batches)
        finally:
            tidy(bitmap)

    def parsed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tools = _Reader()
        bits = np.frombuffer(bitmap.value, np.uint8)
        for batch in sliced(batches):
            counts, digests, texts, contexts = [], [], [], []
            for text in byte_texts(batch.column("text")):
                words = text.split() if text else []
                counts.append(len(words))
                found = None
                if len(words) >= window:
                    codes = tools.hashes.of(words)
                    places, hashes, owner = _anchors(codes, tools.rolling, window, anchor)
                    hit = np.flatnonzero(test_bits(bits, hashes, bitmap_bits))
                    if len(hit):
                        windows = tools.rolling.grams(codes, window, _WINDOW_SALT)
                        ends = np.searchsorted(owner, hit, "right")
                        starts = np.searchsorted(owner, hit, "left")
                        found = [{"anchor": a, "first": int(s), "windows": windows[s:e].tobytes()} for a, s, e in zip(hashes[hit].astype(np.int64).tolist(), starts, ends)]
                contexts.append(found)
                texts.append(text if found else None)
                digests.append(None if found else _digest(words))
            yield pa.RecordBatch.from_arrays([batch.column("rid"), batch.column("doc_id"), pa.array(counts, pa.int64()), pa.array(digests, pa.string()), pa.array(texts, pa.binary()), pa.array(contexts, _CONTEXT)], names=["rid", "doc_id", "n_words", "digest", "text", "contexts"])

    return run


def longest_elsewhere(symbols: np.ndarray, sizes: np.ndarray, copies: np.ndarray) -> np.ndarray:
    """For each place of the sequences (symbols end to end, lengths in sizes) how many symbols from there on also stand
    at some other place; a sequence that has copies holds all of itself at another place."""
    total, left = len(symbols), np.repeat(np.cumsum(sizes), sizes) - np.arange(len(symbols))
    ranks = [np.unique(symbols, return_inverse=True)[1]]
    reach = 1
    while reach < int(sizes.max(initial=0)):
        # rank of twice the length; what ends before is a rank of its own below all others
        ahead = np.where(left > reach, ranks[-1][np.minimum(np.arange(total) + reach, total - 1)] + 1, 0)
        ranks.append(np.unique(ranks[-1].astype(np.int64) * (total + 1) + ahead, return_inverse=True)[1])
        reach *= 2
    order = np.argsort(ranks[-1], kind="stable")
    # common prefix of neighbours in suffix order, from the longest doubled length down
    one, two = order[:-1], order[1:]
    shared = np.zeros(total - 1 if total else 0, np.int64)
    for level in range(len(ranks) - 1, -1, -1):
        step = 1 << level
        room = np.minimum(left[one], left[two]) - shared >= step
        a, b = np.minimum(one + shared, total - 1), np.minimum(two + shared, total - 1)
        shared += np.where(room & (ranks[level][a] == ranks[level][b]), step, 0)
    best = np.zeros(total, np.int64)
    best[one] = shared
    best[two] = np.maximum(best[two], shared)
    return np.where(np.repeat(copies, sizes) > 1, left, best)


def greedy_factors(longest: list[int]) -> list[tuple[int, int]]:
    """(start, length) of the factors of one sequence, given the longest match at each place."""
    found, at = [], 0
    while at < len(longest):
        if longest[at]:
            found.append((at, longest[at]))
        at += longest[at] or 1
    return found


#: Windows that a task indexes together; a block that has more is indexed alone.
BLOCK_WINDOWS = 50_000


def _block_factors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For rows sorted by anchor, one for each distinct context: its factors relative to the anchor's block, as packed
    (start, length) pairs of bytes. Several blocks are indexed at once; their symbols are kept apart by the anchor."""
    held: list[tuple[int, int, bytes, int]] = []
    size = 0

    def parse() -> pa.RecordBatch:
        sizes = np.array([len(w) // 8 for _, _, w, _ in held], np.int64)
        windows = np.frombuffer(b"".join(w for _, _, w, _ in held), np.uint64)
        anchors = np.repeat(np.array([a for a, _, _, _ in held], np.int64).view(np.uint64), sizes)
        with np.errstate(over="ignore"):
            symbols = windows + mix64(anchors)
        longest = longest_elsewhere(symbols, sizes, np.array([c for _, _, _, c in held], np.int64)).tolist()
        rows, at = [], 0
        for (anchor, ctx, _, _), n in zip(held, sizes.tolist()):
            found = greedy_factors(longest[at : at + n])
            if found:
                rows.append((anchor, ctx, np.array(found, np.uint16).tobytes()))
            at += n
        held.clear()
        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.binary())], names=["anchor", "context", "factors"])

    for batch in batches:
        for row in zip(*(batch.column(c).to_pylist() for c in ("anchor", "context", "windows", "copies"))):
            if size >= BLOCK_WINDOWS and row[0] != held[-1][0]:
                yield parse()
                size = 0
            held.append(row)
            size += len(row[2]) // 8
    if held:
        yield parse()
    tidy()


_FACTORED = "doc_id long, n_words long, n_removed long, kept_sha256 string, factors array<struct<start: int, length: int>>"
_FACTOR = pa.list_(pa.struct([("start", pa.int32()), ("length", pa.int32())]))


def _factor_batches(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            removed, digests, factors = [], [], []
            for text, digest, parts, n in zip(batch.column("text").to_pylist(), batch.column("digest").to_pylist(), batch.column("parts").to_pylist(), batch.column("n_words").to_pylist()):
                if not parts:
                    removed.append(0)
                    digests.append(digest if digest is not None else _digest(text.split()))
                    factors.append([])
                    continue
                words = text.split()
                pairs = np.frombuffer(b"".join(p["factors"] for p in parts), np.uint16).reshape(-1, 2).astype(np.int64)
                starts = pairs[:, 0] + np.repeat([p["first"] for p in parts], [len(p["factors"]) // 4 for p in parts])
                steps = np.zeros(n + 1, np.int32)
                np.add.at(steps, starts, 1)
                np.add.at(steps, starts + pairs[:, 1] + window - 1, -1)
                gone = np.cumsum(steps)[:n] > 0
                edges = np.flatnonzero(np.diff(np.concatenate(([False], gone, [False])).astype(np.int8)))
                factors.append([{"start": int(a), "length": int(b - a)} for a, b in zip(edges[::2], edges[1::2])])
                removed.append(int(gone.sum()))
                digests.append(_digest([w for w, g in zip(words, gone.tolist()) if not g]))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_words"), pa.array(removed, pa.int64()), pa.array(digests, pa.string()), pa.array(factors, _FACTOR)], names=["doc_id", "n_words", "n_removed", "kept_sha256", "factors"])
        tidy()

    return run


def duplicate_factors(docs: DataFrame, window: int = WINDOW, anchor: int = ANCHOR, bitmap_bits: int = BITMAP_BITS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 and the removed word spans (`factors`), one row per document.

    Shuffled are: two to four bytes per anchor for the bitmap; for documents with a repeated anchor their contexts, alike ones
    pre-aggregated; and their texts, once, to meet the factors. Only the bitmap, of fixed size, passes the driver.
    """
    spark = docs.sparkSession
    bounded_batches(spark)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    bitmap = spark.sparkContext.broadcast(repetition_bitmaps(slim, lambda: _anchor_hasher(window, anchor), bitmap_bits=bitmap_bits)[0])
    parsed = slim.withColumn("rid", F.monotonically_increasing_id()).select("rid", "doc_id", "text").mapInArrow(_parse_batches(bitmap, window, anchor, bitmap_bits), _PARSED)
    parsed = materialize(parsed, "dedup-parsed")
    places = parsed.filter(F.col("contexts").isNotNull()).select("rid", F.explode("contexts").alias("c")).select("rid", "c.anchor", "c.first", "c.windows", F.xxhash64("c.windows").alias("context"))
    classes = places.groupBy("anchor", "context").agg(F.min("windows").alias("windows"), F.count("*").alias("copies"))
    blocks = classes.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(_block_factors, "anchor long, context long, factors binary")
    parts = places.select("rid", "anchor", "context", "first").join(blocks, ["anchor", "context"]).groupBy("rid").agg(F.collect_list(F.struct("first", "factors")).alias("parts"))
    whole = parsed.select("rid", "doc_id", "n_words", "digest", "text")
    open_docs = whole.filter(F.col("text").isNotNull()).join(parts, "rid", "left")
    done = whole.filter(F.col("text").isNull()).withColumn("parts", F.lit(None).cast(parts.schema["parts"].dataType))
    cols = ["doc_id", "n_words", "digest", "text", "parts"]
    finish = _factor_batches(window)
    quick = done.select("doc_id", "n_words", F.lit(0).cast("long").alias("n_removed"), F.col("digest").alias("kept_sha256"), F.expr("cast(array() as array<struct<start: int, length: int>>)").alias("factors"))
    return quick.unionByName(open_docs.select(*cols).mapInArrow(finish, _FACTORED))


def dedup_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return duplicate_factors(read_table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_removed", "kept_sha256")


DEDUP_SQL = r"""
WITH w AS MATERIALIZED (
  SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
), win AS MATERIALIZED (
  SELECT doc_id, p, md5(array_to_string(ws[p : p + 34], ' ')) AS k
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 33)) AS p FROM w)
), hit AS (
  SELECT doc_id, p FROM win WHERE k IN (SELECT k FROM win GROUP BY k HAVING count(*) > 1)
), gone AS (
  SELECT DISTINCT doc_id, unnest(range(p, p + 35)) AS q FROM hit
), lists AS (
  SELECT doc_id, list(q) AS qs, count(*) AS n FROM gone GROUP BY doc_id
), words AS (
  SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS q FROM w
), kept AS (
  SELECT words.doc_id, string_agg(word, ' ' ORDER BY words.q) AS t
  FROM words ANTI JOIN gone ON words.doc_id = gone.doc_id AND words.q = gone.q GROUP BY words.doc_id
)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM w LEFT JOIN lists USING (doc_id) LEFT JOIN kept USING (doc_id)
"""
