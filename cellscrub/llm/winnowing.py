"""Benchmark decontamination by winnowing, with built-in functions only.

Documents and benchmark items are cut into words. Of each 10-word window the least of its six 5-gram hashes is its
fingerprint, so two equal windows have equal fingerprints wherever they stand. Fingerprints of documents meet those of
the items; documents that share one are read again, their windows with a shared fingerprint are extended to the ten
words and compared as text. Items of fewer than ten words are one window of their own length, fingerprinted whole.

The items' fingerprints are broadcast only while their number is within `broadcast_limit`; beyond it the same join is
shuffled. Defined results: a null text has no words; repeated rows (same id and text) get equal results; a null id or
item id is a value like any other (a null item id counts as a hit but has no place in the items' list); empty tables give
no hits; other columns are ignored, and kept by `clean_documents`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cellscrub.llm.common import ascii_lower, fresh, materialize, read_table

WINDOW = 10
GRAM = 5
BROADCAST_LIMIT = 500_000
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    return F.filter(F.split(ascii_lower(F.coalesce(text, F.lit(""))), SEPARATORS), lambda w: w != "")


def _pairs(a: Column, b: Column, shift: int, combine) -> Column:
    """combine(a[i], b[i + shift]); what stands past the end is cut off by the caller."""
    return F.zip_with(a, F.slice(b, shift + 1, F.greatest(F.size(b) - shift, F.lit(0))), lambda x, y: combine(x, y))


def _cut(a: Column, words: Column, width: int) -> Column:
    return F.slice(a, 1, F.greatest(F.size(words) - (width - 1), F.lit(0)))


def _salted(hashes: Column, width: int) -> Column:
    return F.transform(hashes, lambda h: F.xxhash64(h, F.lit(width)))


def _spots(prints: str, width: int) -> Column:
    return F.transform(prints, lambda h, i: F.struct((i + 1).alias("place"), F.lit(width).alias("width"), h.alias("fp")))


def _with_grams(df: DataFrame, words: str, widths: list[int]) -> DataFrame:
    """Columns g{k} with the hash of the k words from each place on; built by doubling, each with one pass."""
    have = {1}
    df = df.withColumn("g1", F.transform(words, lambda w: F.xxhash64(w)))
    for width in sorted(widths):
        done = 0
        for bit in (8, 4, 2, 1):
            if not (width - done) & bit or bit > width - done:
                continue
            for step in (2, 4, 8):
                if step <= bit and step not in have:
                    half = step // 2
                    df = df.withColumn(f"g{step}", _pairs(F.col(f"g{half}"), F.col(f"g{half}"), half, F.xxhash64))
                    have.add(step)
            if done and done + bit not in have:
                df = df.withColumn(f"g{done + bit}", _pairs(F.col(f"g{done}"), F.col(f"g{bit}"), done, F.xxhash64))
                have.add(done + bit)
            done += bit
    return df


def _fingerprints(df: DataFrame, words: str, short: list[int], window: int, gram: int) -> DataFrame:
    """df with `fp{window}`, for each window its least gram hash, and `fp{m}` for each short length."""
    df = _with_grams(df, words, [gram, *short])
    least, have = F.col(f"g{gram}"), 1
    span = window - gram + 1
    while have < span:
        step = min(have, span - have)
        df = df.withColumn(f"m{have + step}", _pairs(least, least, step, F.least))
        have += step
        least = F.col(f"m{have}")
    out = df.withColumn(f"fp{window}", _cut(least, F.col(words), window))
    for m in short:
        out = out.withColumn(f"fp{m}", _salted(_cut(F.col(f"g{m}"), F.col(words), m), m))
    return out


def _windows(df: DataFrame, words: str, keys: list[str], short: list[int], window: int) -> DataFrame:
    """keys, words, place (from 1), width and fingerprint of every window."""
    spots = F.flatten(F.array(*[_spots(f"fp{m}", m) for m in [window, *short]]))
    return df.select(*keys, words, F.explode(spots).alias("s")).select(*keys, words, "s.place", "s.width", "s.fp")


def item_windows(benchmark: DataFrame, window: int = WINDOW, gram: int = GRAM, id_col: str = "item_id", text_col: str = "text") -> tuple[DataFrame, list[int]]:
    """item_id, fp, width and words (one string) of each item's windows; and the short items' lengths, nine at most."""
    items = benchmark.select(F.col(id_col).cast("string").alias("item_id"), words_of(F.col(text_col).cast("string")).alias("words"))
    sized = items.filter(F.size("words") > 0)
    short = sorted(r.n for r in sized.filter(F.size("words") < window).select(F.size("words").alias("n")).distinct().collect())
    every = _windows(_fingerprints(sized, "words", short, window, gram), "words", ["item_id"], short, window)
    own = every.filter((F.size("words") >= window) & (F.col("width") == window) | (F.size("words") == F.col("width")))
    return materialize(own.select("item_id", "fp", "width", F.array_join(F.slice("words", F.col("place"), F.col("width")), " ").alias("words")), "bench-windows"), short


def hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, gram: int = GRAM, broadcast_limit: int = BROADCAST_LIMIT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_key, place, width, item_id: every occurrence of an item's window in a document, once per document."""
    items, short = item_windows(benchmark, window, gram)
    prints = materialize(items.select("fp").distinct(), "bench-prints")
    if prints.count() <= broadcast_limit:
        prints = F.broadcast(prints)
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text).alias("text_key"), text.alias("t"))
    marked = _fingerprints(slim.select("doc_id", "text_key", words_of(F.col("t")).alias("words")), "words", short, window, gram)
    distinct = F.array_distinct(F.flatten(F.array(*[F.col(f"fp{m}") for m in [window, *short]])))
    suspects = materialize(marked.select("doc_id", "text_key", F.explode(distinct).alias("fp")).join(prints, "fp", "left_semi").select("doc_id", "text_key").distinct(), "bench-suspects")
    same = F.col("d.doc_id").eqNullSafe(F.col("s.doc_id")) & (F.col("d.text_key") == F.col("s.text_key"))
    again = slim.alias("d").join(suspects.alias("s"), same, "left_semi").dropDuplicates(["doc_id", "text_key"])
    cut = _fingerprints(again.select("doc_id", "text_key", words_of(F.col("t")).alias("words")), "words", short, window, gram)
    spots = _windows(cut, "words", ["doc_id", "text_key"], short, window).join(prints, "fp", "left_semi")
    spots = spots.select("doc_id", "text_key", "place", "width", "fp", F.array_join(F.slice("words", F.col("place"), F.col("width")), " ").alias("words"))
    return spots.join(items, ["fp", "width", "words"]).select("doc_id", "text_key", "place", "width", "item_id")


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, gram: int = GRAM, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_key, n_words, n_hit, n_items, items_sha256, contaminated; one row per input row."""
    found = materialize(hits(docs, benchmark, window, gram, id_col=id_col, text_col=text_col), "bench-hits")
    covered = found.select("doc_id", "text_key", F.explode(F.sequence("place", F.col("place") + F.col("width") - 1)).alias("w")).distinct().groupBy("doc_id", "text_key").agg(F.count("*").alias("n_hit"))
    named = found.select("doc_id", "text_key", "item_id").distinct().groupBy("doc_id", "text_key").agg(F.count("*").alias("n_items"), F.sha2(F.array_join(F.array_sort(F.collect_list("item_id")), ",").cast("binary"), 256).alias("items_sha256"))
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text).alias("text_key"), F.size(words_of(text)).cast("long").alias("n_words")).alias("d")
    both = covered.alias("c").join(named.alias("n"), F.col("c.doc_id").eqNullSafe(F.col("n.doc_id")) & (F.col("c.text_key") == F.col("n.text_key"))).select(F.col("c.doc_id").alias("hit_id"), F.col("c.text_key").alias("hit_key"), "n_hit", "n_items", "items_sha256")
    out = base.join(materialize(both, "bench-totals"), F.col("d.doc_id").eqNullSafe(F.col("hit_id")) & (F.col("d.text_key") == F.col("hit_key")), "left")
    none = F.sha2(F.lit("").cast("binary"), 256)
    return out.select("doc_id", "text_key", "n_words", F.coalesce("n_hit", F.lit(0)).alias("n_hit"), F.coalesce("n_items", F.lit(0)).alias("n_items"), F.coalesce("items_sha256", none).alias("items_sha256"), (F.coalesce("n_hit", F.lit(0)) > 0).alias("contaminated"))


def clean_documents(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs, all columns, in which no window of an item occurs."""
    own, hashed = fresh(docs, "__id"), fresh(docs, "__key")
    dirty = materialize(hits(docs, benchmark, id_col=id_col, text_col=text_col).select(F.col("doc_id").alias(own), F.col("text_key").alias(hashed)).distinct(), "bench-dirty")
    key = F.xxhash64(F.coalesce(docs[text_col].cast("string"), F.lit("")))
    return docs.join(dirty, docs[id_col].cast("long").eqNullSafe(F.col(own)) & (key == F.col(hashed)), "left_anti")


def decontamination_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "benchmark")).drop("text_key")


DECONTAMINATION_SQL = r"""
WITH low AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS ws FROM documents
), it AS (
  SELECT CAST(item_id AS VARCHAR) AS item_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS ws FROM benchmark
), iw AS MATERIALIZED (
  SELECT DISTINCT item_id, least(len(ws), 10) AS m, array_to_string(ws[p : p + least(len(ws), 10) - 1], ' ') AS k
  FROM (SELECT item_id, ws, unnest(range(1, greatest(len(ws) - 8, 2))) AS p FROM it WHERE len(ws) > 0)
), sizes AS (
  SELECT DISTINCT m FROM iw
), dw AS (
  SELECT doc_id, p, m, array_to_string(ws[p : p + m - 1], ' ') AS k FROM (SELECT doc_id, ws, m, unnest(range(1, len(ws) - m + 2)) AS p FROM low, sizes WHERE len(ws) >= m)
), hit AS MATERIALIZED (
  SELECT doc_id, p, dw.m, item_id FROM dw JOIN iw ON dw.m = iw.m AND dw.k = iw.k
), cov AS (
  SELECT doc_id, count(DISTINCT q) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + m)) AS q FROM hit) GROUP BY doc_id
), named AS (
  SELECT doc_id, count(*) AS n_items, sha256(string_agg(item_id, ',' ORDER BY item_id)) AS items_sha256 FROM (SELECT DISTINCT doc_id, item_id FROM hit) GROUP BY doc_id
)
SELECT low.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  coalesce(items_sha256, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM low LEFT JOIN cov USING (doc_id) LEFT JOIN named USING (doc_id)
"""
