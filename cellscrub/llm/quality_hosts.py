"""Quality rules with host-level verdicts.

Per document exact text statistics decide which base rules it fails: too short, or too repetitive. Failures of each rule
are summed by host. Every rule has an empirical beta prior (method of moments over the host rates), and a host's counts
turn it into a posterior: the mean is the host's shrunk failure rate. A host is rejected, with all its documents, when for
some rule the posterior mean less two standard deviations passes `host_limit`, so neither a few bad documents of a small
host nor a rate that is merely above the others' is enough.

Defined results: a null or blank text has no words and fails the base rules; a null host is never pooled or rejected;
an empty table gives an empty result; repeated rows are judged one by one and each counts for its host; other columns
of the input are ignored here and kept by `filter_documents`.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellscrub.llm.common import bounded_batches, byte_texts, fresh, materialize, read_table, tidy

MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20
NGRAM = 5
HOST_LIMIT = 0.5
DEVIATIONS = 2.0

_SYMBOLS = b"#*$%&|<>"
_NOT_SYMBOLS = bytes(b for b in range(256) if b not in _SYMBOLS)
_CONTINUATION = bytes(range(0x80, 0xC0))
_HAS_WORD = re.compile(rb"[^\x20\x09-\x0D]")

RULES = ("too_short", "too_repetitive")

STATS_SCHEMA = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long"


def repeated_words(words: list[bytes], n: int = NGRAM) -> int:
    """How many words lie in an n-word window that occurs twice or more in the same text."""
    if len(words) <= n:
        return 0
    grams = list(zip(*(words[i:] for i in range(n))))
    counts = Counter(grams)
    if len(counts) == len(grams):
        return 0
    steps = np.zeros(len(words) + 1, np.int32)
    starts = np.flatnonzero(np.fromiter((counts[g] > 1 for g in grams), bool, len(grams)))
    np.add.at(steps, starts, 1)
    np.add.at(steps, starts + n, -1)
    return int(np.count_nonzero(np.cumsum(steps[:-1])))


def text_stats(text: bytes | None) -> tuple[int, int, int, int, int]:
    if not text:
        return 0, 0, 0, 0, 0
    words = text.split()
    joined = b"".join(words)
    lines = text.split(b"\n")
    if len(lines) > 1:
        seen: set[bytes] = set()
        dup = 0
        for line in lines:
            if line in seen:
                dup += 1
            elif _HAS_WORD.search(line):
                seen.add(line)
    else:
        dup = 0
    return len(words), len(joined.translate(None, _CONTINUATION)), len(text.translate(None, _NOT_SYMBOLS)), dup, repeated_words(words)


def _stats_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = [field.split()[0] for field in STATS_SCHEMA.split(", ")]
    for batch in batches:
        rows = np.array([text_stats(t) for t in byte_texts(batch.column("text"))], np.int64).reshape(-1, 5)
        kept = [batch.column(i) for i in range(batch.num_columns) if batch.schema.names[i] != "text"]
        yield pa.RecordBatch.from_arrays(kept + [pa.array(rows[:, i]) for i in range(5)], names=[n for n in batch.schema.names if n != "text"] + names)
    tidy()


def document_stats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """doc_id, host, the five statistics, a flag for each rule and base_failed; one scan, no shuffle."""
    bounded_batches(docs.sparkSession)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(host_col).cast("string").alias("host"), F.col(text_col).cast("string").alias("text"))
    stats = slim.mapInArrow(_stats_batches, f"doc_id long, host string, {STATS_SCHEMA}")
    flagged = stats.withColumn("too_short", F.col("n_words") < MIN_WORDS).withColumn("too_repetitive", 100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    return flagged.withColumn("base_failed", F.col("too_short") | F.col("too_repetitive"))


def beta_prior(mean: float | None, variance: float | None) -> tuple[float, float]:
    """Mean and weight of the beta prior over host rates: m(1-m)/v - 1, and 1 where the variance leaves none."""
    m, v = mean or 0.0, variance or 0.0
    return m, m * (1 - m) / v - 1 if 0 < v < m * (1 - m) else 1.0


def host_verdicts(stats: DataFrame, host_limit: float = HOST_LIMIT) -> DataFrame:
    """host, host_docs, failures and shrunk rate by rule, host_rate (the highest), host_rejected; the priors come from one
    aggregate over hosts, two numbers a rule."""
    failures = [F.sum(F.col(r).cast("long")).alias(f"{r}_failures") for r in RULES]
    hosts = materialize(stats.filter(F.col("host").isNotNull()).groupBy("host").agg(F.count("*").alias("host_docs"), *failures), "quality-host-sums")
    rate = {r: F.col(f"{r}_failures") / F.col("host_docs") for r in RULES}
    told = hosts.agg(*[f(rate[r]).alias(f"{r}_{k}") for r in RULES for k, f in (("m", F.avg), ("v", F.var_pop))]).first()
    lows = []
    for r in RULES:
        m, weight = beta_prior(told[f"{r}_m"], told[f"{r}_v"])
        size = F.col("host_docs") + weight
        mean = (F.col(f"{r}_failures") + m * weight) / size
        hosts = hosts.withColumn(f"{r}_rate", mean)
        lows.append(mean - DEVIATIONS * F.sqrt(mean * (1 - mean) / (size + 1)))
    highest = F.greatest(*[f"{r}_rate" for r in RULES])
    return hosts.select("*", F.round(highest, 6).alias("host_rate"), (F.greatest(*lows) > host_limit).alias("host_rejected"))


def judge(docs: DataFrame, host_limit: float = HOST_LIMIT, **columns: str) -> DataFrame:
    """doc_id, host, statistics, base_failed, host_rate and the final verdict `kept`; one row per input row.

    The statistics are written once. Hosts are summed with map-side combine, so a host with a third of all rows is one
    row per task; Spark broadcasts the written verdicts only below its size threshold and otherwise shuffles, where
    adaptive execution splits the hot host.
    """
    stats = materialize(document_stats(docs, **columns), "quality-stats")
    verdicts = materialize(host_verdicts(stats, host_limit), "quality-hosts")
    joined = stats.join(verdicts.select("host", "host_rate", "host_rejected"), "host", "left")
    return joined.withColumn("kept", ~F.col("base_failed") & ~F.coalesce(F.col("host_rejected"), F.lit(False)))


def filter_documents(docs: DataFrame, host_limit: float = HOST_LIMIT, text_col: str = "text", host_col: str = "source") -> DataFrame:
    """The rows of docs, with all their columns, whose own text and host pass."""
    bounded_batches(docs.sparkSession)
    stats = document_stats(docs.select(F.lit(0).alias("i"), F.col(text_col).alias("t"), F.col(host_col).alias("h")), "i", "t", "h")
    host = fresh(docs, "__host")
    rejected = materialize(host_verdicts(stats, host_limit).filter("host_rejected").select(F.col("host").alias(host)), "quality-rejected")

    def passing(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = (text_stats(t) for t in byte_texts(batch.column(text_col)))
            yield batch.filter(pa.array([s[0] >= MIN_WORDS and 100 * s[4] <= MAX_REPEAT_PERCENT * s[0] for s in found], pa.bool_()))
        tidy()

    return docs.mapInArrow(passing, docs.schema).join(rejected, F.col(host_col).cast("string") == F.col(host), "left_anti")


def quality_query(spark, sf_dir: str) -> DataFrame:
    out = judge(read_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "host_rate")


QUALITY_SQL = r"""
WITH t AS (
  SELECT doc_id, source, coalesce(text, '') AS text, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
), lines AS (
  SELECT doc_id, sum(n - 1) AS dup FROM (SELECT doc_id, line, count(*) AS n FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM t) WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY ALL) GROUP BY doc_id
), grams AS (
  SELECT doc_id, p, array_to_string(ws[p : p + 4], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 3)) AS p FROM t)
), again AS (
  SELECT doc_id, count(DISTINCT q) AS rep FROM (
    SELECT doc_id, unnest(range(p, p + 5)) AS q FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS n FROM grams) WHERE n > 1
  ) GROUP BY doc_id
), stats AS (
  SELECT t.doc_id, source, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
    CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(coalesce(dup, 0) AS BIGINT) AS n_dup_lines, CAST(coalesce(rep, 0) AS BIGINT) AS n_repeat_words
  FROM t LEFT JOIN lines USING (doc_id) LEFT JOIN again USING (doc_id)
), judged AS (
  SELECT *, n_words < 10 AS short, 100 * n_repeat_words > 20 * n_words AS repetitive FROM stats
), hosts AS (
  SELECT source, count(*) AS n, count(*) FILTER (short) AS fs, count(*) FILTER (repetitive) AS fr FROM judged WHERE source IS NOT NULL GROUP BY source
), rates AS (
  SELECT source, n, f, rule, avg(f / n) OVER (PARTITION BY rule) AS m, var_pop(f / n) OVER (PARTITION BY rule) AS v
  FROM (SELECT source, n, fs AS f, 1 AS rule FROM hosts UNION ALL SELECT source, n, fr, 2 FROM hosts)
), shrunk AS (
  SELECT source, n + w AS size, (f + m * w) / (n + w) AS r FROM (SELECT *, CASE WHEN v > 0 AND m * (1 - m) > v THEN m * (1 - m) / v - 1 ELSE 1.0 END AS w FROM rates)
), verdicts AS (
  SELECT source, max(r) AS r, max(r - 2 * sqrt(r * (1 - r) / (size + 1))) AS low FROM shrunk GROUP BY source
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, short OR repetitive AS base_failed, NOT (short OR repetitive) AND NOT coalesce(low > 0.5, false) AS kept, round(r, 6) AS host_rate
FROM judged LEFT JOIN verdicts USING (source)
"""
