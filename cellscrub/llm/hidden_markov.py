"""Hidden Markov language model: Baum-Welch over partitions, exact likelihood by the scaled forward recursion.

Counts of all training tokens are exact and stay in a table. The most frequent words (`lookup_words`, a fixed bound) are
also sent to the tasks; all other words meet their counts by a join. The model has `states` hidden states that emit the
end, one of the `emitted_words` most frequent words, or one of `shared_classes` classes, among which all other words are
dealt by a hash: Baum-Welch learns from every word, the rarer ones sharing what they teach with the few others of their
class. A word of a class has the smoothed share of its own count in it, and each class holds back the share of one type
never seen, so the model is a distribution over all words whatever the size of the vocabulary.

Each round of training adds up expected counts over whole training documents. Documents are cut into blocks of `SEGMENT`
tokens only to work on many at once: the blocks' transfer matrices carry the forward message into every block and the
backward message out of it, and the step from block to block is counted like any other. Training ends after `rounds`
rounds, or when the likelihood gains less than `tolerance` a token. Scoring multiplies the same transfer matrices in
order, which is the forward recursion over the whole document.

Defined results: a null or blank text is the end alone; a null id is held out; repeated rows are scored one by one and
each counts in training; without training rows every token is unseen; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellscrub.llm.common import bounded_batches, byte_texts, materialize, read_table, sliced, tidy

STATES = 4
ROUNDS = 4
EMITTED_WORDS = 8000
SHARED_CLASSES = 8192
LOOKUP_WORDS = 200_000
SEGMENT = 256
TOLERANCE = 1e-4
SMOOTH = 0.1
PRIOR = 20.0
HELD_OUT_OF = 10
END = b"\n"

_END, _FIRST = 0, 1


def held_out(doc_id: int | None) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % HELD_OUT_OF == 0


def _count_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    counts: Counter[bytes] = Counter()

    def drain() -> pa.RecordBatch:
        batch = pa.RecordBatch.from_arrays([pa.array(counts.keys(), pa.binary()), pa.array(counts.values(), pa.int64())], names=["word", "n"])
        counts.clear()
        return batch

    for batch in batches:
        for doc_id, text in zip(batch.column("doc_id").to_pylist(), byte_texts(batch.column("text"))):
            if not held_out(doc_id):
                counts.update((text or b"").lower().split())
                counts[END] += 1
        if len(counts) > 500_000:
            yield drain()
    if counts:
        yield drain()
    tidy()


def token_counts(docs: DataFrame) -> DataFrame:
    """word (bytes; the end is a newline), n: over all training rows; counted in each task before the shuffle."""
    return docs.mapInArrow(_count_batches, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))


def shared_class(word: bytes, classes: int) -> int:
    return zlib.crc32(word) % classes


@dataclass
class Vocabulary:
    """What the tasks know of the counts: the most frequent words with theirs, the smoothed counts of each shared class
    (of its words and one unseen type), and the totals. Class codes: the end, the shared classes, the emitted words."""

    words: list[bytes]
    counts: np.ndarray
    n_tokens: int
    n_types: int
    n_end: int
    emitted: int
    masses: np.ndarray

    @property
    def total(self) -> float:
        return self.n_tokens + SMOOTH * (self.n_types + 1)

    def class_shares(self) -> np.ndarray:
        shares = np.concatenate(([self.n_end + SMOOTH], self.masses, self.counts[: self.emitted] + SMOOTH))
        return shares / shares.sum()

    def codes(self) -> np.ndarray:
        """The code of each looked-up word."""
        own = np.arange(self.emitted) + _FIRST + len(self.masses)
        return np.concatenate((own, [shared_class(w, len(self.masses)) + _FIRST for w in self.words[self.emitted :]])).astype(np.int64)


def _vocabulary(counts: DataFrame, emitted: int, lookup: int, classes: int) -> Vocabulary:
    """The driver gets the totals, counts by size of count and by class (of fixed number), and `lookup` words at most."""
    if emitted + classes + _FIRST > 1 << 16:
        raise ValueError("more classes than a 16-bit code can tell apart")
    words = counts.filter(F.col("word") != F.lit(END))
    totals = counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.count("*").alias("v"), F.coalesce(F.max(F.when(F.col("word") == F.lit(END), F.col("n"))), F.lit(0)).alias("e")).first()
    size = F.floor(F.log2(F.col("n").cast("double")) * 16).cast("int")
    least, room = None, lookup
    for r in sorted(words.groupBy(size.alias("size")).count().collect(), key=lambda r: -r["size"]):
        room -= r["count"]
        if room < 0:
            break
        least = r["size"]
    top = words.filter(size >= least).toArrow().to_pydict() if least is not None else {"word": [], "n": []}
    ranked = sorted(zip(top["n"], top["word"]), key=lambda r: (-r[0], r[1]))
    names, sizes = [bytes(w) for _, w in ranked], np.array([n for n, _ in ranked], np.float64)
    masses = np.full(classes, SMOOTH)
    for r in words.groupBy((F.crc32("word") % classes).cast("int").alias("c")).agg(F.sum("n").alias("n"), F.count("*").alias("v")).collect():
        masses[r.c] += r.n + SMOOTH * r.v
    own = min(emitted, len(names))
    for w, n in zip(names[:own], sizes):
        masses[shared_class(w, classes)] -= n + SMOOTH
    return Vocabulary(names, sizes, totals.n, totals.v, totals.e, own, np.maximum(masses, SMOOTH))


_CODED = "doc_id long, held_out boolean, n_tokens long, n_known long, known_log double, share_log double, codes binary, others array<binary>"


def _code_batches(shared):
    """Per document: class codes (uint16), what the lookup words give, and the words to be looked up by the join.

    share_log: of all words of shared classes, less the class's smoothed count, and for looked-up ones with their own."""

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab: Vocabulary = shared.value
        get = {w: i for i, w in enumerate(vocab.words)}.get
        code_of, classes = vocab.codes(), len(vocab.masses)
        logs = np.log10(vocab.counts + SMOOTH)
        mass_logs = np.log10(vocab.masses)
        end_log = np.log10(vocab.n_end + SMOOTH)
        for batch in sliced(batches):
            rows: list[list] = [[] for _ in range(7)]
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), byte_texts(batch.column("text"))):
                words = (text or b"").lower().split()
                at = np.fromiter((get(w, -1) for w in words), np.int64, len(words))
                known = at >= 0
                others = [words[i] for i in np.flatnonzero(~known).tolist()]
                codes = np.zeros(len(words) + 1, np.int64)
                codes[:-1][known] = code_of[at[known]]
                codes[:-1][~known] = np.fromiter((zlib.crc32(w) % classes + _FIRST for w in others), np.int64, len(others))
                of_class = codes[(codes >= _FIRST) & (codes < _FIRST + classes)] - _FIRST
                share = float(logs[at[at >= vocab.emitted]].sum() - mass_logs[of_class].sum())
                out = held_out(doc_id), len(words) + 1, int(known.sum()) + (vocab.n_end > 0), float(logs[at[known]].sum() + end_log), share, codes.astype(np.uint16).tobytes(), others
                for column, value in zip(rows, out):
                    column.append(value)
            kinds = [pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.binary(), pa.list_(pa.binary())]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id")] + [pa.array(r, k) for r, k in zip(rows, kinds)], names=[f.split()[0] for f in _CODED.split(", ")])

    return _closing(coded, shared)


def _closing(work, *shared):
    """work over batches; what it held goes at the task's end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from work(batches)
        finally:
            tidy(*shared)

    return run


@dataclass
class Model:
    start: np.ndarray
    move: np.ndarray
    emit: np.ndarray

    @staticmethod
    def initial(shares: np.ndarray, states: int) -> Model:
        """The shares of the words, tilted differently in each state by a fixed hash; states tend to stay."""
        k = np.arange(len(shares), dtype=np.uint64)[None, :] * np.uint64(0x9E3779B97F4A7C15) + np.arange(1, states + 1, dtype=np.uint64)[:, None] * np.uint64(0xD1B54A32D192ED03)
        k = (k ^ (k >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        tilt = 0.3 + 1.4 * ((k >> np.uint64(40)).astype(np.float64) / 2**24)
        emit = shares[None, :] * tilt
        move = np.full((states, states), 0.08 / max(1, states - 1)) if states > 1 else np.ones((1, 1))
        if states > 1:
            np.fill_diagonal(move, 0.92)
        return Model(np.full(states, 1 / states), move, emit / emit.sum(1, keepdims=True))


@dataclass
class _Blocks:
    """Sequences in blocks, by (time, block) with the longest block first, and how they belong together."""

    grid: np.ndarray
    running: np.ndarray
    opening: np.ndarray
    #: For each sequence the columns of its blocks, in order.
    columns: list[np.ndarray]

    @staticmethod
    def of(sequences: list[np.ndarray], size: int) -> _Blocks:
        pieces, owner = [], []
        for i, s in enumerate(sequences):
            for at in range(0, len(s), size):
                pieces.append(s[at : at + size])
                owner.append(i)
        sizes = np.array([len(p) for p in pieces])
        order = np.argsort(-sizes, kind="stable")
        grid = np.zeros((sizes[order[0]], len(pieces)), np.uint16)
        for j, i in enumerate(order.tolist()):
            grid[: sizes[i], j] = pieces[i]
        at = np.empty(len(pieces), np.int64)
        at[order] = np.arange(len(pieces))
        first = np.diff(owner, prepend=-1) > 0
        return _Blocks(grid, np.searchsorted(-sizes[order], -np.arange(len(grid)), "left"), first[order], np.split(at, np.flatnonzero(first)[1:]))

    def by_depth(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """For each place in a sequence the sequences that reach it, and their columns there."""
        depth = np.array([len(c) for c in self.columns])
        padded = np.zeros((len(depth), int(depth.max())), np.int64)
        for i, c in enumerate(self.columns):
            padded[i, : len(c)] = c
        for d in range(padded.shape[1]):
            live = np.flatnonzero(depth > d)
            yield live, padded[live, d]


def _transfers(blocks: _Blocks, model: Model, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each wanted block the matrix from the state before it to that at its end, with its tokens emitted, and the
    log10 factor taken out of it; a sequence's first token follows no move. Other blocks keep the identity."""
    k = len(model.start)
    rows = np.ascontiguousarray(model.emit.T)
    transfer = np.broadcast_to(np.eye(k), (len(wanted), k, k)).copy()
    scale = np.zeros(len(wanted))
    picked = np.flatnonzero(wanted)
    if not len(picked):
        return transfer, scale
    running = np.searchsorted(picked, blocks.running, "left")
    part, part_scale, opening = transfer[picked], scale[picked], blocks.opening[picked]
    for t in range(len(blocks.grid)):
        n = running[t]
        if not n:
            break
        now = (part[:n].reshape(-1, k) @ model.move).reshape(n, k, k)
        if t == 0:
            now[opening] = np.eye(k)
        now *= rows[blocks.grid[t, picked[:n]]][:, None, :]
        if t % 8 == 7 or t == len(blocks.grid) - 1 or running[t + 1] != n:
            top = now.max((1, 2))
            part_scale[:n] += np.log10(top)
            now /= top[:, None, None]
        part[:n] = now
    transfer[picked], scale[picked] = part, part_scale
    return transfer, scale


def expected_counts(sequences: list[np.ndarray], model: Model, block: int = SEGMENT) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
    """Baum-Welch sums (start, move, emit by class) over whole sequences, and their log10 likelihood."""
    blocks = _Blocks.of(sequences, block)
    grid, running = blocks.grid, blocks.running
    steps, width = grid.shape
    k = len(model.start)
    rows = np.ascontiguousarray(model.emit.T)
    several = np.zeros(width, bool)
    for c in blocks.columns:
        several[c] = len(c) > 1
    transfer, _ = _transfers(blocks, model, several)
    # messages into each block from before it, and out of its end from behind it
    before, behind = np.tile(model.start, (width, 1)), np.ones((width, k))
    levels = list(blocks.by_depth())
    steps_on = [(here[np.searchsorted(those, live)], following) for (those, here), (live, following) in zip(levels, levels[1:])]
    for came, following in steps_on:
        state = np.einsum("nj,njk->nk", before[came], transfer[came])
        before[following] = state / state.sum(1, keepdims=True)
    for came, following in reversed(steps_on):
        message = np.einsum("njk,nk->nj", transfer[following], behind[following])
        behind[came] = message / message.max(1, keepdims=True)
    alpha = np.zeros((steps, width, k))
    scale = np.ones((steps, width))
    last = np.zeros((width, k))
    now = np.where(blocks.opening[:, None], before, before @ model.move) * rows[grid[0]]
    for t in range(steps):
        n = running[t]
        if t:
            now = (now[:n] @ model.move) * rows[grid[t, :n]]
        scale[t, :n] = now.sum(1)
        now = now / scale[t, :n, None]
        alpha[t, :n] = last[:n] = now
    beta = behind / (last * behind).sum(1, keepdims=True)
    move, emit = np.zeros((k, k)), np.zeros((model.emit.shape[1], k))
    for t in range(steps - 1, -1, -1):
        n = running[t]
        gamma = alpha[t, :n] * beta[:n]
        alpha[t, :n] = gamma / gamma.sum(1, keepdims=True)
        if t:
            ahead = rows[grid[t, :n]] * beta[:n] / scale[t, :n, None]
            move += model.move * (alpha[t - 1, :n].T @ ahead)
            beta[:n] = ahead @ model.move.T
    inner = ~blocks.opening
    if inner.any():
        ahead = rows[grid[0, inner]] * beta[inner] / scale[0, inner, None]
        move += model.move * (before[inner].T @ ahead)
    start = alpha[0, blocks.opening].sum(0)
    mask = np.arange(width)[None, :] < running[:, None]
    codes = grid[mask]
    for s in range(k):
        emit[:, s] = np.bincount(codes, weights=alpha[:, :, s][mask], minlength=len(emit))
    return start, move, emit, float(np.log10(scale).sum())


def log_likelihoods(sequences: list[np.ndarray], model: Model, block: int = SEGMENT) -> np.ndarray:
    """log10 likelihood of each whole sequence of codes."""
    blocks = _Blocks.of(sequences, block)
    transfer, scale = _transfers(blocks, model, np.ones(blocks.grid.shape[1], bool))
    out = np.zeros(len(sequences))
    state = np.tile(model.start, (len(sequences), 1))
    for live, columns in blocks.by_depth():
        state[live] = np.einsum("nj,njk->nk", state[live], transfer[columns])
        total = state[live].sum(1)
        out[live] += np.log10(total) + scale[columns]
        state[live] /= total[:, None]
    return out


def _batched(codes: list[bytes], budget: int = 400_000) -> Iterator[list[np.ndarray]]:
    held, size = [], 0
    for c in codes:
        held.append(np.frombuffer(c, np.uint16))
        size += len(held[-1])
        if size > budget:
            yield held
            held, size = [], 0
    if held:
        yield held


def _training_batches(shared):
    def sums_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model: Model = shared.value
        sums = None
        for batch in batches:
            for sequences in _batched(batch.column("codes").to_pylist()):
                got = expected_counts(sequences, model)
                sums = got if sums is None else tuple(a + b for a, b in zip(sums, got))
        if sums is not None:
            flat = np.concatenate([sums[0], sums[1].ravel(), sums[2].ravel(), [sums[3]]])
            at = np.flatnonzero(flat)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(flat[at])], names=["place", "value"])

    return _closing(sums_of, shared)


def train(coded: DataFrame, shares: np.ndarray, states: int = STATES, rounds: int = ROUNDS, tolerance: float = TOLERANCE) -> tuple[Model, list[float]]:
    """The model and the training likelihood (log10 a token) before each round; the driver gets the summed counts, of
    fixed size."""
    spark = coded.sparkSession
    model, history, m = Model.initial(shares, states), [], len(shares)
    for _ in range(rounds):
        shared = spark.sparkContext.broadcast(model)
        sums = coded.filter("NOT held_out").select("codes").mapInArrow(_training_batches(shared), "place long, value double").groupBy("place").agg(F.sum("value").alias("value")).toArrow()
        shared.unpersist()
        if not sums.num_rows:
            break
        flat = np.zeros(states + states * states + m * states + 1)
        flat[np.array(sums.column("place"))] = np.array(sums.column("value"))
        start, move = flat[:states] + 1, flat[states : states + states * states].reshape(states, states) + 1
        counts = flat[states + states * states : -1].reshape(m, states).T
        emit = counts + PRIOR * shares[None, :]
        history.append(float(flat[-1] / counts.sum()))
        model = Model(start / start.sum(), move / move.sum(1, keepdims=True), emit / emit.sum(1, keepdims=True))
        if len(history) > 1 and history[-1] - history[-2] < tolerance:
            break
    return model, history


def _scoring_batches(shared):
    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model: Model = shared.value
        for batch in batches:
            parts = [log_likelihoods(s, model) for s in _batched(batch.column("codes").to_pylist())]
            logs = np.concatenate(parts) if parts else np.empty(0)
            names = [n for n in batch.schema.names if n != "codes"]
            yield pa.RecordBatch.from_arrays([batch.column(n) for n in names] + [pa.array(logs)], names=names + ["class_log"])

    return _closing(scored, shared)


def score_documents(docs: DataFrame, states: int = STATES, rounds: int = ROUNDS, emitted_words: int = EMITTED_WORDS, lookup_words: int = LOOKUP_WORDS, shared_classes: int = SHARED_CLASSES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score; one row per input row."""
    spark = docs.sparkSession
    bounded_batches(spark)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    counts = materialize(token_counts(slim), "lm-counts")
    vocab = _vocabulary(counts, emitted_words, lookup_words, shared_classes)
    shared = spark.sparkContext.broadcast(vocab)
    coded = materialize(slim.mapInArrow(_code_batches(shared), _CODED).withColumn("rid", F.monotonically_increasing_id()), "lm-coded")
    shared.unpersist()
    others = coded.select("rid", F.explode("others").alias("word")).join(counts.withColumnRenamed("n", "c"), "word", "left")
    looked_up = others.groupBy("rid").agg(F.count("c").alias("o_known"), F.sum(F.log10(F.coalesce("c", F.lit(0)) + SMOOTH)).alias("o_log"))
    model, _ = train(coded, vocab.class_shares(), states, rounds)
    slim_codes = coded.select("rid", "doc_id", "held_out", "n_tokens", "n_known", "known_log", "share_log", "codes")
    scored = slim_codes.mapInArrow(_scoring_batches(spark.sparkContext.broadcast(model)), "rid long, doc_id long, held_out boolean, n_tokens long, n_known long, known_log double, share_log double, class_log double")
    both = scored.join(looked_up, "rid", "left")
    other_log = F.coalesce("o_log", F.lit(0.0))
    return both.select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("n_known") + F.coalesce("o_known", F.lit(0))).alias("n_known"),
        F.lit(vocab.n_tokens).cast("long").alias("train_tokens"),
        (F.col("known_log") + other_log - F.col("n_tokens") * float(np.log10(vocab.total))).alias("base_score"),
        (F.col("class_log") + F.col("share_log") + other_log).alias("score"),
    )


def language_model_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(read_table(spark, sf_dir, "documents"))
