"""Toxicity of deobfuscated text: a noisy channel under a character language model, then a lexical classifier.

One scan counts letter trigrams of all documents and, of the labelled training rows, in how many texts of either class
each word stands. Words that speak for toxicity form the lexicon; the character model is an even mixture of corpus and
lexicon. Places that look disguised (letters next to digits or symbols, single letters a few separators
apart, letters three times over, words that are a lexicon word but for doubled letters) become a lattice in which symbols
stand for letters, separators and repeats can vanish; its best path over all states is found by Viterbi decoding. A place that
ends in symbols is decoded with and without them. The classifier is a logistic regression on a document's lexicon hits, restored ones included.

At most `label_bound` labelled rows are used (those with the smallest hash), one per text; all else covers all rows.

The lexicon holds at most LEXICON_BOUND words, the strongest; it comes from the bounded labelled sample alone.

Defined results: null, blank and wordless texts score like any text without hits; repeated rows get equal scores; rows
with a null id are held out; unlabelled rows are scored alike; without training labels every score is the prior's;
an empty table gives an empty result; other columns are never read.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellscrub.llm.common import bounded_batches, byte_texts, read_table, tidy

LABEL_BOUND = 200_000
FIT_BOUND = 100_000
LEXICON_BOUND = 20_000
LEAST_TEXTS = 3
LEAST_LOG_ODDS = 2.0
HELD_OUT_OF = 5

# What a symbol may stand for.
LEET = {"0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "*": "abcdefghijklmnopqrstuvwxyz"}
SEPARATORS = " .-_,/'~"
_SYMBOLS = b"@$!|+*"
_EDGES = b".,;:?\"'()[]{}#%&<>="

_LETTER, _LEET, _SPACE, _OTHER = 1, 2, 3, 0
_CLASS = np.zeros(256, np.uint8)
_CLASS[[*range(65, 91), *range(97, 123)]] = _LETTER
_CLASS[[ord(c) for c in LEET]] = _LEET
_CLASS[[9, 10, 11, 12, 13, 32]] = _SPACE
_LETTER_CODE = np.zeros(256, np.int64)
_LETTER_CODE[97:123] = _LETTER_CODE[65:91] = np.arange(1, 27)
_WORDS = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 97 <= c <= 122 else 32 for c in range(256))
_GAP = rb"(?:[ ._-]{1,3}|\*)"
_SPACED = re.compile(rb"(?<![^\s])(?:[A-Za-z0-9@$!|*]" + _GAP + rb"){2,}[A-Za-z0-9@$!|*](?![^\s.,;:!?])")
_INNER = re.compile(rb"(?<![A-Za-z0-9])(?:[A-Za-z0-9@$!|*](?:[._-]{1,3}|\*)){2,}[A-Za-z0-9@$!|*](?![A-Za-z0-9])")
_REPEAT = re.compile(rb"([a-z])\1+")


def held_out(doc_id: int | None) -> bool:
    return doc_id is None or zlib.crc32(str(doc_id).encode()) % HELD_OUT_OF == 0


def plain_words(text: bytes) -> list[bytes]:
    return text.translate(_WORDS).split()


def disguised(text: bytes) -> list[bytes]:
    """The places of a text that may hide a word, each whole."""
    raw = np.frombuffer(text, np.uint8)
    kinds = _CLASS[raw]
    found = []
    if len(raw) > 1:
        mixed = kinds[:-1] + kinds[1:] == _LETTER + _LEET
        mixed &= (kinds[:-1] == _LETTER) | (kinds[:-1] == _LEET)
        marks = np.flatnonzero(mixed)
        if len(raw) > 2:
            letters = _LETTER_CODE[raw]
            triple = (letters[:-2] > 0) & (letters[:-2] == letters[1:-1]) & (letters[1:-1] == letters[2:])
            if triple.any():
                marks = np.union1d(marks, np.flatnonzero(triple))
        if len(marks):
            spaces = np.flatnonzero(kinds == _SPACE)
            left = np.unique(np.searchsorted(spaces, marks))
            starts = np.concatenate(([0], spaces + 1))[left]
            ends = np.concatenate((spaces, [len(raw)]))[left]
            for a, b in zip(starts.tolist(), ends.tolist()):
                token = text[a:b].strip(_EDGES)
                bare = token.rstrip(_SYMBOLS + _EDGES)
                found += {t for t in (token, bare) if t}
        lone = (kinds[1:-1] != _SPACE) & (kinds[:-2] == _SPACE) & (kinds[2:] == _SPACE) if len(raw) > 2 else np.zeros(0, bool)
        if np.count_nonzero(lone) >= 2:
            found += _SPACED.findall(text)
        if b"-" in text or b"." in text or b"_" in text or b"*" in text:
            inner = (kinds[1:-1] == _OTHER) | (raw[1:-1] == 42)
            near = inner & ((kinds[:-2] == _LETTER) | (kinds[:-2] == _LEET)) & ((kinds[2:] == _LETTER) | (kinds[2:] == _LEET))
            if np.count_nonzero(near) >= 2:
                found += _INNER.findall(text)
    return found


_EVERY = np.arange(729)


@dataclass
class CharacterModel:
    """Interpolated letter trigrams; 0 is the edge of a word."""

    trigrams: np.ndarray
    cache: dict = field(default_factory=dict)
    scores: list = field(default_factory=list)
    plain: list = field(default_factory=list)

    def __post_init__(self):
        # by what is written next; an edge that follows an edge is free
        self.scores = [np.ascontiguousarray(self.trigrams[:, :, o]) for o in range(27)]
        self.scores[0] = self.scores[0].copy()
        self.scores[0][:, 0] = 0.0
        self.plain = [m.tolist() for m in self.scores]

    @staticmethod
    def mixture(corpus: np.ndarray, words: list[bytes], weight: float = 0.5) -> CharacterModel:
        own = np.zeros(27**3)
        for w in words:
            codes = np.concatenate(([0, 0], _LETTER_CODE[np.frombuffer(w, np.uint8)], [0]))
            np.add.at(own, codes[:-2] * 729 + codes[1:-1] * 27 + codes[2:], 1)
        parts = [(x / x.sum(), w) for x, w in ((corpus.astype(np.float64), 1 - weight), (own, weight)) if x.sum()]
        total = sum(x * w for x, w in parts) / sum(w for _, w in parts) if parts else np.ones(27**3) / 27**3
        cube = total.reshape(27, 27, 27)
        one = cube.sum((0, 1)) + 1e-6
        two = cube.sum(0) + 1e-4 * one[None, :]
        one /= one.sum()
        two = two / two.sum(1, keepdims=True)
        rows = cube.sum(2, keepdims=True)
        three = np.where(rows > 0, cube / np.maximum(rows, 1e-300), two[None])
        return CharacterModel(np.log(0.7 * three + 0.25 * two[None] + 0.05 * one[None, None]).astype(np.float32))

    def restore(self, place: bytes) -> list[bytes]:
        """The words on the best path through the lattice of one place."""
        found = self.cache.get(place)
        if found is None:
            if len(self.cache) > 100_000:
                self.cache.clear()
            found = self.cache[place] = self._viterbi(place.lower().decode("utf-8", "replace"))
        return found

    @staticmethod
    def options(text: str, i: int) -> list[tuple[int, float]]:
        """What the character at i may have been written for (0 an edge, -1 nothing, else a letter), and its cost."""
        c = text[i]
        options: list[tuple[int, float]] = []
        if "a" <= c <= "z":
            options.append((ord(c) - 96, 0.0))
            if i and text[i - 1] == c:
                # a double letter is common, three in a row are not
                options.append((-1, 0.4 if text[max(0, i - 2) : i] == c + c or text[i + 1 : i + 2] == c else 2.5))
        elif c in LEET:
            options += [(ord(x) - 96, 1.0 + 0.5 * math.log(len(LEET[c]))) for x in LEET[c]]
            options.append((0, 4.0))
            if c in "*!|" or i and text[i - 1] == c:
                options.append((-1, 1.0))
        elif c in SEPARATORS:
            options += [(-1, 0.7), (0, 0.7)]
        else:
            options.append((0, 0.0))
        return options

    def _viterbi(self, text: str) -> list[bytes]:
        """Best path over all states (the two letters before); an edge after an edge costs nothing more."""
        return self._over_matrix(text) if "*" in text else self._over_states(text)

    def _over_states(self, text: str) -> list[bytes]:
        """For places without a character that may be any letter: few states are alive at a time."""
        score = self.plain
        best: dict[tuple[int, int], float] = {(0, 0): 0.0}
        back: list[dict] = []
        for i in range(len(text)):
            now: dict[tuple[int, int], float] = {}
            trace: dict = {}
            options = self.options(text, i)
            for state, value in best.items():
                for out, cost in options:
                    if out == -1:
                        to, total = state, value - cost
                    elif out == 0:
                        to, total = (0, 0), value - cost + score[0][state[0]][state[1]]
                    else:
                        to, total = (state[1], out), value - cost + score[out][state[0]][state[1]]
                    if to not in now or total > now[to]:
                        now[to] = total
                        trace[to] = state, out
            best = now
            back.append(trace)
        state = max(best, key=lambda s: best[s] + score[0][s[0]][s[1]])
        out = []
        for trace in reversed(back):
            state, letter = trace[state]
            if letter != -1:
                out.append(" " if letter == 0 else chr(96 + letter))
        return "".join(reversed(out)).encode().split()

    def _over_matrix(self, text: str) -> list[bytes]:
        score = self.scores
        best = np.full((27, 27), -np.inf, np.float32)
        best[0, 0] = 0.0
        back = []
        for i in range(len(text)):
            now, came, wrote = np.full(729, -np.inf, np.float32), np.zeros(729, np.int32), np.zeros(729, np.int8)

            def offer(places, values, origins, out, now=now, came=came, wrote=wrote):
                better = values > now[places]
                at = places[better]
                now[at], came[at], wrote[at] = values[better], origins[better], out[better] if isinstance(out, np.ndarray) else out

            letters = []
            for out, cost in self.options(text, i):
                if out == -1:
                    offer(_EVERY, best.ravel() - cost, _EVERY, out)
                elif out == 0:
                    whole = (best + score[0]).ravel()
                    top = int(whole.argmax())
                    offer(_EVERY[:1], whole[top : top + 1] - cost, _EVERY[top : top + 1], out)
                else:
                    letters.append((out, cost))
            if letters:
                # all letters of a character cost the same
                written = slice(1, 27) if len(letters) == 26 else [o for o, _ in letters]
                through = best[:, :, None] + self.trigrams[:, :, written]
                first = through.argmax(0)
                values = np.take_along_axis(through, first[None], 0)[0] - letters[0][1]
                names = _EVERY[1:27] if len(letters) == 26 else np.array(written)
                offer((_EVERY[:27, None] * 27 + names).ravel(), values.ravel(), (first * 27 + _EVERY[:27, None]).ravel(), np.broadcast_to(names, values.shape).ravel())
            best = now.reshape(27, 27)
            back.append((came, wrote))
        state = int((best + score[0]).argmax())
        out = []
        for came, wrote in reversed(back):
            if wrote[state] != -1:
                out.append(" " if wrote[state] == 0 else chr(96 + wrote[state]))
            state = came[state]
        return "".join(reversed(out)).encode().split()


def _profile_batches(labels):
    """Letter trigrams of every document as one row of counts a task, and (word, toxic texts, other texts)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        toxic = labels.value
        trigrams = np.zeros(27**3, np.int64)
        words: dict[bytes, list[int]] = {}
        for batch in batches:
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), byte_texts(batch.column("text"))):
                if not text:
                    continue
                codes = _LETTER_CODE[np.frombuffer(text, np.uint8)]
                codes = np.concatenate(([0, 0], codes, [0]))
                keep = (codes[1:-1] > 0) | (codes[2:] > 0)
                trigrams += np.bincount((codes[:-2] * 729 + codes[1:-1] * 27 + codes[2:])[keep], minlength=27**3)
                label = toxic.get(doc_id)
                if label is not None:
                    for w in set(plain_words(text)):
                        words.setdefault(w, [0, 0])[label] += 1
            if len(words) > 400_000:
                yield _profile_rows(words, None)
                words = {}
        yield _profile_rows(words, trigrams)
        del toxic, words
        tidy(labels)

    return run


def _profile_rows(words: dict, trigrams: np.ndarray | None) -> pa.RecordBatch:
    rows = [(w, n[1], n[0]) for w, n in words.items()]
    if trigrams is not None:
        at = np.flatnonzero(trigrams)
        rows += [(b"\x00%d" % i, int(trigrams[i]), 0) for i in at.tolist()]
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.binary()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.int64())], names=["word", "yes", "no"])


@dataclass
class Detector:
    lexicon: dict[bytes, float]
    characters: CharacterModel
    weights: np.ndarray | None = None
    squeezed: set = field(default_factory=set)
    unstretched: set = field(default_factory=set)

    def __post_init__(self):
        self.squeezed = {_REPEAT.sub(rb"\1", w) for w in self.lexicon}

    def stretched(self, words: set[bytes]) -> list[bytes]:
        """Those words that are some lexicon word but for letters that stand several times."""
        found = []
        for w in words - self.unstretched:
            short = _REPEAT.sub(rb"\1", w)
            if short != w and short in self.squeezed and w not in self.lexicon:
                found.append(w)
            else:
                self.unstretched.add(w)
        if len(self.unstretched) > 100_000:
            self.unstretched.clear()
        return found

    def features(self, text: bytes | None) -> list[float]:
        if not text:
            return [0.0, 0.0, 0.0, 0.0, 0.0]
        get = self.lexicon.get
        words = plain_words(text)
        hits = {w: s for w in words if (s := get(w)) is not None}
        times = sum(1 for w in words if w in hits) if hits else 0
        for place in [*disguised(text), *self.stretched(set(words))]:
            for w in self.characters.restore(place):
                s = get(w)
                if s is not None:
                    times += w not in hits
                    hits[w] = s
        total = sum(hits.values())
        return [min(total, 20.0), float(bool(hits)), min(len(hits), 5.0), max(hits.values(), default=0.0), times / (len(words) + 20.0) * 20]

    def probability(self, features: np.ndarray) -> np.ndarray:
        with_bias = np.hstack([np.ones((len(features), 1)), features])
        return 1 / (1 + np.exp(-np.clip(with_bias @ self.weights, -30, 30)))


def _feature_batches(shared, labels):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        detector, toxic = shared.value, labels.value
        for batch in batches:
            rows = [(toxic[d], detector.features(t)) for d, t in zip(batch.column("doc_id").to_pylist(), byte_texts(batch.column("text"))) if d in toxic]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.list_(pa.float64()))], names=["toxic", "features"])
        del detector, toxic
        tidy(shared, labels)

    return run


def _score_batches(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        detector = shared.value
        for batch in batches:
            ids = batch.column("doc_id").to_pylist()
            features = np.array([detector.features(t) for t in byte_texts(batch.column("text"))], np.float64).reshape(-1, 5)
            chance = detector.probability(features)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([held_out(d) for d in ids], pa.bool_()), pa.array(chance), pa.array((chance >= 0.5).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])
        del detector
        tidy(shared)

    return run


def _logistic(x: np.ndarray, y: np.ndarray, decay: float = 1.0, rounds: int = 30) -> np.ndarray:
    """Newton steps; the decay keeps separable data finite."""
    x = np.hstack([np.ones((len(x), 1)), x])
    w = np.zeros(x.shape[1])
    penalty = np.full(x.shape[1], decay)
    penalty[0] = 1e-3
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (y - p) - penalty * w
        hess = (x * (p * (1 - p))[:, None]).T @ x + np.diag(penalty)
        step = np.linalg.solve(hess, grad)
        w = w + step
        if np.abs(step).max() < 1e-8:
            break
    return w


def training_labels(docs: DataFrame, labels: DataFrame, bound: int = LABEL_BOUND) -> dict[int, int]:
    """doc_id to label of at most `bound` training rows, one per text."""
    rule = F.crc32(F.col("doc_id").cast("string").cast("binary")) % HELD_OUT_OF != 0
    known = labels.filter(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & rule).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)
    keys = docs.select("doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("t"))
    one = keys.join(known, "doc_id").groupBy("t").agg(F.min(F.struct("doc_id", "toxic")).alias("r")).select("r.doc_id", "r.toxic").toArrow()
    return dict(zip(one.column("doc_id").to_pylist(), [int(x > 0) for x in one.column("toxic").to_pylist()]))


def train(docs: DataFrame, labels: DataFrame, label_bound: int = LABEL_BOUND, fit_bound: int = FIT_BOUND) -> Detector:
    spark = docs.sparkSession
    toxic = training_labels(docs, labels, label_bound)
    shared_labels = spark.sparkContext.broadcast(toxic)
    n_yes = sum(toxic.values())
    n_no = len(toxic) - n_yes
    profile = docs.mapInArrow(_profile_batches(shared_labels), "word binary, yes long, no long").groupBy("word").agg(F.sum("yes").alias("yes"), F.sum("no").alias("no"))
    odds = F.log((F.col("yes") + 0.1) / (n_yes + 0.2)) - F.log((F.col("no") + 0.5) / (n_no + 1.0))
    is_count = F.substring("word", 1, 1) == F.lit(b"\x00")
    strong = profile.filter(is_count | (F.col("yes") >= LEAST_TEXTS) & (odds >= LEAST_LOG_ODDS)).withColumn("odds", F.when(~is_count, odds))
    rows = strong.orderBy(F.desc_nulls_first("odds"), "word").limit(LEXICON_BOUND + 27**3).toArrow()
    corpus, lexicon = np.zeros(27**3), {}
    for word, yes, score in zip(*(rows.column(c).to_pylist() for c in ("word", "yes", "odds"))):
        if score is None:
            corpus[int(word[1:])] = yes
        elif len(lexicon) < LEXICON_BOUND:
            lexicon[bytes(word)] = score
    ascii_words = [w for w in lexicon if all(97 <= b <= 122 for b in w)]
    detector = Detector(lexicon, CharacterModel.mixture(corpus, ascii_words))
    used = toxic if len(toxic) <= fit_bound else dict(sorted(toxic.items(), key=lambda r: zlib.crc32(str(r[0]).encode()))[:fit_bound])
    data = docs.mapInArrow(_feature_batches(spark.sparkContext.broadcast(detector), spark.sparkContext.broadcast(used)), "toxic int, features array<double>").toArrow()
    if data.num_rows:
        detector.weights = _logistic(np.array(data.column("features").to_pylist()), np.array(data.column("toxic").to_pylist(), np.float64))
    else:
        detector.weights = np.array([-2.0, 0, 0, 0, 0, 0])
    return detector


def score_documents(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", **bounds: int) -> DataFrame:
    """doc_id, held_out, score, predicted; one row per input row."""
    bounded_batches(docs.sparkSession)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    detector = train(slim, labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")), **bounds)
    shared = docs.sparkSession.sparkContext.broadcast(detector)
    return slim.mapInArrow(_score_batches(shared), "doc_id long, held_out boolean, score double, predicted int")


def toxicity_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels"))
