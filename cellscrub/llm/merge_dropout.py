"""SentencePiece BPE encoding with seeded merge-dropout, and lossless decoding.

A text is cut into units that no merge can cross (a run of spaces with the word after it, or a newline). Within a unit
an agenda holds the candidate merges by vocabulary score, leftmost first on ties; a candidate that comes up is skipped
for good with the dropout rate's chance. Every occurrence of a unit draws for itself: a keyed hash of (seed, document id,
place of the unit) gives the numbers of candidates taken between two skips (geometric, which is the same as one draw a
candidate), so any rerun of a task repeats the draws exactly. What is remembered is a tree of segmentations by unit and
numbers drawn so far; an occurrence walks down it and only what nobody has drawn before is segmented anew.
Characters outside the vocabulary, and literal U+2581, become byte tokens, which keeps decoding lossless.

Defined results: a null text stays null in ids and in the decoded text; an empty text has no ids; a null id counts as
document 0; repeated rows get equal ids; rows are independent, so an empty table gives an empty result. All other
columns pass through, but for one named like the output column, which is replaced.
"""

from __future__ import annotations

import heapq
import os
import re
import struct
from collections.abc import Iterator
from itertools import accumulate, chain, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cellscrub.llm.common import bounded_batches, read_table, sliced, tidy

DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"
DROPOUT = 0.1
SEED = 17
CACHE_BOUND = 300_000

_MASK = (1 << 64) - 1
_STEP = 0x9E3779B97F4A7C15
_GAPS = 1024
_CACHED = 64
_SPACE = "▁"
_UNIT = re.compile(r" +[^ \n]*|[^ \n]+|\n")


def _mixed(x: np.ndarray) -> np.ndarray:
    """Well spread 64-bit values of 64-bit values."""
    with np.errstate(over="ignore"):
        x = (x ^ x >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ x >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
        return x ^ x >> np.uint64(31)


class Codec:
    """A BPE vocabulary with byte fallback, read from the bytes of a SentencePiece model file."""

    def __init__(self, model: bytes, dropout: float = DROPOUT, seed: int = SEED, cache_bound: int = CACHE_BOUND):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_proto=model)
        self.dropout, self.seed = dropout, seed
        # a draw below ladder[-k] takes k candidates at least before the next skip
        chances = [(1 - dropout) ** k for k in range(1, _GAPS + 1)] if dropout > 0 else []
        self.ladder = np.array([min(int(c * 2**64), _MASK) for c in reversed(chances)], np.uint64)
        self.score: dict[str, float] = {}
        self.id_of: dict[str, int] = {}
        self.byte_ids = [0] * 256
        self.piece_bytes: list[bytes] = []
        for i in range(sp.get_piece_size()):
            piece = sp.id_to_piece(i)
            if sp.is_byte(i):
                self.byte_ids[int(piece[3:5], 16)] = i
                self.piece_bytes.append(bytes([int(piece[3:5], 16)]))
            elif sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i):
                self.piece_bytes.append(b"")
            else:
                self.score[piece] = sp.get_score(i)
                self.id_of[piece] = i
                self.piece_bytes.append(piece.replace(_SPACE, " ").encode())
        self.cache_bound = cache_bound
        self.forget()
        self.pairs: tuple | None = None
        self.char_table = np.full(0x110000, -1, np.int32)
        for p, i in self.id_of.items():
            if len(p) == 1:
                self.char_table[ord(" " if p == _SPACE else p)] = i
        self.code = np.dtype("<u2" if sp.get_piece_size() <= 65536 else "<u4")

    def _drawn(self, keys: np.ndarray, draw: int) -> np.ndarray:
        with np.errstate(over="ignore"):
            return _mixed(keys + np.uint64((draw + 1) * 0xC2B2AE3D27D4EB4F & _MASK))

    def _gaps(self, keys: np.ndarray, draw: int) -> np.ndarray:
        """Candidates taken before the skip of that number, by occurrence; _GAPS means so many and no skip yet."""
        return len(self.ladder) - np.searchsorted(self.ladder, self._drawn(keys, draw), "right")

    def _skips(self, keys: np.ndarray, draw: int, traces: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which occurrences skip one of so many candidates, and those's gaps: one comparison tells the others apart."""
        drawn = self._drawn(keys, draw)
        hit = (traces > 0) & (self.ladder[np.minimum(len(self.ladder) - traces, len(self.ladder) - 1)] <= drawn)
        return hit, len(self.ladder) - np.searchsorted(self.ladder, drawn[hit], "right")

    def segment(self, unit: str, key: int) -> list[int]:
        """Ids of one unit under an occurrence's key; unit's spaces are plain spaces."""
        draws = np.array([key], np.uint64)
        return self._segment(unit, (int(self._gaps(draws, i)[0]) for i in range(1 << 60)) if len(self.ladder) else iter(()))[0]

    def _segment(self, unit: str, gaps: Iterator[int]) -> tuple[list[int], int]:
        """Ids of one unit, and how many candidates came up after the last skip."""
        piece = [_SPACE if c == " " else "" if c == _SPACE else c for c in unit]
        n = len(piece)
        after = list(range(1, n + 1))
        before = list(range(-1, n - 1))
        score = self.score.get
        push, pop = heapq.heappush, heapq.heappop
        agenda = []
        for i in range(n - 1):
            rank = score(piece[i] + piece[i + 1])
            if rank is not None and piece[i] and piece[i + 1]:
                agenda.append((-rank, i, i + 2))
        heapq.heapify(agenda)
        gap = togo = next(gaps, _GAPS)
        taken = 0
        while agenda:
            _, left, end = pop(agenda)
            right = after[left] if piece[left] else n
            # stale if either side has grown or gone since
            if right >= n or after[right] != end:
                continue
            while togo == 0 and gap == _GAPS:
                gap = togo = next(gaps, _GAPS)
            if togo == 0:
                gap = togo = next(gaps, _GAPS)
                taken = 0
                continue
            togo -= 1
            taken += 1
            piece[left] += piece[right]
            piece[right] = None
            after[left] = end
            at = before[left]
            if at >= 0 and piece[at]:
                rank = score(piece[at] + piece[left])
                if rank is not None:
                    push(agenda, (-rank, at, end))
            if end < n:
                before[end] = left
                if piece[end]:
                    rank = score(piece[left] + piece[end])
                    if rank is not None:
                        push(agenda, (-rank, left, after[end]))
        ids: list[int] = []
        id_of = self.id_of
        at = 0
        while at < n:
            found = id_of.get(piece[at])
            if found is not None:
                ids.append(found)
            else:
                ids += [self.byte_ids[b] for b in (piece[at] or _SPACE).encode()]
            at = after[at]
        return ids, taken

    def _pair_table(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Sorted keys left * 2**32 + right of all joinable pieces, with the joined id and its rank (low is early)."""
        if self.pairs is None:
            rows = []
            for piece, i in self.id_of.items():
                for cut in range(1, len(piece)):
                    left, right = self.id_of.get(piece[:cut]), self.id_of.get(piece[cut:])
                    if left is not None and right is not None:
                        rows.append((left << 32 | right, i, -self.score[piece]))
            rows.sort()
            self.pairs = np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows], np.int32), np.array([r[2] for r in rows], np.float64)
        return self.pairs

    def _joined(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Joined ids and ranks; rank is infinite where the two are no piece."""
        keys, ids, ranks = self._pair_table()
        want = left.astype(np.int64) << 32 | right.astype(np.int64)
        at = np.minimum(np.searchsorted(keys, want), len(keys) - 1)
        good = (keys[at] == want) & (left >= 0) & (right >= 0)
        return ids[at], np.where(good, ranks[at], np.inf)

    def segment_many(self, units: list[tuple[str, int]]) -> list[bytes]:
        """`segment` of many (unit, key), packed."""
        return self._walk([u for u, _ in units], np.fromiter((k for _, k in units), np.uint64, len(units)))

    def _walk(self, units: list[str], keys: np.ndarray) -> list[bytes]:
        """Packed ids of every occurrence: from its unit down the tree, one level a skip."""
        at = np.fromiter(map(self.units.get, units, repeat(-1)), np.int64, len(units))
        new = [units[k] for k in np.flatnonzero(at < 0).tolist()]
        fresh = [u for u in dict.fromkeys(new) if len(u) <= _CACHED]
        if fresh:
            first = self._grow(fresh, np.zeros((len(fresh), 0), np.int64))
            self.units.update(zip(fresh, range(first, first + len(fresh))))
        if new:
            at[at < 0] = np.fromiter(map(self.units.get, new, repeat(-1)), np.int64, len(new))
        visits = [at[at >= 0]]
        live = np.flatnonzero(at >= 0) if len(self.ladder) else np.zeros(0, np.int64)
        draw = 0
        while len(live):
            hit, gap = self._skips(keys[live], draw, self.traces[at[live]])
            live = live[hit]
            child = at[live] * _GAPS + gap
            found = np.fromiter(map(self.children.get, child.tolist(), repeat(-1)), np.int64, len(child))
            gone = np.flatnonzero(found < 0)
            if len(gone):
                fresh_keys, sample, back = np.unique(child[gone], return_index=True, return_inverse=True)
                who = live[gone[sample]]
                path = np.stack([self._gaps(keys[who], i) for i in range(draw + 1)], 1)
                first = self._grow([units[k] for k in who.tolist()], path)
                self.children.update(zip(fresh_keys.tolist(), range(first, first + len(who))))
                found[gone] = first + back
            at[live] = found
            visits.append(found)
            draw += 1
        out = list(map(self.packed.__getitem__, at.tolist())) if len(self.packed) else [b""] * len(units)
        for k in np.flatnonzero(at < 0).tolist():
            out[k] = np.array(self.segment(units[k], int(keys[k])), self.code).tobytes()
        self.used = np.concatenate((self.used, np.zeros(len(self.packed) - len(self.used), np.int64)))
        self.used += np.bincount(np.concatenate(visits), minlength=len(self.used))
        if len(self.packed) > self.cache_bound:
            self._prune()
        return out

    def _grow(self, units: list[str], path: np.ndarray) -> int:
        """Adds nodes for units after the skips of path (gaps by column); the first one's number."""
        first = len(self.packed)
        packed, traces = self._segment_paths(units, path)
        self.packed += packed
        self.traces = np.concatenate((self.traces, traces))
        return first

    def _prune(self) -> None:
        """Keep what was used twice since the last time (with a node goes all below it), or nothing if that is too much."""
        kept = self.used >= 2
        if np.count_nonzero(kept) > self.cache_bound // 2:
            self.forget()
            return
        number = (np.cumsum(kept) - 1).tolist()
        stays = kept.tolist()
        self.units = {u: number[i] for u, i in self.units.items() if stays[i]}
        self.children = {number[k // _GAPS] * _GAPS + k % _GAPS: number[i] for k, i in self.children.items() if stays[i]}
        self.packed = [p for p, s in zip(self.packed, stays) if s]
        self.traces = self.traces[kept]
        self.used = np.zeros(len(self.packed), np.int64)

    def _segment_paths(self, units: list[str], path: np.ndarray) -> tuple[list[bytes], np.ndarray]:
        """Packed ids and candidates after the last skip: each step takes the first agenda entry of every unit at once.

        Units whose characters are not all pieces of their own, and very long ones, take the plain way.
        """
        out: list[bytes] = [b""] * len(units)
        traces = np.zeros(len(units), np.int16)
        sizes = np.fromiter(map(len, units), np.int64, len(units))
        codes = np.frombuffer("".join(units).encode("utf-32-le"), np.uint32)
        ids = self.char_table[codes]
        starts = np.cumsum(sizes) - sizes
        plain = (np.minimum.reduceat(ids, starts) < 0) | (sizes > 40)
        for k in np.flatnonzero(plain).tolist():
            found, traces[k] = self._segment(units[k], iter(path[k].tolist()))
            out[k] = np.array(found, self.code).tobytes()
        short = np.flatnonzero(~plain)
        short = short[np.argsort(sizes[short], kind="stable")]
        for at in range(0, len(short), 8192):
            part = short[at : at + 8192]
            traces[part] = self._segment_block(path[part], sizes[part], ids, starts[part], part.tolist(), out)
        return out, traces

    def _segment_block(self, path: np.ndarray, sizes: np.ndarray, ids: np.ndarray, starts: np.ndarray, places: list[int], out: list[bytes]) -> np.ndarray:
        n, width = len(sizes), int(sizes[-1]) + 1
        step = np.arange(width)[None, :]
        piece = np.where(step < sizes[:, None], ids[np.minimum(starts[:, None] + step, len(ids) - 1)], -1).astype(np.int32)
        after = np.tile(np.arange(1, width + 1, dtype=np.int32), (n, 1))
        before = np.tile(np.arange(-1, width - 1, dtype=np.int32), (n, 1))
        joined = np.full((n, width), -1, np.int32)
        rank = np.full((n, width), np.inf)
        joined[:, :-1], rank[:, :-1] = self._joined(piece[:, :-1], piece[:, 1:])
        path = np.concatenate((path, np.full((n, 1), _GAPS)), 1)
        skips, togo, taken = np.zeros(n, np.int64), path[:, 0].copy(), np.zeros(n, np.int16)
        live = np.flatnonzero(np.isfinite(rank).any(1))
        while len(live):
            best = rank[live].argmin(1)
            more = np.isfinite(rank[live, best])
            live, best = live[more], best[more]
            if not len(live):
                break
            right = after[live, best]
            end = after[live, right]
            skip = togo[live] == 0
            dropped = live[skip]
            rank[dropped, best[skip]] = np.inf
            skips[dropped] += 1
            togo[dropped] = path[dropped, skips[dropped]]
            taken[dropped] = 0
            rows, left, right, end = live[~skip], best[~skip], right[~skip], end[~skip]
            togo[rows] -= 1
            taken[rows] += 1
            piece[rows, left] = joined[rows, left]
            piece[rows, right] = -1
            rank[rows, right] = np.inf
            after[rows, left] = end
            inside = end < sizes[rows]
            before[rows[inside], end[inside]] = left[inside]
            following = np.where(inside, piece[rows, np.minimum(end, width - 1)], -1)
            joined[rows, left], rank[rows, left] = self._joined(piece[rows, left], following)
            ahead = before[rows, left]
            some = ahead >= 0
            r, p = rows[some], ahead[some]
            joined[r, p], rank[r, p] = self._joined(piece[r, p], piece[r, left[some]])
        kept = piece >= 0
        flat, ends = piece[kept].astype(self.code), np.cumsum(kept.sum(1))
        data, step, last = flat.tobytes(), self.code.itemsize, 0
        for k, e in zip(places, ends.tolist()):
            out[k] = data[last * step : e * step]
            last = e
        return taken

    def encode(self, text: str, doc_id: int = 0) -> bytes:
        """Ids of a whole text, packed as little-endian uint16 (uint32 for vocabularies over 65,536 pieces)."""
        return self.encode_many([text], [doc_id])[0]

    def encode_many(self, texts: list[str | None], doc_ids: list[int | None]) -> list[bytes | None]:
        """`encode` of several texts."""
        cut = [_UNIT.findall(" " + t) if t else [] for t in texts]
        sizes = np.fromiter(map(len, cut), np.int64, len(cut))
        ends = list(accumulate(sizes.tolist()))
        drawn = np.fromiter((xxhash.xxh3_64_intdigest(struct.pack("<qI", d or 0, self.seed & 0xFFFFFFFF)) for d in doc_ids), np.uint64, len(cut))
        place = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        with np.errstate(over="ignore"):
            keys = _mixed(np.repeat(drawn, sizes) + place.astype(np.uint64) * np.uint64(_STEP))
        packed = self._walk(list(chain.from_iterable(cut)), keys)
        return [None if t is None else b"".join(packed[e - len(c) : e]) for t, c, e in zip(texts, cut, ends)]

    def forget(self) -> None:
        """Drop the tree; workers outlive their tasks and share the executor's memory with others."""
        # nodes by number: segmentation, candidates after the last skip, visits; roots by unit, others by parent and gap
        self.packed: list[bytes] = []
        self.traces, self.used = np.zeros(0, np.int16), np.zeros(0, np.int64)
        self.units: dict[str, int] = {}
        self.children: dict[int, int] = {}

    def decode(self, packed: bytes) -> str:
        table = self.piece_bytes
        data = b"".join([table[i] for i in np.frombuffer(packed, self.code).tolist()])
        return data[1:].decode() if data else ""


_codecs: dict[tuple, Codec] = {}


def _codec(model: bytes, dropout: float, seed: int) -> Codec:
    key = (xxhash.xxh3_64_intdigest(model), dropout, seed)
    if key not in _codecs:
        _codecs[key] = Codec(model, dropout, seed)
    return _codecs[key]


def _model_bytes(path: str) -> bytes:
    """A public vocabulary file of about half a megabyte, read on the driver and shipped with the tasks."""
    if not os.path.isfile(path):
        raise FileNotFoundError(f"no SentencePiece model at {path}; pass model_path")
    with open(path, "rb") as f:
        return f.read()


def _appended(df: DataFrame, name: str, kind: T.DataType) -> T.StructType:
    return T.StructType([f for f in df.schema.fields if f.name != name] + [T.StructField(name, kind)])


def _replaced(batch: pa.RecordBatch, name: str, values: pa.Array) -> pa.RecordBatch:
    kept = [i for i, n in enumerate(batch.schema.names) if n != name]
    return pa.RecordBatch.from_arrays([batch.column(i) for i in kept] + [values], names=[batch.schema.names[i] for i in kept] + [name])


def encode_documents(docs: DataFrame, model_path: str = DEFAULT_MODEL, dropout: float = DROPOUT, seed: int = SEED, text_col: str = "text", id_col: str = "doc_id", out_col: str = "piece_ids") -> DataFrame:
    """docs with out_col: packed ids as in Codec.encode (`unpack_ids` gives an array column); no shuffle."""
    model = _model_bytes(model_path)
    bounded_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(model, dropout, seed)
        try:
            for batch in sliced(batches, text_col, rows=1000, budget=2_000_000):
                out = codec.encode_many(batch.column(text_col).to_pylist(), batch.column(id_col).cast(pa.int64()).to_pylist())
                yield _replaced(batch, out_col, pa.array(out, pa.binary()))
        finally:
            codec.forget()
            tidy()

    return docs.mapInArrow(run, _appended(docs, out_col, T.BinaryType()))


def decode_documents(encoded: DataFrame, model_path: str = DEFAULT_MODEL, ids_col: str = "piece_ids", out_col: str = "decoded") -> DataFrame:
    """encoded with out_col: the exact text that the ids stand for, whatever the dropout was."""
    model = _model_bytes(model_path)
    bounded_batches(encoded.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(model, 0.0, 0)
        try:
            for batch in sliced(batches, ids_col):
                out = [None if b is None else codec.decode(b) for b in batch.column(ids_col).to_pylist()]
                yield _replaced(batch, out_col, pa.array(out, pa.string()))
        finally:
            tidy()

    return encoded.mapInArrow(run, _appended(encoded, out_col, T.StringType()))


def unpack_ids(packed, width: int = 2):
    """Array column of ids from a packed column of that many bytes an id, with built-in functions only."""
    word = lambda i: F.conv(F.hex(F.reverse(F.substring(packed, i * width + 1, width))), 16, 10).cast("int")
    return F.when(F.octet_length(packed) > 0, F.transform(F.sequence(F.lit(0), (F.octet_length(packed) / width - 1).cast("int")), word)).when(packed.isNotNull(), F.array().cast("array<int>"))


def merge_dropout_query(spark: SparkSession, sf_dir: str, model_path: str = DEFAULT_MODEL) -> DataFrame:
    """Per document: token count and digest of the sampled segmentation, and the digest of the text decoded from it."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    coded = encode_documents(docs, model_path).withColumn("text_sha256", F.sha2(F.encode("text", "utf-8"), 256)).drop("text")
    both = decode_documents(coded, model_path)
    width = Codec(_model_bytes(model_path)).code.itemsize
    decoded = F.sha2(F.encode("decoded", "utf-8"), 256)
    return both.select("doc_id", F.floor(F.octet_length("piece_ids") / width).alias("n_tokens"), F.sha2("piece_ids", 256).alias("ids_sha256"), decoded.alias("decoded_sha256"), decoded.eqNullSafe(F.col("text_sha256")).alias("lossless"))
