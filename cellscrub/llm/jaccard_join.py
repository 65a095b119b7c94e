"""Jaccard similarity join on 5-word shingles by T-occurrence search with DivideSkip.

Two documents link when 100 * |intersection| >= 80 * |union| of their shingle sets. Equal sets are one node from the
start. Shingles have one global order (rarer class first, then hash), and linked sets must share a shingle in their
first n - ceil(0.8 n) + 1 ones; shingles that occur once are dropped from these prefixes, and texts of whose shingles
not 80 % occur elsewhere are left out. The nodes that share a prefix shingle have a hub, the least of them; a group is a
hub with all nodes that share some prefix shingle of which it is the hub. So every pair that may link is in one group at
least, and a group never reaches beyond its hub's neighbours, however long the chains of neighbours get.

A group with at most `group_budget` shingles in its sets is one task: the inverted lists of the sets seen so far are
searched, short lists merged by a heap, the long ones only probed for the candidates that come out; a set is compared with
one representative of each component first and with the other members of a component only if that fails. A larger group
is first compared with its hub, salted over many tasks; what links with the hub needs no further comparison among itself. The rest
is dealt into chunks, and every pair of chunks, and every chunk with each chunk of the linked ones, is a task, so no
task holds more than the budget (or two sets, where they are larger). Only verified links become edges of components.

Defined results: null and blank texts have no shingles, link with nothing and are their own component; repeated rows
and equal texts share a component; a null id never becomes a component id unless its component has no other; an empty
table gives an empty result; other columns are ignored (kept by `keep_representatives`).
"""

from __future__ import annotations

import heapq
from bisect import bisect_left
from collections.abc import Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellscrub.llm.common import RollingHash, WordHashes, bounded_batches, byte_texts, fresh, materialize, mix64, read_table, sliced, tidy
from cellscrub.llm.sketches import repetition_bitmaps, test_bits

SHINGLE = 5
PERCENT = 80
LEVELS = (2, 16)
ID_BITS = 24
GROUP_BUDGET = 100_000
#: A large group's comparison with its hub is dealt into so many tasks for each budget.
SALTS_A_BUDGET = 4
#: A component's name reaches its members in so many tasks.
HEAD_SALTS = 32


def _shingle_hasher(k: int):
    words_of, rolling = WordHashes(), RollingHash()

    def of(text: bytes | None) -> np.ndarray:
        """Distinct shingle hashes, sorted."""
        words = text.lower().split() if text else ()
        if not words:
            return np.empty(0, np.uint64)
        size = min(k, len(words))
        return np.unique(rolling.grams(words_of.of(words), size, size))

    return of


def _least_overlap(n: int, percent: int) -> int:
    return (percent * n + 99) // 100


_NODE = "doc_id long, n_shingles long, key binary, prefix array<long>, shingles binary"


def _node_batches(bitmaps, k: int, percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from nodes(batches)
        finally:
            tidy(bitmaps)

    def nodes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of = _shingle_hasher(k)
        maps = [np.frombuffer(b, np.uint8) for b in bitmaps.value]
        salt = np.uint64(0xA5A5A5A5DEADBEEF)
        for batch in sliced(batches):
            sizes, keys, prefixes, sets = [], [], [], []
            for text in byte_texts(batch.column("text")):
                found = of(text)
                n = len(found)
                sizes.append(n)
                if not n:
                    keys.append(None)
                    prefixes.append(None)
                    sets.append(None)
                    continue
                with np.errstate(over="ignore"):
                    keys.append(np.array([np.add.reduce(mix64(found ^ salt)), np.add.reduce(mix64(found + salt)) + np.uint64(n)], np.uint64).tobytes())
                level = np.zeros(n, np.uint8)
                for bits in maps:
                    level += test_bits(bits, found)
                order = np.lexsort((found, level))
                least = _least_overlap(n, percent)
                head = order[: n - least + 1]
                shared = found[head][level[head] > 0]
                # a partner shares `least` shingles, and whatever is shared was met twice
                if len(shared) and np.count_nonzero(level) >= least:
                    prefixes.append(shared.view(np.int64).tolist())
                    sets.append(found[order].tobytes())
                else:
                    prefixes.append(None)
                    sets.append(None)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(keys, pa.binary()), pa.array(prefixes, pa.list_(pa.int64())), pa.array(sets, pa.binary())], names=["doc_id", "n_shingles", "key", "prefix", "shingles"])
    return run


class InvertedIndex:
    """Lists of set numbers by shingle; set numbers only grow, so every list is sorted."""

    def __init__(self):
        self.lists: dict[int, list[int]] = {}

    def add(self, number: int, shingles: list[int]) -> None:
        for s in shingles:
            found = self.lists.get(s)
            if found is None:
                self.lists[s] = [number]
            else:
                found.append(number)

    def occurring(self, shingles: list[int], least: int) -> Iterator[tuple[int, int]]:
        """(set, overlap) for the sets that share `least` shingles or more with the query.

        The longest lists, fewer than `least` of them, are set aside; a set must then reach the rest of the threshold
        in the short lists, which are merged, and is looked up in the long ones by binary search.
        """
        lists = [x for s in shingles if (x := self.lists.get(s))]
        if len(lists) < least:
            return
        lists.sort(key=len)
        aside = max(0, least - 1 - least // 10)
        short, long = lists[: len(lists) - aside], lists[len(lists) - aside :]
        for number, run in groupby(heapq.merge(*short)):
            overlap = sum(1 for _ in run)
            if overlap < least - aside:
                continue
            left = len(long)
            for one in reversed(long):
                if overlap + left < least:
                    break
                at = bisect_left(one, number)
                overlap += at < len(one) and one[at] == number
                left -= 1
            if overlap >= least:
                yield number, overlap


class _Component:
    __slots__ = ("pending", "index")

    def __init__(self):
        self.pending: list[int] = []
        self.index: InvertedIndex | None = None


def link_sets(sets: list[list[int]], prefix_sizes: list[int], percent: int = PERCENT, joined: list[int] | None = None) -> list[int]:
    """Component root for each set; sets hold distinct shingles in the global order, sorted by size.

    joined may give a component number for each set, equal where sets are known to be linked, to continue from.
    """
    parent = list(range(len(sets)))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    if joined is not None:
        first: dict[int, int] = {}
        for i, c in enumerate(joined):
            parent[i] = first.setdefault(c, i)
    heads = InvertedIndex()
    groups: dict[int, _Component] = {}
    by_prefix: dict[int, set[int]] = {}

    def linked(a: int, b: int, overlap: int) -> bool:
        return 100 * overlap >= percent * (len(sets[a]) + len(sets[b]) - overlap)

    for x, shingles in enumerate(sets):
        near: set[int] = set()
        for s in shingles[: prefix_sizes[x]]:
            near |= by_prefix.get(s, frozenset())
        home = None
        if near:
            least = _least_overlap(len(shingles), percent)
            for head, overlap in heads.occurring(shingles, least):
                if root(head) != root(x) and linked(x, head, overlap):
                    parent[root(x)] = root(head)
                    home = head
            for head in near:
                group = groups[head]
                if root(head) == root(x):
                    home = head
                    continue
                if not group.pending and group.index is None:
                    continue
                if group.index is None:
                    group.index = InvertedIndex()
                for member in group.pending:
                    group.index.add(member, sets[member])
                group.pending = []
                for member, overlap in group.index.occurring(shingles, least):
                    if linked(x, member, overlap):
                        parent[root(x)] = root(head)
                        home = head
                        break
        if home is None:
            home = x
            groups[x] = _Component()
            heads.add(x, shingles)
        else:
            groups[home].pending.append(x)
        for s in shingles[: prefix_sizes[x]]:
            by_prefix.setdefault(s, set()).add(home)
    return [root(i) for i in range(len(sets))]


_TASK = "grp binary, key binary, known boolean, shingles binary"


def _group_batches(percent: int):
    """For rows sorted by task, (a, b) links that join each component of a task's sets; known ones are one already."""

    def solve(rows: list[tuple]) -> Iterator[tuple[bytes, bytes]]:
        rows.sort(key=lambda r: (len(r[2]), r[0]))
        sets = [np.frombuffer(r[2], np.uint64).tolist() for r in rows]
        joined = [-1 if known else i for i, (_, known, _) in enumerate(rows)]
        roots = link_sets(sets, [len(s) - _least_overlap(len(s), percent) + 1 for s in sets], percent, joined)
        told = False
        for r, (key, known, _) in zip(roots, rows):
            if key != rows[r][0] and not (known and (told or rows[r][1])):
                yield key, rows[r][0]
                told = told or known

    def links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, rows, out = None, [], []

        def drain() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], pa.binary()) for i in (0, 1)], names=["a", "b"])
            out.clear()
            return batch

        for batch in batches:
            for task, key, known, shingles in zip(*(batch.column(c).to_pylist() for c in ("grp", "key", "known", "shingles"))):
                if task != current:
                    out += solve(rows)
                    current, rows = task, []
                rows.append((key, known, shingles))
            if len(out) > 20_000:
                yield drain()
        out += solve(rows)
        yield drain()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from links(batches)
        finally:
            tidy()

    return run


def _hub_batches(percent: int):
    """Whether each set links with its group's hub."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, hub = None, np.empty(0, np.uint64)
        for batch in batches:
            flags = []
            for one, of_hub in zip(batch.column("shingles").to_pylist(), batch.column("hub_shingles").to_pylist()):
                if of_hub != last:
                    last, hub = of_hub, np.sort(np.frombuffer(of_hub, np.uint64))
                mine = np.frombuffer(one, np.uint64)
                both = int(np.count_nonzero(hub[np.minimum(np.searchsorted(hub, mine), len(hub) - 1)] == mine))
                flags.append(100 * both >= percent * (len(mine) + len(hub) - both))
            yield pa.RecordBatch.from_arrays([batch.column("hub"), batch.column("key"), batch.column("n"), pa.array(flags, pa.bool_())], names=["hub", "key", "n", "known"])

    return run


def _chunk_tasks(tested: DataFrame, budget: int) -> DataFrame:
    """grp, key, known: members of large groups dealt into tasks, each of two chunks of half the budget at most.

    Chunks of members that don't link with the hub meet each other and every chunk of those that do.
    """
    share = lambda c: F.ceil(F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0)) / (budget / 2)).cast("int")
    parts = tested.groupBy("hub").agg(share(~F.col("known")).alias("open_parts"), share(F.col("known")).alias("known_parts")).filter("open_parts > 0")
    dealt = tested.join(parts, "hub").withColumn("chunk", F.pmod(F.xxhash64("key"), F.when(F.col("known"), F.col("known_parts")).otherwise(F.col("open_parts"))).cast("int"))
    to = lambda n: F.sequence(F.lit(0), n - 1)
    name = lambda kind, i, j: F.concat_ws(":", F.lit(kind), i.cast("string"), j.cast("string"))
    with_known = F.when(F.col("known"), F.transform(to(F.col("open_parts")), lambda i: name("k", i, F.col("chunk")))).otherwise(F.transform(to(F.col("known_parts")), lambda j: name("k", F.col("chunk"), j)))
    others = F.filter(F.transform(to(F.col("open_parts")), lambda i: F.when(i != F.col("chunk"), name("o", F.least(i, F.col("chunk")), F.greatest(i, F.col("chunk"))))), lambda x: x.isNotNull())
    tasks = F.when(F.col("known"), with_known).otherwise(F.concat(with_known, others))
    return dealt.select("hub", "key", "known", F.explode(tasks).alias("t")).select(F.concat("hub", F.encode("t", "utf-8")).alias("grp"), "key", "known")


def connected(edges: DataFrame, rounds: int = 40) -> DataFrame:
    """(node, head) for every node that has an edge and isn't its component's least: alternating stars.

    edges: columns a and b. Each round is two joins with map-side combined minima, written to the shared folder; the
    number of edges never grows, and rounds grow with the logarithm of the longest path.
    """
    current = materialize(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct(), "star")
    state = None
    for _ in range(rounds):
        both = current.union(current.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(least, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        small_least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(small_least, "a").filter("b <> m").select(F.greatest("b", "m").alias("a"), F.least("b", "m").alias("b"))
        current = materialize(small.union(small_least.select("a", F.col("m").alias("b"))).distinct(), "star")
        new = current.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        if state == (new.n, new.h):
            break
        state = (new.n, new.h)
    else:
        raise RuntimeError("components did not settle")
    return current.select(F.col("a").alias("node"), F.col("b").alias("head"))


def components(docs: DataFrame, percent: int = PERCENT, shingle: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text", group_budget: int = GROUP_BUDGET) -> DataFrame:
    """doc_id, n_shingles, component_id, set_key (binary, equal for equal sets); one row per input row."""
    spark = docs.sparkSession
    bounded_batches(spark)
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    bitmaps = spark.sparkContext.broadcast(repetition_bitmaps(slim, lambda: _shingle_hasher(shingle), levels=LEVELS))
    rows = materialize(slim.mapInArrow(_node_batches(bitmaps, shingle, percent), _NODE), "join-nodes")
    bitmaps.unpersist()
    open_rows = rows.filter(F.col("prefix").isNotNull())
    least = open_rows.groupBy("key").agg(F.min("doc_id").alias("least_id"))
    prefixes = open_rows.select("key", "n_shingles", "prefix").dropDuplicates(["key"]).select("key", F.col("n_shingles").alias("n"), F.explode("prefix").alias("s"))
    hubs = prefixes.groupBy("s").agg(F.min("key").alias("hub"), F.count("*").alias("sharing")).filter("sharing > 1").select("s", "hub")
    homes = materialize(prefixes.join(hubs, "s").select("key", "n", "hub").distinct(), "join-homes")
    large = materialize(homes.groupBy("hub").agg(F.ceil(SALTS_A_BUDGET * F.sum("n") / group_budget).cast("int").alias("salts")).filter(F.col("salts") > SALTS_A_BUDGET), "join-large")
    sets = open_rows.select("key", "shingles").dropDuplicates(["key"])
    of_hub = sets.select(F.col("key").alias("hub"), F.col("shingles").alias("hub_shingles")).join(large, "hub").select("hub", "hub_shingles", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"))
    salted = homes.join(large, "hub").withColumn("salt", F.pmod(F.xxhash64("key"), "salts").cast("int"))
    wide = salted.join(sets, "key").join(of_hub.hint("merge"), ["hub", "salt"]).select("hub", "key", "n", "shingles", "hub_shingles")
    tested = materialize(wide.mapInArrow(_hub_batches(percent), "hub binary, key binary, n long, known boolean"), "join-tested")
    small = homes.join(large, "hub", "left_anti").select(F.col("hub").alias("grp"), "key", F.lit(False).alias("known"))
    tasks = small.unionByName(_chunk_tasks(tested, group_budget)).join(sets, "key").select("grp", "key", "known", "shingles")
    solved = tasks.repartition("grp").sortWithinPartitions("grp").mapInArrow(_group_batches(percent), "a binary, b binary")
    stars = connected(solved.unionByName(tested.filter("known").select(F.col("key").alias("a"), F.col("hub").alias("b"))))
    members = stars.select(F.col("node").alias("key"), "head").union(stars.select(F.col("head").alias("key"), "head").distinct()).join(least, "key")
    named = members.groupBy("head").agg(F.min("least_id").alias("component_id"))
    salted = named.select("head", "component_id", F.explode(F.sequence(F.lit(0), F.lit(HEAD_SALTS - 1))).alias("salt"))
    told = members.withColumn("salt", F.pmod(F.xxhash64("key"), F.lit(HEAD_SALTS)).cast("int")).join(salted.hint("merge"), ["head", "salt"]).select("key", "component_id")
    found = materialize(least.join(told, "key", "left").select("key", F.coalesce("component_id", "least_id").alias("component_id")), "join-components")
    return rows.select("doc_id", "n_shingles", "key").join(found, "key", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"), F.col("key").alias("set_key"))


def _id_hasher():
    return lambda text: mix64(np.array([xxhash.xxh3_64_intdigest(text)], np.uint64)) if text is not None else np.empty(0, np.uint64)


def _by_bitmap(bitmap, id_col: str, marked: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.frombuffer(bitmap.value, np.uint8)
        for batch in batches:
            ids = batch.column(id_col).cast(pa.int64()).to_pylist()
            hashes = mix64(np.array([0 if i is None else xxhash.xxh3_64_intdigest(str(i).encode()) for i in ids], np.uint64))
            known = np.array([i is not None for i in ids], bool)
            yield batch.filter(pa.array((test_bits(bits, hashes, ID_BITS) & known) == marked))
        del bits
        tidy(bitmap)

    return run


def keep_representatives(docs: DataFrame, percent: int = PERCENT, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One row of each component, that with the smallest id; all rows without words, and all columns of docs.

    Of rows that repeat a component's smallest id the one with the longest text is kept (the greatest of equally long
    ones); rows with a null id all stay. A bitmap of fixed size over the ids to drop tells most rows apart in place; only
    rows that it marks take part in the exact join.
    """
    spark = docs.sparkSession
    marked = materialize(components(docs, percent, id_col=id_col, text_col=text_col), "join-marked")
    loser, repeat, place = fresh(docs, "__loser"), fresh(docs, "__repeat"), fresh(docs, "__place")
    losers = marked.filter(F.col("n_shingles") > 0).filter(F.col("component_id") != F.col("doc_id")).select(F.col("doc_id").alias(loser)).distinct()
    losers = materialize(losers, "join-losers")
    bitmap = spark.sparkContext.broadcast(repetition_bitmaps(losers.select(F.col(loser).cast("string").alias("text")), _id_hasher, levels=(1,), bitmap_bits=ID_BITS)[0])
    maybe = docs.mapInArrow(_by_bitmap(bitmap, id_col, True), docs.schema)
    exact = maybe.join(losers, maybe[id_col].cast("long") == F.col(loser), "left_anti")
    kept = docs.mapInArrow(_by_bitmap(bitmap, id_col, False), docs.schema).unionByName(exact)
    repeated = materialize(marked.filter("n_shingles > 0 and component_id = doc_id").groupBy(F.col("doc_id").alias(repeat)).count().filter("count > 1").select(repeat), "join-repeats")
    if repeated.isEmpty():
        return kept
    same = kept[id_col].cast("long") == F.col(repeat)
    first = Window.partitionBy(id_col).orderBy(F.coalesce(F.octet_length(text_col), F.lit(0)).desc(), F.col(text_col).desc())
    once = kept.join(repeated, same, "left_semi").withColumn(place, F.row_number().over(first)).filter(F.col(place) == 1).drop(place)
    return kept.join(repeated, same, "left_anti").unionByName(once)


def jaccard_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return components(read_table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


JACCARD_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
), sh AS MATERIALIZED (
  SELECT DISTINCT doc_id, s FROM (
    SELECT doc_id, md5(array_to_string(ws[p : p + 4], ' ')) AS s FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 2))) AS p FROM w WHERE len(ws) > 0)
  )
), sizes AS MATERIALIZED (
  SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id
), links AS MATERIALIZED (
  SELECT a.doc_id AS x, b.doc_id AS y
  FROM (SELECT a.doc_id, b.doc_id AS other, count(*) AS i FROM sh a JOIN sh b ON a.s = b.s AND a.doc_id <> b.doc_id GROUP BY ALL) a
  JOIN sizes sa ON sa.doc_id = a.doc_id JOIN sizes b ON b.doc_id = a.other
  WHERE 100 * i >= 80 * (sa.n + b.n - i)
), reach AS (
  SELECT doc_id AS x, doc_id AS y FROM documents
  UNION
  SELECT reach.x, links.y FROM reach JOIN links ON reach.y = links.x
)
SELECT d.doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, (SELECT min(y) FROM reach WHERE reach.x = d.doc_id) AS component_id
FROM documents d LEFT JOIN sizes USING (doc_id)
"""
