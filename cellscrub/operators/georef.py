"""Reference sources: block joins instead of one request a record, scoring, coverage and agreement.

A ladder of equi-joins (postcode and country, locality and country, name and country) offers candidates; each rung only
sees the records that no earlier one matched, and the best candidate of a record is kept.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellscrub.functions import text as X
from cellscrub.schema import CORE_ATTRS
from cellscrub.session import materialize

RUNGS = (("postcode", "country"), ("postcode", "country_code"), ("locality", "country"), ("locality", "country_code"), ("name", "country"))
COMPARED = ("house_number", "road", "postcode", "locality")
ACCEPT = 0.75
SALTS = 8
PLACE = tuple(c for c in CORE_ATTRS if c not in ("house_number", "road"))
#: Sizes up to which texts are looked up by blocks: words of a text (fractions of such sizes stay apart when rounded), a
#: reference's words beside its place's, and such words in a question; sets of the latter two are listed.
SHORT, STREET_WORDS, ASKED_WORDS = 300, 6, 8
ROUNDED = 1e-6  # scores are rounded before they are compared


def _ratio(c: str) -> Column:
    d, r = F.col(f"d._{c}"), F.col(f"r._{c}")
    return F.when(d.isNotNull() & r.isNotNull(), X.ratio(d, r)).otherwise(0.0)  # X.ratio takes a null beside an empty text as equal


def _score() -> Column:
    """Mean ratio of house number, road, postcode and locality between d (dirty) and r (reference), in lower case."""
    return F.round(reduce(lambda x, y: x + y, (_ratio(c) for c in COMPARED)) / len(COMPARED), 6)


def reference(clean: DataFrame, nations: int | None = None) -> DataFrame:
    """Distinct clean addresses with an id, restricted to the first nations (by number) for a sparse source."""
    rows = clean.select("name", *CORE_ATTRS).distinct()
    if nations is not None:
        rows = rows.filter(F.regexp_extract("country", r"(\d+)$", 1).try_cast("int") < nations)
    return rows.withColumn("ref_id", F.md5(F.concat_ws("|", *[F.coalesce(F.col(c), F.lit("")) for c in ("name", *CORE_ATTRS)])))


def _same(a: str, b: str, cols: tuple[str, ...]) -> Column:
    return reduce(lambda x, y: x & y, (F.col(f"{a}.{c}").eqNullSafe(F.col(f"{b}.{c}")) for c in cols))


def _best_in_blocks(q: DataFrame, r: DataFrame, keys: tuple[str, ...], accept: float) -> DataFrame:
    """qid, score, ref_id: the best accepted reference of every query within its block, the smallest ref_id on ties.

    Exact without comparing whole blocks. First come references alike in all four fields, then those with the same house
    number or the same road. Any other one scores at most a bound: fields that differ from a value of n letters lose
    1 / (n + 1) at least, and the other fields reach their best in the block. Only queries whose bound is not below what
    they have (or `accept`) are compared with the rest of their block.
    """
    fields, on = list(COMPARED), list(keys)
    rows = lambda found: found.groupBy("qid").agg(F.min(F.struct((-F.col("score")).alias("m"), "ref_id")).alias("b")).select("qid", (-F.col("b.m")).alias("score"), F.col("b.ref_id").alias("ref_id"))
    equal = q.join(r, [*on, *[f"_{c}" for c in fields]]).select("qid", F.lit(1.0).alias("score"), "ref_id")
    exact = materialize(rows(equal), "lookup-exact")
    rest = q.join(exact, "qid", "left_anti")
    for c in ("postcode", "locality"):
        if c in keys:
            most = rest.select(*on, f"_{c}").distinct().withColumn(f"u_{c}", F.lit(1.0))
        else:
            most = rest.select(*on, f"_{c}").distinct().alias("d").join(r.select(*on, f"_{c}").distinct().alias("r"), on).groupBy(*on, f"d._{c}").agg(F.max(_ratio(c)).alias(f"u_{c}"))
        rest = rest.alias("d").join(most.alias("m"), _same("d", "m", (*on, f"_{c}"))).select("d.*", f"u_{c}")
    rest = materialize(rest, "lookup-rest")
    by = lambda df: df.withColumn("via", F.explode(F.array(F.struct(F.lit("h").alias("f"), F.col("_house_number").alias("v")), F.struct(F.lit("r").alias("f"), F.col("_road").alias("v"))))).filter("via.v IS NOT NULL").select("*", F.col("via.f").alias("f"), F.col("via.v").alias("fv")).drop("via")
    tasks = max(2 * q.sparkSession.sparkContext.defaultParallelism, rest.count() // 20_000)  # by pairs, not by bytes, which are few
    deal = lambda df, cols: df.repartition(tasks, *cols)
    on_via = [*on, "f", "fv"]
    met = deal(by(rest), on_via).alias("d").join(deal(by(r), on_via).alias("r"), on_via)
    near = materialize(rows(met.select("qid", "ref_id", _score().alias("score")).filter(F.col("score") >= accept)), "lookup-near")
    differing = lambda c: F.when(F.col(f"_{c}").isNull(), 0.0).otherwise(1 - 1 / (F.length(f"_{c}") + 1))
    bound = F.round((differing("house_number") + differing("road") + F.col("u_postcode") + F.col("u_locality")) / 4, 6)
    open_ = rest.withColumn("bound", bound).join(near.select("qid", "score"), "qid", "left").filter(F.col("bound") >= F.coalesce("score", F.lit(accept))).drop("score")
    salted = open_.withColumn("salt", F.pmod("qid", F.lit(SALTS)))  # several tasks share a large block
    every = r.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)).cast("array<bigint>")))
    late = deal(salted, [*on, "salt"]).alias("d").join(deal(every, [*on, "salt"]).alias("r"), [*on, "salt"]).select("qid", "ref_id", _score().alias("score")).filter(F.col("score") >= accept)
    return rows(exact.unionByName(near).unionByName(rows(late)))


def lookup(dirty: DataFrame, ref: DataFrame, accept: float = ACCEPT) -> DataFrame:
    """_id, ref_id, score, rung: the best accepted hit of each record that has one.

    Records and references that are alike in a rung's keys and the compared fields are compared once.
    """
    folded = [F.lower(F.col(c)).alias(f"_{c}") for c in COMPARED]
    asked = [k for k in dict.fromkeys(k for keys in RUNGS for k in keys)]
    left = materialize(dirty.select("_id", *asked, *folded), "lookup-left")
    refs = materialize(ref.select("ref_id", *asked, *folded), "lookup-refs")
    out = None
    for i, keys in enumerate(RUNGS):
        alike = [*keys, *[f"_{c}" for c in COMPARED]]
        known = left.dropna(subset=list(keys))
        q = materialize(known.select(*alike).distinct().withColumn("qid", F.monotonically_increasing_id()), "lookup-asked")
        r = materialize(refs.dropna(subset=list(keys)).groupBy(*alike).agg(F.min("ref_id").alias("ref_id")), "lookup-blocks")
        found = _best_in_blocks(q, r, keys, accept).join(q, "qid")
        hits = known.alias("d").join(found.alias("m"), _same("d", "m", tuple(alike))).select("d._id", "m.ref_id", "m.score")
        best = hits.groupBy("_id").agg(F.min(F.struct((-F.col("score")).alias("m"), "ref_id")).alias("b"))
        best = materialize(best.select("_id", F.col("b.ref_id").alias("ref_id"), (-F.col("b.m")).alias("score"), F.lit(i).alias("rung")), "lookup-hits")
        out = best if out is None else out.unionByName(best)
        if i + 1 < len(RUNGS):
            left = materialize(left.join(best.select("_id"), "_id", "left_anti"), "lookup-left")
    return out


def _best_by_prefix(asked: DataFrame, refs: DataFrame, least: float) -> DataFrame:
    """id, b (see `_code`): the best reference by shared words, for texts of any length.

    Words are ordered from the rarest on; for sizes n and m, sets that are alike enough share at least
    least / (1 + least) * (n + m) words and thus meet in the words before those, so no match is lost.
    """
    counts = refs.select(F.explode("s").alias("w")).groupBy("w").agg(F.count("*").alias("n"))
    bound = least - ROUNDED

    def ordered(sets: DataFrame, key: str) -> DataFrame:
        known = sets.select(F.col(key).alias("id"), F.size("s").alias("size"), F.explode("s").alias("w")).join(counts, "w").groupBy("id", "size").agg(F.array_sort(F.collect_list(F.struct("n", "w"))).alias("k"))
        return materialize(known.select("id", F.col("size").alias("n"), F.col("k.w").alias("k")), "freetext")

    q, r = ordered(asked, "id"), ordered(refs, "no")

    def proposing(some: DataFrame, others: DataFrame) -> DataFrame:
        sizes = F.broadcast(others.select(F.col("n").alias("m")).distinct())
        fits = some.join(sizes, (F.col("m") >= F.col("n") * bound) & (F.col("n") >= F.col("m") * bound))
        take = F.size("k") - F.ceil(F.lit(bound / (1 + bound)) * (F.col("n") + F.col("m")) - 1e-9).cast("int") + 1
        return fits.select("id", "k", "n", "m", F.explode(F.slice("k", 1, F.greatest(take, F.lit(0)))).alias("w"))

    left, right = proposing(q, r).alias("q"), proposing(r, q).alias("r")
    pairs = left.join(right, (F.col("q.w") == F.col("r.w")) & (F.col("q.n") == F.col("r.m")) & (F.col("q.m") == F.col("r.n")))
    scored = pairs.select(F.col("q.id").alias("id"), F.col("r.id").alias("no"), _shared(F.size(F.array_intersect("q.k", "r.k")), F.col("q.n") + F.col("r.n")).alias("score"))
    return scored.filter(F.col("score") >= least).groupBy("id").agg(_code().alias("b"))


def _shared(common: Column, sizes: Column) -> Column:
    """Shared words over all words; sizes is the sum of both sizes."""
    return F.round(common / (sizes - common), 6)


def _code() -> Column:
    """The highest score and its smallest reference number in one long, which is aggregated without a sort."""
    return F.min((1000000 - F.round(F.col("score") * 1000000).cast("long")) * 2**42 + F.col("no"))


def _subset(words: Column, mask: Column) -> Column:
    """Those of the sorted words whose bit is set, as one text."""
    return F.array_join(F.filter(words, lambda w, i: F.getbit(mask, i) == 1), " ")


def _masks(words: Column) -> Column:
    return F.sequence(F.lit(0).cast("long"), F.pow(F.lit(2), F.size(words)).cast("long") - 1)


def _best_by_blocks(asked: DataFrame, refs: DataFrame, least: float) -> DataFrame:
    """n, ka, kb, b: the best reference of every question, of which `refs` has few street words each.

    References with the same place words p form a block, and a table holds, for each block and each set of street words,
    the smallest reference with those. A question shares o words with a block, and x street words at most beside them, which bounds
    its score there. It is looked up in the block with the highest bound first, then in all blocks whose bound is not
    below what it has. The block -1 holds all references, for those that share no place word.
    """
    refs = refs.withColumn("street", F.array_except("s", "p")).withColumn("m", F.size("s"))
    blocks = refs.groupBy("p").agg(F.min("m").alias("least_m"), F.max(F.size("street")).alias("most_x")).withColumn("bid", F.monotonically_increasing_id())
    blocks = materialize(blocks.withColumn("size_p", F.size("p")), "freetext-blocks")
    made = refs.join(blocks.select("p", "bid"), "p").select(F.explode(F.array("bid", F.lit(-1).cast("long"))).alias("bid"), "no", "m", "street")
    table = made.select("bid", "no", "m", "street", F.explode(_masks(F.col("street"))).alias("mask")).select("bid", _subset(F.col("street"), F.col("mask")).alias("key"), "m", "no")
    table = materialize(table.groupBy("bid", "key").agg(F.min(F.struct("m", "no")).alias("r")).select("bid", "key", "r.m", "r.no"), "freetext-table")

    floor = least - ROUNDED
    groups = materialize(asked.select("kb", F.size("ka").alias("c"), "n").distinct().withColumn("gid", F.monotonically_increasing_id()), "freetext-groups")
    q = materialize(asked.withColumn("c", F.size("ka")).join(groups, ["kb", "c", "n"]).withColumn("qid", F.monotonically_increasing_id()), "freetext-asked")
    # kb has the rarest words first: enough shared words include one of the first `take`, and a pair counts at its first shared word
    ends = blocks.agg(F.min("least_m").alias("least_m"), F.max("most_x").alias("most_x"))
    least_m, most_x = ends.first() or (0, 0)
    need = F.ceil(F.lit(floor / (1 + floor)) * (F.col("n") + F.lit(least_m)) - 1e-9).cast("int") - F.least("c", F.lit(most_x))
    take = F.greatest(F.size("kb") - F.greatest(need, F.lit(1)) + 1, F.lit(0))
    tasks = max(2 * refs.sparkSession.sparkContext.defaultParallelism, groups.count() // 20_000)  # by pairs, not by bytes, which are few
    shared = F.array_intersect("kb", "p")
    met = groups.repartition(tasks, "gid").withColumn("w", F.explode(F.slice("kb", 1, take))).join(blocks.withColumn("w", F.explode("p")), "w").filter(shared[0] == F.col("w"))
    met = met.select("gid", "n", "c", "bid", F.size(shared).alias("o"), "size_p", "least_m", "most_x")
    whole = ends.select(F.lit(-1).cast("long").alias("bid"), F.lit(0).alias("o"), F.lit(0).alias("size_p"), "*")
    met = met.unionByName(groups.select("gid", "n", "c").crossJoin(F.broadcast(whole)))

    def bound(x: Column) -> Column:
        common = F.col("o") + x
        return common / (F.col("n") + F.greatest(F.col("least_m"), F.col("size_p") + x) - common)

    offers = met.withColumn("most", bound(F.least("c", "most_x"))).filter(F.col("most") >= floor)
    offers = materialize(offers.select("gid", "bid", "o", "size_p", "least_m", "most_x", "most"), "freetext-offers")

    def looked_up(rows: DataFrame) -> DataFrame:
        """qid, b of rows with a question, a block and `floor`, below which no score counts."""
        masks = F.filter(_masks(F.col("ka")), lambda k: (F.bit_count(k) <= F.col("most_x")) & (bound(F.bit_count(k)) >= F.col("floor")))
        tried = rows.select("qid", "n", "bid", "o", "ka", F.explode(masks).alias("mask")).select("qid", "bid", (F.col("o") + F.bit_count("mask")).alias("common"), "n", _subset(F.col("ka"), F.col("mask")).alias("key"))
        hits = tried.join(table, ["bid", "key"]).select("qid", "no", _shared(F.col("common"), F.col("n") + F.col("m")).alias("score"))
        return hits.filter(F.col("score") >= least).groupBy("qid").agg(_code().alias("b"))

    first = offers.groupBy("gid").agg(F.max(F.struct("most", "bid", "o", "size_p", "least_m", "most_x")).alias("f")).select("gid", "f.*")
    found = materialize(looked_up(q.join(first, "gid").withColumn("floor", F.lit(floor))), "freetext-first")
    left = q.join(found, "qid", "left").withColumn("floor", F.coalesce(_score_of("b") - ROUNDED, F.lit(floor))).drop("b")
    rest = offers.join(first.select("gid", "bid"), ["gid", "bid"], "left_anti")
    late = looked_up(left.join(rest, "gid").filter(F.col("most") >= F.col("floor")))
    best = found.unionByName(late).groupBy("qid").agg(F.min("b").alias("b"))
    return best.join(q, "qid").select("n", "ka", "kb", "b")


def _score_of(code: str) -> Column:
    return (1000000 - F.shiftright(code, 42)) / 1000000


def lookup_freetext(dirty: DataFrame, ref: DataFrame, least: float = 0.5) -> DataFrame:
    """_id, ref_id, score: the best reference by shared words of the whole address, least (above 0) or better.

    Equal word sets are compared once. Short texts go by blocks of places; references with more than STREET_WORDS words
    beside their place's and questions with many such words, or either with more than SHORT words, go by prefixes. Both are exact.
    """
    words = lambda *cols: F.array_sort(F.array_distinct(X.tokens(F.concat_ws(" ", *[F.col(c) for c in cols]))))
    asked = materialize(dirty.select("_id", words(*CORE_ATTRS).alias("s")), "freetext")
    sets = materialize(asked.filter(F.size("s") > 0).groupBy("s").agg(F.min("_id").alias("id")), "freetext")
    refs = ref.select("ref_id", words(*CORE_ATTRS).alias("s"), words(*PLACE).alias("p")).filter(F.size("s") > 0).groupBy("s").agg(F.min(F.struct("ref_id", "p")).alias("r")).select("s", "r.*")
    # numbers in the order of ref_id
    refs = refs.repartitionByRange(64, "ref_id").sortWithinPartitions("ref_id").withColumn("no", F.monotonically_increasing_id())
    refs = materialize(refs, "freetext")
    few = (F.size("s") <= SHORT) & (F.size("s") - F.size("p") <= STREET_WORDS)
    near, far = refs.filter(few), refs.filter(~few)
    of = lambda c, place: near.select(F.explode(c).alias("w"), F.lit(place).alias("place"))
    known = of(F.array_except("s", "p"), 0).unionByName(of("p", 1)).groupBy("w").agg(F.count_if(F.col("place") == 0).alias("a"), F.sum("place").alias("b"))
    cut = sets.select("id", F.size("s").alias("n"), F.explode("s").alias("w")).join(known, "w").groupBy("id", "n")
    cut = cut.agg(*[F.array_sort(F.collect_list(F.when(F.col(c) > 0, F.struct(F.lit(0).cast("long") if c == "a" else F.col(c), "w")))).alias(c) for c in "ab"])
    cut = materialize(cut.select("id", "n", F.col("a.w").alias("ka"), F.col("b.w").alias("kb")), "freetext")
    long_ = (F.col("n") > SHORT) | (F.size("ka") > ASKED_WORDS)
    short = cut.filter(~long_)
    best = short.join(_best_by_blocks(short.select("n", "ka", "kb").distinct(), near, least), ["n", "ka", "kb"]).select("id", "b")
    if not far.isEmpty():
        best = best.unionByName(_best_by_prefix(sets, far, least))
    if not (large := cut.filter(long_)).isEmpty():
        best = best.unionByName(_best_by_prefix(sets.join(large.select("id"), "id"), near, least))
    best = best.groupBy("id").agg(F.min("b").alias("b")).select("id", (F.col("b") % 2**42).alias("no"), _score_of("b").alias("score"))
    found = best.join(refs.select("no", "ref_id"), "no").join(sets, "id").select("s", "ref_id", "score")
    return asked.join(found, "s").select("_id", "ref_id", "score").distinct()


def lookup_client(dirty: DataFrame, client: Callable[[dict], dict | None], schema: str = "_id string, ref_id string, score double") -> DataFrame:
    """One request a record through a pluggable client, for real services."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            hits = [(r["_id"], h["ref_id"], h["score"]) for r in frame.to_dict("records") if (h := client(r))]
            yield pd.DataFrame(hits, columns=["_id", "ref_id", "score"])

    return dirty.mapInPandas(run, schema)


def coverage(dirty: DataFrame, hits: DataFrame, by: str = "source") -> DataFrame:
    """by, n, matched, match_rate, countries of a union of lookups that carry `by`."""
    n = dirty.agg(F.count("*").alias("n"))
    per = hits.join(dirty.select("_id", "country"), "_id").groupBy(by).agg(F.count("*").alias("matched"), F.count_distinct("country").alias("countries"))
    return per.crossJoin(F.broadcast(n)).select(by, "n", "matched", F.round(F.col("matched") / F.col("n"), 6).alias("match_rate"), "countries")


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """n_both, n_agree, agreement of two sources' hits."""
    both = a.alias("a").join(b.alias("b"), "_id").select((F.col("a.ref_id") == F.col("b.ref_id")).cast("long").alias("same"))
    return both.agg(F.count("*").alias("n_both"), F.coalesce(F.sum("same"), F.lit(0)).alias("n_agree"), F.round(F.coalesce(F.avg("same"), F.lit(0.0)), 6).alias("agreement"))
