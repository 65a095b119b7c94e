"""factor_repair: probabilistic repair over co-occurrence, priors and constraints.

Noisy cells are the blank and the dependency-violating ones. Their candidates are values with P(value | another
attribute's value) of at least `tau` for some other attribute, plus their own. Constraint features count the dependencies
by which a candidate keeps to, or departs from, the majority of its record's left side. A softmax over the candidates'
features is fitted on cells assumed clean, a bounded sample in hash order, and the likeliest candidate is the repair.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cellscrub.operators.fd import Dependency
from cellscrub.schema import ATTRS
from cellscrub.session import materialize
from cellscrub.systems.base import long, rule_sides, side_counts

TAU = 0.3
MAX_DOMAIN = 20
FIT_CELLS = 4000
FEATURES = ("cooccur", "prior", "support", "own_value", "listed", "kept", "broken")


def violating(dirty: DataFrame, fds: list[Dependency]) -> DataFrame:
    """_id, attr of right sides in groups with several values; one pass for all dependencies."""
    known = rule_sides(dirty, fds).filter("v IS NOT NULL")
    bad = known.groupBy("rule", "key").agg((F.min("v") != F.max("v")).alias("bad")).filter("bad").select("rule", "key")
    return known.join(bad, ["rule", "key"], "left_semi").select("_id", "attr").distinct()


def detect(dirty: DataFrame, fds: list[Dependency]) -> DataFrame:
    blank = long(dirty).filter(F.col("value").isNull()).select("_id", "attr")
    return blank.union(violating(dirty, fds)).distinct()


def cooccurrence(dirty: DataFrame, attrs: tuple[str, ...] = ATTRS) -> DataFrame:
    """b_attr, b, attr, v, n: pairs of values in a record, counted over distinct records first.

    Values are counted as 64-bit hashes, every unordered pair of columns once, so that counting runs on fixed-width rows
    with map-side sums; names come back by a join of the results with the distinct values, and pairs are mirrored last.
    """
    counted = dirty.groupBy(*attrs).agg(F.count("*").alias("n"))
    coded = counted.select("n", *[F.when(F.col(a).isNotNull(), F.xxhash64(F.lit(i), F.col(a))).alias(a) for i, a in enumerate(attrs)])
    couples = F.array(*[F.struct(F.lit(i).alias("i"), F.col(a).alias("x"), F.lit(j).alias("j"), F.col(b).alias("y")) for i, a in enumerate(attrs) for j, b in enumerate(attrs) if i < j])
    pairs = coded.select("n", F.inline(couples)).filter("x IS NOT NULL AND y IS NOT NULL").groupBy("i", "x", "j", "y").agg(F.sum("n").alias("n"))
    values = long(counted, attrs, ("n",)).filter("value IS NOT NULL").select("attr", "value").distinct()
    at = F.array_position(F.array(*[F.lit(a) for a in attrs]), F.col("attr")).cast("int")
    names = materialize(values.select(F.xxhash64((at - 1), F.col("value")).alias("h"), "attr", "value"), "cooccur-names")
    named = pairs.join(names.select(F.col("h").alias("x"), F.col("attr").alias("b_attr"), F.col("value").alias("b")), "x").join(names.select(F.col("h").alias("y"), "attr", F.col("value").alias("v")), "y")
    both = F.array(F.struct("b_attr", "b", "attr", "v"), F.struct(F.col("attr").alias("b_attr"), F.col("v").alias("b"), F.col("b_attr").alias("attr"), F.col("b").alias("v")))
    return named.select(F.inline(both), "n").select("b_attr", "b", "attr", "v", "n")


def constraint_votes(dirty: DataFrame, cells: DataFrame, fds: list[Dependency]) -> DataFrame:
    """_id, attr, v, kept: how many dependencies name v as the majority of the record's left side; one pass for all."""
    rows = rule_sides(dirty, fds)
    counts = side_counts(rows)
    most = counts.groupBy("rule", "key").agg(F.min(F.struct((-F.col("n")).alias("m"), "v")).alias("b"), F.sum("n").alias("size")).filter("size > 1").select("rule", "key", F.col("b.v").alias("v"))
    return rows.drop("v").join(cells.select("_id", "attr"), ["_id", "attr"], "left_semi").join(most, ["rule", "key"]).groupBy("_id", "attr", "v").agg(F.count("*").alias("kept"))


def conditional(counts: DataFrame, tau: float = TAU) -> DataFrame:
    """b_attr, b, attr, v, p of at least tau: so at most 1 / tau values for each condition."""
    total = counts.groupBy("b_attr", "b", "attr").agg(F.sum("n").alias("t"))
    return counts.join(total, ["b_attr", "b", "attr"]).withColumn("p", F.col("n") / F.col("t")).filter(F.col("p") >= tau).select("b_attr", "b", "attr", "v", "p", "n")


def learned(dirty: DataFrame, tau: float = TAU) -> DataFrame:
    """The written rules of `conditional`."""
    return materialize(conditional(cooccurrence(dirty), tau), "factor-rules")


def candidates(dirty: DataFrame, cells: DataFrame, fds: list[Dependency], tau: float = TAU, max_domain: int = MAX_DOMAIN, listed: DataFrame | None = None, rules: DataFrame | None = None) -> DataFrame:
    """_id, attr, own, v and the features of every candidate of the given cells; listed: (attr, v) of outside data; rules:
    what `learned` gives for dirty and tau, where it is there already. Each source of candidates is read once: their union is
    summed up by candidate, and what holds for a whole cell comes from a window over it."""
    rules = learned(dirty, tau) if rules is None else rules
    values = long(dirty)
    prior = values.filter(F.col("value").isNotNull()).groupBy("attr", F.col("value").alias("v")).agg(F.count("*").alias("c"))
    rows = cells.select("_id", "attr").join(dirty, "_id")
    near = rows.select("_id", "attr", F.inline(F.array(*[F.struct(F.lit(a).alias("b_attr"), F.col(a).alias("b")) for a in ATTRS]))).filter(F.col("b").isNotNull() & (F.col("b_attr") != F.col("attr")))
    found = near.join(rules, ["attr", "b_attr", "b"]).groupBy("_id", "attr", "v").agg(F.sum(F.log(F.col("p"))).alias("lp"), F.count("*").alias("k"), F.max("n").alias("support"))
    own = cells.select("_id", "attr").join(values, ["_id", "attr"]).filter("value IS NOT NULL").select("_id", "attr", F.col("value").alias("v"), F.col("value").alias("own"))
    votes = constraint_votes(dirty, cells, fds)
    every = found.unionByName(own, allowMissingColumns=True).unionByName(votes, allowMissingColumns=True).repartition("_id", "attr")
    cell = Window.partitionBy("_id", "attr")
    out = every.groupBy("_id", "attr", "v").agg(*[F.max(c).alias(c) for c in ("lp", "k", "support", "own", "kept")])
    out = out.withColumn("own", F.max("own").over(cell)).withColumn("ruled", F.sum("kept").over(cell))
    out = materialize(out, "factor-candidates").join(prior, ["attr", "v"], "left")
    if listed is not None:
        out = out.join(listed.select("attr", "v").distinct().withColumn("hit", F.lit(1.0)), ["attr", "v"], "left")
    else:
        out = out.withColumn("hit", F.lit(0.0))
    features = out.select(
        "_id", "attr", "own", "v",
        (F.coalesce("k", F.lit(0)) + 0.3 * F.coalesce("lp", F.lit(0.0))).alias("cooccur"),
        F.log1p(F.coalesce("c", F.lit(0))).alias("prior"),
        F.log1p(F.coalesce("support", F.lit(0))).alias("support"),
        F.col("v").eqNullSafe(F.col("own")).cast("double").alias("own_value"),
        F.coalesce("hit", F.lit(0.0)).alias("listed"),
        F.log1p(F.coalesce("kept", F.lit(0))).alias("kept"),
        F.log1p(F.coalesce("ruled", F.lit(0)) - F.coalesce("kept", F.lit(0))).alias("broken"),
    )
    place = F.row_number().over(Window.partitionBy("_id", "attr").orderBy(F.desc("own_value"), F.desc("cooccur"), F.desc("prior"), "v"))
    return features.withColumn("_p", place).filter(F.col("_p") <= max_domain + 1).drop("_p")


def fit(dirty: DataFrame, noisy: DataFrame, fds: list[Dependency], limit: int = FIT_CELLS, epochs: int = 20, **options) -> np.ndarray:
    """Softmax weights from cells assumed clean: the observed value should win. The own-value feature is hidden from
    half of them, or it would explain everything."""
    sample = long(dirty).filter(F.col("value").isNotNull()).join(noisy, ["_id", "attr"], "left_anti").select("_id", "attr").orderBy(F.md5(F.concat("_id", "attr"))).limit(limit)
    shown = F.pmod(F.xxhash64("_id", "attr"), F.lit(2))
    found = candidates(dirty, materialize(sample, "factor-sample"), fds, **options)
    # as columns of numbers, not a Python object for every candidate
    rows = found.select(F.concat_ws("|", "_id", "attr").alias("cell"), (F.col("own_value") > 0).alias("right"), *[F.col(f).cast("double") * (shown if f == "own_value" else 1.0) for f in FEATURES]).toArrow()
    cell = rows.column(0).combine_chunks().dictionary_encode().indices.to_numpy() if rows.num_rows else np.zeros(0, dtype=int)
    right = rows.column(1).to_numpy().astype(bool)
    values = np.column_stack([rows.column(i + 2).to_numpy() for i in range(len(FEATURES))])
    order = np.argsort(cell, kind="stable")
    groups = np.split(order, np.flatnonzero(np.diff(cell[order])) + 1)
    w = np.zeros(len(FEATURES))
    data = [(values[g], right[g]) for g in groups if right[g].any() and len(g) > 1]
    for _ in range(epochs):
        grad = np.zeros(len(FEATURES))
        for x, y in data:
            s = x @ w
            p = np.exp(s - s.max())
            grad += x[y].sum(0) - (p / p.sum()) @ x
        if data:
            w += 0.3 * grad / len(data)
    return w


def correct(dirty: DataFrame, cells: DataFrame, fds: list[Dependency], **options) -> DataFrame:
    """_id, attr, repair, score for the given error cells."""
    options = {"rules": learned(dirty, options.get("tau", TAU))} | options  # fitting and scoring share them
    w = fit(dirty, detect(dirty, fds), fds, **options)
    scored = candidates(dirty, cells, fds, **options)
    score = sum((F.col(n) * float(x) for n, x in zip(FEATURES, w)), F.lit(0.0))
    best = scored.withColumn("score", score).groupBy("_id", "attr").agg(F.min(F.struct((-F.col("score")).alias("m"), "v")).alias("b"))
    return best.select("_id", "attr", F.col("b.v").alias("repair"), (-F.col("b.m")).alias("score"))
