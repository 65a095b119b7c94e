"""corrector_ensemble: value, vicinity and domain makers propose; a model per column picks.

Value makers learn from the labelled tuples alone: exact pairs, token replacements, and edits. An edit removes, adds or
replaces a piece at a value's start, end or anywhere, as it was seen between the two sides of a labelled error; its weight
is how often it restores the labelled errors that it applies to. Beside these stand general normal forms that need no
knowledge of the errors (letter case, decoded entities). Vicinity is P(value | another attribute) over the rows, domain
the value's share in its column. A logistic model over the makers' probabilities is fitted on the labelled errors.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from difflib import SequenceMatcher
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellscrub.functions import text as X
from cellscrub.schema import ATTRS
from cellscrub.session import materialize
from cellscrub.systems import factor
from cellscrub.systems.base import Labels, long

MAKERS = ("value", "vicinity", "domain")
MOST = 50
FEATURES = ("exact", "tokens", "shape", "vicinity", "agree", "domain")


def normal_forms(c: Column) -> dict[str, Column]:
    """General normal forms, each a column expression."""
    capital = lambda w: F.concat(F.upper(F.left(w, F.lit(1))), F.lower(F.substring(w, 2, 1000)))
    return {"titled": F.array_join(F.transform(F.split(c, " "), capital), " "), "upper": F.upper(c), "lower": F.lower(c), "decoded": X.entity_decoded(c)}


def edited(value: str, op: str, old: str, new: str) -> str | None:
    """A value after one edit, or None where the edit does not apply."""
    if op == "start":
        return new + value[len(old) :] if value.startswith(old) else None
    if op == "end":
        return value[: len(value) - len(old)] + new if value.endswith(old) else None
    return value.replace(old, new) if old in value else None


def learned_edits(pairs: list[tuple[str, str, str]]) -> list[tuple[str, str, str, str, float]]:
    """(attr, op, old, new, p) of the edits that turn labelled dirty values into clean ones, and how often they do so among
    the labelled errors of the column that they apply to."""
    seen: dict[str, set[tuple[str, str, str]]] = defaultdict(set)
    of_column: dict[str, list[tuple[str, str]]] = defaultdict(list)
    for attr, d, c in pairs:
        of_column[attr].append((d, c))
        for tag, i, j, k, m in SequenceMatcher(None, d, c, autojunk=False).get_opcodes():
            if tag == "equal":
                continue
            old, new = d[i:j], c[k:m]
            if i == 0:
                seen[attr].add(("start", old, new))
            if j == len(d):
                seen[attr].add(("end", old, new))
            if old:
                seen[attr].add(("any", old, new))
    out = []
    for attr, edits in seen.items():
        for op, old, new in sorted(edits):
            tried = [edited(d, op, old, new) == c for d, c in of_column[attr] if edited(d, op, old, new) is not None]
            if sum(tried):
                out.append((attr, op, old, new, sum(tried) / (len(tried) + 0.5)))
    return out


def _token_swaps(pairs: list[tuple[str, str]]) -> dict[str, str]:
    """Tokens that one labelled error lost for another, in the same place."""
    votes: dict[str, Counter] = defaultdict(Counter)
    for d, c in pairs:
        x, y = d.split(" "), c.split(" ")
        if len(x) == len(y):
            for a, b in zip(x, y):
                if a != b and sum(p != q for p, q in zip(x, y)) <= 2:
                    votes[a][b] += 1
    return {a: v.most_common(1)[0][0] for a, v in votes.items() if a and not any(ch.isdigit() for ch in a)}


def _shape(c: Column) -> Column:
    return F.concat_ws("", F.when(c == F.upper(c), "U").when(c == F.lower(c), "L").otherwise("M"), F.when(c.contains("-"), "-"), F.when(c.rlike(r"[.]$"), "."), F.when(c.contains("&#"), "&"))


def proposals(dirty: DataFrame, cells: DataFrame, truth: list[dict], makers: tuple[str, ...] = MAKERS) -> DataFrame:
    """_id, attr, v and the makers' probabilities, at most MOST candidates a cell."""
    spark = dirty.sparkSession
    wrong = [(t["attr"], (t["dirty"] or "").strip(), t["clean"]) for t in truth if (t["dirty"] or "").strip() != (t["clean"] or "").strip() and t["clean"]]
    own = materialize(cells.select("_id", "attr").join(long(dirty), ["_id", "attr"]), "ensemble-cells")  # every maker reads them
    parts = []
    zero = F.lit(0.0)
    if "value" in makers:
        exact = defaultdict(Counter)
        for a, d, c in wrong:
            if d:
                exact[a, d][c] += 1
        rows = [(a, d, c, n / sum(v.values())) for (a, d), v in exact.items() for c, n in v.items()]
        table = spark.createDataFrame(rows, "attr string, value string, v string, p double")
        parts.append(own.join(F.broadcast(table), ["attr", "value"]).select("_id", "attr", "v", F.col("p").alias("exact"), zero.alias("tokens"), zero.alias("shape")))
        swaps = _token_swaps([(d, c) for _, d, c in wrong if d])
        if swaps:
            pairs = F.create_map(*[F.lit(x) for p in swaps.items() for x in p])
            swapped = F.array_join(F.transform(F.split("value", " "), lambda w: F.coalesce(F.element_at(pairs, w), w)), " ")
            parts.append(own.filter(swapped != F.col("value")).select("_id", "attr", swapped.alias("v"), zero.alias("exact"), F.lit(0.9).alias("tokens"), zero.alias("shape")))
        tries = spark.createDataFrame([(a, d, c) for a, d, c in wrong if d] or [("", "", "")], "attr string, value string, clean string")
        edits = learned_edits([(a, d, c) for a, d, c in wrong if d])
        if edits:
            table = F.broadcast(spark.createDataFrame(edits, "attr string, op string, old string, new string, p double"))
            value, old, new = F.col("value"), F.col("old"), F.col("new")
            made = F.when((F.col("op") == "start") & value.startswith(old), F.concat(new, F.substring(value, F.length(old) + 1, F.length(value)))).when((F.col("op") == "end") & value.endswith(old), F.concat(F.left(value, F.length(value) - F.length(old)), new)).when((F.col("op") == "any") & value.contains(old), F.replace(value, old, new))
            tried = own.filter(value.isNotNull()).join(table, "attr").withColumn("v", made).filter("v IS NOT NULL AND v <> value")
            parts.append(tried.select("_id", "attr", "v", zero.alias("exact"), zero.alias("tokens"), F.col("p").alias("shape")))
        kinds = normal_forms(F.col("value"))
        tried = tries.select(_shape(F.col("value")).alias("s"), *[F.coalesce(e == F.col("clean"), F.lit(False)).cast("double").alias(k) for k, e in kinds.items()]).collect()
        rate = lambda rs, k: (sum(r[k] for r in rs) + 0.02) / (len(rs) + 1)
        by_shape: dict[str, list] = defaultdict(list)
        for r in tried:
            by_shape[r.s].append(r)
        learned = [(s, k, rate(rs, k)) for s, rs in by_shape.items() for k in kinds] + [("", k, rate(tried, k)) for k in kinds]
        good = {(s, k): p for s, k, p in learned if p > 0.04}
        options = F.array(*[F.struct(e.alias("v"), F.coalesce(*([F.when(_shape(F.col("value")) == s, p) for (s, kk), p in good.items() if kk == k and s] + [F.lit(good.get(("", k), 0.01))])).alias("p")) for k, e in kinds.items()])
        made = own.filter(F.col("value").isNotNull()).select("_id", "attr", "value", F.inline(options)).filter("v IS NOT NULL AND v <> value AND p > 0.02")
        parts.append(made.select("_id", "attr", "v", zero.alias("exact"), zero.alias("tokens"), F.col("p").alias("shape")))
    if "vicinity" in makers:
        rules = factor.learned(dirty, 0.05)
        rows = cells.select("_id", "attr").join(dirty, "_id")
        near = rows.select("_id", "attr", F.inline(F.array(*[F.struct(F.lit(a).alias("b_attr"), F.col(a).alias("b")) for a in ATTRS]))).filter("b IS NOT NULL AND b_attr <> attr")
        found = near.join(rules, ["attr", "b_attr", "b"]).filter("n > 1").groupBy("_id", "attr", "v").agg(F.max("p").alias("vicinity"), F.sum("p").alias("agree"))
        parts.append(found)
    if parts:  # one candidate may come from several makers
        every = reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), parts)
        out = materialize(every.groupBy("_id", "attr", "v").agg(*[F.max(f).alias(f) for f in FEATURES if f in every.columns]), "ensemble-candidates")
    else:
        out = own.select("_id", "attr", F.col("value").alias("v")).limit(0)
    if "domain" in makers:
        counts = long(dirty).filter("value IS NOT NULL").groupBy("attr", F.col("value").alias("v")).agg(F.count("*").alias("n"))
        share = counts.withColumn("domain", F.col("n") / F.sum("n").over(Window.partitionBy("attr"))).filter("n > 1").select("attr", "v", "domain")
        out = out.join(share, ["attr", "v"], "left")
    for f in FEATURES:
        out = out.withColumn(f, F.coalesce(F.col(f) if f in out.columns else zero, zero).cast("double"))
    out = out.join(own, ["_id", "attr"]).filter(~F.col("v").eqNullSafe(F.col("value")))
    top = F.row_number().over(Window.partitionBy("_id", "attr").orderBy(F.desc(F.col("exact") + F.col("tokens") + F.col("shape") + F.col("agree")), F.desc("domain"), "v"))
    return out.withColumn("_p", top).filter(F.col("_p") <= MOST).select("_id", "attr", "v", *FEATURES)


def correct(dirty: DataFrame, cells: DataFrame, labels: Labels, makers: tuple[str, ...] = MAKERS, threshold: float = 0.0) -> DataFrame:
    """_id, attr, repair, score for the given error cells."""
    truth = labels.draw()
    spark = dirty.sparkSession
    clean = {(t["_id"], t["attr"]): t["clean"] for t in truth if (t["dirty"] or "").strip() != (t["clean"] or "").strip()}
    every = materialize(proposals(dirty, cells, truth, makers), "proposals")
    data: dict[str, list] = defaultdict(list)
    if clean:
        ids = spark.createDataFrame(sorted(clean), "_id string, attr string")
        for r in every.join(F.broadcast(ids), ["_id", "attr"]).collect():
            data[r.attr].append(([r[f] for f in FEATURES], float(r.v == clean[r._id, r.attr])))
    prior = np.array([-2.5, 3.0, 2.0, 4.0, 2.5, 0.5, 1.0])
    score = None
    for a in ATTRS:
        w = prior.copy()
        if data[a]:
            x = np.array([[1.0, *f] for f, _ in data[a]])
            y = np.array([y for _, y in data[a]])
            for _ in range(200):  # pulled towards the prior weights, as labels are few
                p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
                w += 0.5 * (x.T @ (y - p) / len(y) - 0.02 * (w - prior))
        s = F.lit(float(w[0])) + sum((F.col(f) * float(c) for f, c in zip(FEATURES, w[1:])), F.lit(0.0))
        score = F.when(F.col("attr") == a, s) if score is None else score.when(F.col("attr") == a, s)
    chance = every.withColumn("score", 1 / (1 + F.exp(-score)))
    best = chance.filter(F.col("score") > threshold).groupBy("_id", "attr").agg(F.min(F.struct((-F.col("score")).alias("m"), "v")).alias("b"))
    return best.select("_id", "attr", F.col("b.v").alias("repair"), (-F.col("b.m")).alias("score"))
