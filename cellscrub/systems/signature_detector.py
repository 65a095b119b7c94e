"""signature_detector: many weak strategies per cell, clustered, labelled by a few tuples, propagated and learned.

Every strategy is a column expression over the cell and the frequencies of its value. Cells with the same column and
the same bits collapse into one weighted signature, so clustering, tuple choice and the classifier see a table whose
size is bounded by the signatures that occur, whatever the number of rows; the result is a lookup of signature to flag.
"""

from __future__ import annotations

from collections import defaultdict

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cellscrub.functions import text as X
from cellscrub.operators.fd import Dependency
from cellscrub.schema import ATTRS
from cellscrub.session import materialize
from cellscrub.systems.base import Labels, long, pattern_of, rule_sides, side_counts

FAMILIES = ("frequency", "pattern", "length", "numeric", "dependency", "dictionary", "missing", "encoding")
POOL = 2000


def signatures(dirty: DataFrame, fds: list[Dependency], families: tuple[str, ...] = FAMILIES, attrs: tuple[str, ...] = ATTRS) -> DataFrame:
    """_id, attr, value, bits: one character for each strategy; three aggregations over (attr, value) counts."""
    cells = long(dirty, attrs)
    values = cells.groupBy("attr", "value").agg(F.count("*").alias("n"))
    column = Window.partitionBy("attr")
    known = values.withColumn("total", F.sum("n").over(column)).withColumn("pattern", pattern_of(F.col("value")))
    known = known.withColumn("pn", F.sum("n").over(Window.partitionBy("attr", "pattern")))
    size, number = F.length("value"), F.try_to_number(F.regexp_extract("value", "^([0-9]{1,9})$", 1), F.lit("999999999")).cast("double")
    weighted = known.withColumn("size", size).withColumn("num", number)
    stats = weighted.groupBy("attr").agg(
        (F.sum(F.col("size") * F.col("n")) / F.sum(F.when(F.col("size").isNotNull(), F.col("n")))).alias("m"),
        F.sqrt(F.sum(F.col("size") * F.col("size") * F.col("n")) / F.sum(F.when(F.col("size").isNotNull(), F.col("n")))).alias("q"),
        F.sum(F.when(F.col("num").isNotNull(), F.col("n")).otherwise(0)).alias("nums"),
        F.percentile_approx("num", F.array(F.lit(0.25), F.lit(0.75)), F.lit(1000)).alias("iqr"),
    )
    known = weighted.join(F.broadcast(stats), "attr")
    z = F.abs(F.col("size") - F.col("m")) / F.sqrt(F.greatest(F.col("q") * F.col("q") - F.col("m") * F.col("m"), F.lit(0.01)))
    spread = F.col("iqr")[1] - F.col("iqr")[0]
    off = (F.col("nums") > 0.5 * F.col("total")) & (F.col("num").isNull() | (F.col("num") < F.col("iqr")[0] - 1.5 * spread) | (F.col("num") > F.col("iqr")[1] + 1.5 * spread))
    toks = X.tokens(F.coalesce("value", F.lit("")))
    own = {
        "frequency": [F.col("n") <= 1, *[F.col("n") / F.col("total") < p for p in (0.0001, 0.0005, 0.002, 0.01, 0.05)]],
        "pattern": [F.col("pn") / F.col("total") < p for p in (0.001, 0.01, 0.05, 0.2)],
        "length": [z > t for t in (1.0, 2.0, 3.0)],
        "numeric": [off],
        "dictionary": [F.arrays_overlap(toks, F.array(*[F.lit(k) for k in sorted(X.ABBREVIATIONS)])), F.arrays_overlap(toks, F.array(*[F.lit(k) for k in sorted(X.ALIASES)]))],
        "missing": [F.col("value").isNull()],
        "encoding": [X.maybe_encoded(F.coalesce("value", F.lit(""))), F.coalesce(F.col("value") == F.upper("value"), F.lit(False)), F.coalesce(F.col("value") == F.lower("value"), F.lit(False))],
    }
    bits = [F.when(F.coalesce(c, F.lit(False)), "1").otherwise("0") for f in families if f in own for c in own[f]]
    table = known.select(F.col("attr").alias("_a"), F.col("value").alias("_v"), F.concat(*bits).alias("bits"))
    out = cells.join(table, (F.col("attr") == F.col("_a")) & F.col("value").eqNullSafe(F.col("_v"))).drop("_a", "_v")
    if "dependency" in families and fds:
        majority = violating_minority(dirty, fds)
        out = out.join(majority, ["_id", "attr"], "left").withColumn("bits", F.concat("bits", F.when(F.col("minor"), "1").otherwise("0"), F.when(F.col("minor").isNotNull(), "1").otherwise("0"))).drop("minor")
    return out


def violating_minority(dirty: DataFrame, fds: list[Dependency]) -> DataFrame:
    """_id, attr, minor: cells of violated dependencies, and whether their value is not the group's majority; one pass for
    all dependencies."""
    sides = rule_sides(dirty, fds)
    group = Window.partitionBy("rule", "key")
    counts = side_counts(sides).withColumn("top", F.max("n").over(group)).withColumn("k", F.count("*").over(group))
    bad = counts.filter("k > 1").select("rule", "key", "v", (F.col("n") < F.col("top")).alias("minor"))
    return sides.join(bad, ["rule", "key", "v"]).groupBy("_id", "attr").agg(F.max("minor").alias("minor"))


def clusters(weighted: dict[str, int], k: int) -> dict[str, int]:
    """Agglomerative (single driver table): signatures to cluster numbers, merging the closest by weighted Hamming."""
    groups = [[s] for s in sorted(weighted, key=lambda s: (-weighted[s], s))]
    far = lambda a, b: sum(x != y for x, y in zip(a[0], b[0]))
    if len(groups) > 400:  # rare signatures join the nearest of the frequent ones
        heads, rest = groups[:400], groups[400:]
        for g in rest:
            min(heads, key=lambda h: far(h, g)).extend(g)
        groups = heads
    while len(groups) > k:
        best = min(((far(a, b), i, j) for i, a in enumerate(groups) for j, b in enumerate(groups[:i])), key=lambda t: t)
        _, i, j = best
        groups[j] = sorted(groups[j] + groups[i], key=lambda s: (-weighted[s], s))
        del groups[i]
    return {s: n for n, g in enumerate(groups) for s in g}


def choose_tuples(pool: dict[str, dict[str, int]], budget: int) -> list[str]:
    """Greedy: the tuple whose cells lie in most clusters without a label, again and again."""
    covered: set[tuple[str, int]] = set()
    out: list[str] = []
    for _ in range(min(budget, len(pool))):
        best = max((i for i in sorted(pool) if i not in out), key=lambda i: sum((a, c) not in covered for a, c in pool[i].items()))
        out.append(best)
        covered |= set(pool[best].items())
    return out


def _learned(signs: list[str], labelled: dict[str, float], weighted: dict[str, int]) -> dict[str, bool]:
    """Per column: a signature's flag by the nearest labelled ones, closer ones counting more."""
    out = {}
    for s in signs:
        if not labelled:
            out[s] = False
            continue
        score = weight = 0.0
        for t, y in labelled.items():
            d = sum(a != b for a, b in zip(s, t))
            w = 2.0 ** (-2 * d)
            score, weight = score + w * y, weight + w
        out[s] = score / weight > 0.5
    return out


def detect(dirty: DataFrame, fds: list[Dependency], labels: Labels, families: tuple[str, ...] = FAMILIES, propagate: bool = True) -> DataFrame:
    """_id, attr of the flagged cells."""
    spark = dirty.sparkSession
    cells = materialize(signatures(dirty, fds, families), "signatures")
    collapsed = cells.groupBy("attr", "bits").agg(F.count("*").alias("n"), F.count_if(F.col("value").isNull()).alias("blank")).collect()
    weighted: dict[str, dict[str, int]] = defaultdict(dict)
    for r in collapsed:
        weighted[r.attr][r.bits] = r.n
    budget = labels.budget
    cluster = {a: clusters(w, budget + 1) for a, w in weighted.items()}
    pool_ids = cells.select("_id").distinct().orderBy(F.md5("_id"), "_id").limit(POOL)
    pool: dict[str, dict[str, int]] = defaultdict(dict)
    bits_of: dict[tuple[str, str], str] = {}
    for r in cells.join(pool_ids, "_id").select("_id", "attr", "bits").collect():
        pool[r._id][r.attr] = cluster[r.attr][r.bits]
        bits_of[r._id, r.attr] = r.bits
    truth = labels.of(choose_tuples(pool, budget))
    seen: dict[str, dict[str, list[float]]] = defaultdict(lambda: defaultdict(list))
    for t in truth:
        wrong = float((t["dirty"] or "").strip() != (t["clean"] or "").strip())
        seen[t["attr"]][bits_of[t["_id"], t["attr"]]].append(wrong)
    rows = []
    for a, w in weighted.items():
        own = {s: sum(y) / len(y) for s, y in seen[a].items()}
        if propagate:
            by_cluster: dict[int, list[float]] = defaultdict(list)
            for s, y in seen[a].items():
                by_cluster[cluster[a][s]] += y
            pure = {c: y for c, y in by_cluster.items() if len(set(y)) == 1}
            own |= {s: pure[c][0] for s, c in cluster[a].items() if c in pure and s not in own}
        rows += [(a, s, bool(f)) for s, f in _learned(list(w), own, w).items()]
    lookup = spark.createDataFrame(rows, "attr string, bits string, flag boolean").filter("flag").select("attr", "bits")
    blank = F.col("value").isNull()
    return cells.join(F.broadcast(lookup), ["attr", "bits"], "left_semi").select("_id", "attr").union(cells.filter(blank).select("_id", "attr")).distinct()


def ablation(dirty: DataFrame, fds: list[Dependency], make_labels) -> dict[str, DataFrame]:
    """Flags with each strategy family left out."""
    return {f: detect(dirty, fds, make_labels(), tuple(x for x in FAMILIES if x != f)) for f in FAMILIES}


