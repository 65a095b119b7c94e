"""Functional dependencies: tests, level-wise discovery, summaries and counterexamples.

Discovery works on the distinct records. A level's candidate sets are tested together in grouping sets of bounded
width: a set X determines A when no group of X has two values of A, told by min and max with a sentinel for nulls.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellscrub.schema import ATTRS
from cellscrub.session import materialize

CHUNK = 8
_NULL = "\x00null"


@dataclass(frozen=True)
class Dependency:
    lhs: tuple[str, ...]
    rhs: str
    g3: float = 0.0


def _values(df: DataFrame, cols: Sequence[str]) -> DataFrame:
    return df.select(*[F.coalesce(F.col(c).cast("string"), F.lit(_NULL)).alias(c) for c in cols])


def holds(df: DataFrame, lhs: Sequence[str], rhs: str) -> DataFrame:
    """n_groups, n_violating, holds."""
    groups = _values(df, [*lhs, rhs]).groupBy(*lhs).agg((F.min(rhs) != F.max(rhs)).alias("bad"))
    return groups.agg(F.count("*").alias("n_groups"), F.count_if("bad").alias("n_violating"), (F.count_if("bad") == 0).alias("holds"))


def g3(df: DataFrame, lhs: Sequence[str], rhs: str) -> DataFrame:
    """n_rows, n_remove, g3: the share of rows to delete before the dependency holds."""
    per = _values(df, [*lhs, rhs]).groupBy(*lhs, rhs).agg(F.count("*").alias("n")).groupBy(*lhs).agg(F.sum("n").alias("n"), F.max("n").alias("best"))
    return per.agg(F.sum("n").alias("n_rows"), F.sum(F.col("n") - F.col("best")).alias("n_remove"), F.round(F.sum(F.col("n") - F.col("best")) / F.sum("n"), 6).alias("g3"))


def discover(df: DataFrame, attrs: Sequence[str] = ATTRS, max_lhs: int = 3, epsilon: float = 0.0) -> list[Dependency]:
    """Minimal dependencies with up to max_lhs attributes on the left; with epsilon > 0 approximate ones (g3)."""
    records = materialize(_values(df, attrs).groupBy(*attrs).agg(F.count("*").alias("_n")), "fd-records")
    total = records.agg(F.sum("_n")).first()[0] or 0
    found: list[Dependency] = []
    open_rhs = {a: [] for a in attrs}
    for size in range(1, max_lhs + 1):
        candidates = []
        for lhs in combinations(attrs, size):
            rhs = [a for a in attrs if a not in lhs and not any(set(f) <= set(lhs) for f in open_rhs[a])]
            if rhs:
                candidates.append((lhs, rhs))
        for at in range(0, len(candidates), CHUNK):
            part = candidates[at : at + CHUNK]
            for (lhs, rhs), errors in zip(part, _test(records, part, attrs, epsilon > 0)):
                for a, bad in zip(rhs, errors):
                    if (bad <= epsilon * total) if epsilon > 0 else bad == 0:
                        found.append(Dependency(lhs, a, round(bad / total, 6) if epsilon > 0 and total else 0.0))
                        open_rhs[a].append(lhs)
    return sorted(found, key=lambda f: (f.rhs, len(f.lhs), f.lhs))


def _test(records: DataFrame, part: list, attrs: Sequence[str], weighted: bool) -> list[list[float]]:
    """For each candidate, per right side the number of violating groups, or of rows to remove."""
    if weighted:
        out = []
        for lhs, rhs in part:
            sums = []
            for a in rhs:
                per = records.groupBy(*lhs, a).agg(F.sum("_n").alias("n")).groupBy(*lhs).agg((F.sum("n") - F.max("n")).alias("r"))
                sums.append(float(per.agg(F.sum("r")).first()[0] or 0))
            out.append(sums)
        return out
    keys = [f"_k{a}" for a in attrs]
    both = records.select(*attrs, *[F.col(a).alias(k) for a, k in zip(attrs, keys)])
    sets = [[F.col(f"_k{a}") for a in lhs] for lhs, _ in part]
    bounds = [f.alias(n) for a in attrs for f, n in ((F.min(a), f"lo_{a}"), (F.max(a), f"hi_{a}"))]
    groups = both.groupingSets(sets, *[F.col(k) for k in keys]).agg(F.grouping_id().alias("gid"), *bounds)
    rows = {r.gid: r for r in groups.groupBy("gid").agg(*[F.count_if(F.col(f"lo_{a}") != F.col(f"hi_{a}")).alias(a) for a in attrs]).collect()}
    out = []
    for lhs, rhs in part:
        gid = sum(0 if a in lhs else 1 << (len(attrs) - 1 - i) for i, a in enumerate(attrs))
        out.append([float(rows[gid][a]) if gid in rows else 0.0 for a in rhs])
    return out


def as_frame(spark, found: list[Dependency]) -> DataFrame:
    return spark.createDataFrame([(",".join(f.lhs), f.rhs, len(f.lhs), f.g3) for f in found], "lhs string, rhs string, lhs_size int, g3 double")


def summary(spark, found: list[Dependency]) -> DataFrame:
    """rhs, lhs_size, n."""
    return as_frame(spark, found).groupBy("rhs", "lhs_size").agg(F.count("*").alias("n"))


def select(found: list[Dependency], max_lhs: int = 3, scope: str = "all") -> list[Dependency]:
    """Those with a short left side; scope 'country' keeps the ones towards country and its code."""
    return [f for f in found if len(f.lhs) <= max_lhs and (scope == "all" or f.rhs in ("country", "country_code"))]


def slice_only(spark, of_slice: list[Dependency], of_all: list[Dependency]) -> DataFrame:
    """Dependencies that hold in a slice but do not follow from one that holds everywhere."""
    extra = [f for f in of_slice if not any(g.rhs == f.rhs and set(g.lhs) <= set(f.lhs) for g in of_all)]
    return as_frame(spark, extra)


def counterexamples(df: DataFrame, lhs: Sequence[str], rhs: str) -> DataFrame:
    """lhs values with more than one rhs value, and those values."""
    pairs = df.select(*lhs, rhs).distinct()
    return pairs.groupBy(*lhs).agg(F.count("*").alias("n_values"), F.array_join(F.array_sort(F.collect_list(rhs)), "|").alias("rhs_values")).filter("n_values > 1")


def minimal_sql(source: str, attrs: Sequence[str] = ATTRS, max_lhs: int = 3) -> str:
    """`found`: lhs, rhs, lhs_size of the minimal dependencies, by plain distinct counts in DuckDB."""
    sets = [x for size in range(1, max_lhs + 1) for x in combinations(attrs, size)]
    row = lambda cols: "(" + ", ".join(cols) + ")"
    cols = [f"count(DISTINCT {row(x)}) AS s{i}" for i, x in enumerate(sets)]
    tests = []
    for i, x in enumerate(sets):
        cols += [f"count(DISTINCT {row((*x, a))}) AS s{i}_{a}" for a in attrs if a not in x]
        tests += [f"SELECT '{','.join(x)}' AS lhs, '{a}' AS rhs, {len(x)} AS lhs_size, s{i} = s{i}_{a} AS ok FROM counts" for a in attrs if a not in x]
    return f"""
records AS MATERIALIZED (SELECT DISTINCT {", ".join(attrs)} FROM {source}), counts AS MATERIALIZED (SELECT {", ".join(cols)} FROM records),
valid AS MATERIALIZED (SELECT lhs, rhs, lhs_size FROM ({" UNION ALL ".join(tests)}) WHERE ok),
found AS MATERIALIZED (
  SELECT * FROM valid v WHERE NOT EXISTS (SELECT 1 FROM valid o WHERE o.rhs = v.rhs AND o.lhs_size < v.lhs_size AND list_has_all(string_split(v.lhs, ','), string_split(o.lhs, ',')))
)"""
