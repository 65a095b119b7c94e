"""fd_majority_repair: every right side takes the value best supported by its left side, dependencies in graph order.

Variants: order topological or support, weighting by rows or by distinct records, min_support, rounds for cycles.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellscrub.operators.fd import Dependency
from cellscrub.schema import ATTRS
from cellscrub.session import materialize
from cellscrub.systems.base import apply_best, rule_sides, side_counts

CYCLE_ROUNDS = 3


def plan(fds: list[Dependency]) -> list[tuple[list[Dependency], int]]:
    """Groups of dependencies with their rounds: attributes after those that determine them, cycles together."""
    attrs = sorted({f.rhs for f in fds} | {a for f in fds for a in f.lhs})
    reach = {a: {f.rhs for f in fds if a in f.lhs} for a in attrs}
    for k in attrs:
        for a in attrs:
            if k in reach[a]:
                reach[a] |= reach[k]
    cycle = {a: frozenset({b for b in reach[a] if a in reach[b]} | {a}) for a in attrs}
    above = {a: len({b for b in attrs if a in reach[b] and b not in cycle[a]}) for a in attrs}
    groups: dict[frozenset, list[Dependency]] = {}
    for f in fds:
        groups.setdefault(cycle[f.rhs], []).append(f)
    ordered = sorted(groups.items(), key=lambda g: (min(above[a] for a in g[0]), sorted(g[0])))
    return [(sorted(g, key=lambda f: (len(f.lhs), f.lhs, f.rhs)), CYCLE_ROUNDS if len(c) > 1 else 1) for c, g in ordered]


def best_values(dirty: DataFrame, fds: list[Dependency], weighting: str = "row", min_support: int = 1) -> DataFrame:
    """rule, key, v, n: the most frequent right side of every left side, smallest on ties."""
    counted = dirty.select(*ATTRS).distinct() if weighting == "distinct" else dirty
    counts = side_counts(rule_sides(counted, fds, ())).filter(F.col("n") >= min_support)
    best = counts.groupBy("rule", "key").agg(F.min(F.struct((-F.col("n")).alias("m"), "v")).alias("b"))
    return best.select("rule", "key", F.col("b.v").alias("v"), (-F.col("b.m")).cast("double").alias("n"))


def repaired(dirty: DataFrame, fds: list[Dependency], order: str = "topological", weighting: str = "row", min_support: int = 1, rounds: int | None = None) -> DataFrame:
    """The records after all repairs: in each group of the plan one aggregation and one join for all its dependencies, over
    the same written state, and one write a round."""
    if order == "topological":
        groups = plan(fds)
    else:
        groups = [([f], 1) for f in sorted(fds, key=lambda f: (len(f.lhs), f.lhs, f.rhs))]
    for group, times in groups:
        for _ in range(rounds or times):
            dirty = materialize(apply_best(dirty, group, best_values(dirty, group, weighting, min_support)), "fd-repair")
    return dirty


def correct(dirty: DataFrame, fds: list[Dependency], attrs: tuple[str, ...] = ATTRS, **options) -> DataFrame:
    """_id, attr, repair, score of the changed cells."""
    after = repaired(dirty, fds, **options).select("_id", *[F.col(a).alias(f"r_{a}") for a in attrs])
    both = dirty.join(after, "_id")
    rows = F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).alias("was"), F.col(f"r_{a}").alias("repair")) for a in attrs])
    return both.select("_id", F.inline(rows)).filter(~F.col("was").eqNullSafe(F.col("repair"))).select("_id", "attr", "repair", F.lit(1.0).alias("score"))


def flags(dirty: DataFrame, repairs: DataFrame) -> DataFrame:
    return repairs.select("_id", "attr")


def detect(dirty: DataFrame, fds: list[Dependency], **options) -> DataFrame:
    return flags(dirty, correct(dirty, fds, **options))
