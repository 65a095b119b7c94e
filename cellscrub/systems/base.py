"""What all systems share: blank handling, long form of dirty records, labels, and the yardsticks.

A system never sees clean values but through `Labels`, which gives them for chosen tuples and counts how many it gave,
and through the list of true error cells where the protocol grants it.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellscrub.operators.fd import Dependency
from cellscrub.schema import ATTRS

LABEL_BUDGET = 20


def present(c: Column) -> Column:
    """A value, or null where it is blank."""
    return F.nullif(F.trim(c), F.lit(""))


def records(pairs: DataFrame, attrs: tuple[str, ...] = ATTRS) -> DataFrame:
    """The dirty side of pairs under the attributes' own names, blanks as null."""
    return pairs.select("_id", *[present(F.col(f"d_{a}")).alias(a) for a in attrs])


def long(dirty: DataFrame, attrs: tuple[str, ...] = ATTRS, keep: tuple[str, ...] = ("_id",)) -> DataFrame:
    """_id, attr, value."""
    return dirty.select(*keep, F.inline(F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).alias("value")) for a in attrs])))


def rule_sides(dirty: DataFrame, fds: Sequence[Dependency], keep: tuple[str, ...] = ("_id",)) -> DataFrame:
    """rule, key, attr, v: every record's left side under every dependency, where it has no blank, with its right side.
    One scan serves all dependencies, however many there are."""
    if not fds:
        return long(dirty, keep=keep).select(*keep, F.lit(0).alias("rule"), F.lit("").alias("key"), "attr", F.col("value").alias("v")).limit(0)
    whole = lambda f: reduce(lambda x, y: x & y, (F.col(a).isNotNull() for a in f.lhs))
    sides = [F.struct(F.lit(i).alias("rule"), F.when(whole(f), F.to_json(F.array(*f.lhs))).alias("key"), F.lit(f.rhs).alias("attr"), F.col(f.rhs).alias("v")) for i, f in enumerate(fds)]
    return dirty.select(*keep, F.inline(F.array(*sides))).filter("key IS NOT NULL")


def side_counts(sides: DataFrame) -> DataFrame:
    """rule, key, v, n: rows by left side and known right side."""
    return sides.filter("v IS NOT NULL").groupBy("rule", "key", "v").agg(F.count("*").alias("n"))


def apply_best(dirty: DataFrame, fds: Sequence[Dependency], best: DataFrame) -> DataFrame:
    """Every right side takes the proposal (rule, key, v, n) with most support, the largest value on ties, all proposals
    from the same state of the records. `_id` is a key of dirty."""
    taken = sorted({f.rhs for f in fds})
    offers = rule_sides(dirty, fds).drop("v").join(best.select("rule", "key", F.struct("n", "v").alias("offer")), ["rule", "key"])
    won = offers.groupBy("_id").agg(*[F.max(F.when(F.col("attr") == a, F.col("offer")))["v"].alias(f"_w_{a}") for a in taken])
    return dirty.join(won, "_id", "left").select(*[F.coalesce(f"_w_{c}", c).alias(c) if c in taken else F.col(c) for c in dirty.columns])


@dataclass
class Labels:
    """Truth for a bounded number of tuples."""

    truth: DataFrame
    budget: int = LABEL_BUDGET
    asked: set[str] = field(default_factory=set)

    def of(self, ids: list[str]) -> list[dict]:
        """Rows (_id, attr, dirty, clean) of the tuples, as driver data of budget x attributes rows at most."""
        new = [i for i in ids if i not in self.asked][: max(0, self.budget - len(self.asked))]
        self.asked |= set(new)
        rows = self.truth.filter(F.col("_id").isin(sorted(self.asked))).select("_id", "attr", "dirty", "clean").collect()
        return [r.asDict() for r in rows]

    def draw(self, n: int | None = None) -> list[dict]:
        """The first n tuples in hash order."""
        ids = [r._id for r in self.truth.select("_id").distinct().orderBy(F.md5("_id"), "_id").limit(n or self.budget).collect()]
        return self.of(ids)


def flag_nothing(cells: DataFrame) -> DataFrame:
    return cells.select("_id", "attr").limit(0)


def flag_all(cells: DataFrame) -> DataFrame:
    return cells.select("_id", "attr")


def flag_missing(cells: DataFrame) -> DataFrame:
    return cells.filter(present(F.col("dirty")).isNull()).select("_id", "attr")


def repair_by_mode(cells: DataFrame) -> DataFrame:
    """Every cell's column mode (smallest value on ties)."""
    best = cells.filter(present(F.col("dirty")).isNotNull()).groupBy("attr", "dirty").agg(F.count("*").alias("n")).groupBy("attr").agg(F.min(F.struct((-F.col("n")).alias("n"), F.col("dirty").alias("v"))).alias("b"))
    return cells.join(F.broadcast(best), "attr").select("_id", "attr", F.col("b.v").alias("repair"), F.lit(1.0).alias("score"))


def pattern_of(c: Column) -> Column:
    """Character classes with runs collapsed: `10a` gives `9a`."""
    c = F.regexp_replace(F.regexp_replace(F.regexp_replace(c, r"\p{Lu}+", "A"), r"\p{Ll}+", "a"), r"\p{N}+", "9")
    return F.regexp_replace(c, r"\s+", " ")


def window_share(*keys: str) -> Column:
    return F.col("n") / F.sum("n").over(Window.partitionBy(*keys))
