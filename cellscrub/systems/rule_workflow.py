"""rule_workflow_repair: dependency, pattern and missing-value cleaners in an order planned on a coreset.

Rows that share a violated left side form a block. In blocks under `single_max` rows the rules vote together (support,
doubled for values of the column's usual pattern); in larger ones the dependency decides alone. The degrade ladder
changes the sampling mode, drops dependencies with long left sides and then moves `single_max`, until a run fits.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cellscrub.operators import fd as D
from cellscrub.operators import measure
from cellscrub.schema import ATTRS
from cellscrub.session import materialize
from cellscrub.systems.base import apply_best, long, pattern_of, rule_sides, side_counts

CORESET = 2000


@dataclass(frozen=True)
class Config:
    sampling: str = "coreset"
    max_lhs: int = 3
    single_max: int = 1000
    rounds: int = 2
    pattern_share: float = 0.02
    fill_share: float = 0.5


def coreset(dirty: DataFrame, k: int = CORESET) -> DataFrame:
    """The k most complete rows, spread over countries."""
    full = sum((F.col(a).isNotNull().cast("int") for a in ATTRS), F.lit(0))
    place = F.row_number().over(Window.partitionBy("country").orderBy(F.desc("_full"), F.md5("_id"), "_id"))
    return dirty.withColumn("_full", full).withColumn("_place", place).orderBy("_place", F.md5("_id"), "_id").limit(k).select(*dirty.columns)


def usual_patterns(dirty: DataFrame, share: float) -> DataFrame:
    """attr, pattern, n: the patterns that at least `share` of a column's values have."""
    counts = long(dirty).filter(F.col("value").isNotNull()).groupBy("attr", pattern_of(F.col("value")).alias("pattern")).agg(F.count("*").alias("n"))
    return counts.withColumn("total", F.sum("n").over(Window.partitionBy("attr"))).filter(F.col("n") >= share * F.col("total")).drop("total")


def pattern_flags(dirty: DataFrame, share: float = 0.02) -> DataFrame:
    """_id, attr of values whose pattern is unusual in their column."""
    usual = usual_patterns(dirty, share).select("attr", "pattern")
    have = long(dirty).filter(F.col("value").isNotNull()).withColumn("pattern", pattern_of(F.col("value")))
    return have.join(usual, ["attr", "pattern"], "left_anti").select("_id", "attr")


def _violations(sample: DataFrame, fds: list[D.Dependency], config: Config) -> dict[str, int]:
    """How many cells each cleaner would touch on the sample."""
    flagged = pattern_flags(sample, config.pattern_share).count()
    missing = sample.agg(sum((F.count_if(F.col(a).isNull()) for a in ATTRS), F.lit(0))).first()[0]
    groups = side_counts(rule_sides(sample, fds, ())).groupBy("rule", "key").agg((F.sum("n") - F.max("n")).alias("n"))
    wrong = groups.agg(F.sum("n")).first()[0] or 0
    return {"dependency": wrong, "pattern": flagged, "missing": missing}


def planned(dirty: DataFrame, fds: list[D.Dependency], config: Config) -> list[str]:
    """Cleaners by expected gain for their cost."""
    found = _violations(coreset(dirty) if config.sampling == "coreset" else dirty, fds, config)
    cost = {"dependency": 1.0 + len(fds) / 4, "pattern": 1.0, "missing": 1.0}
    return sorted(found, key=lambda c: (-found[c] / cost[c], c))


def _dependency(dirty: DataFrame, fds: list[D.Dependency], config: Config) -> DataFrame:
    block = Window.partitionBy("rule", "key")
    alike = F.count("*").over(Window.partitionBy("rule", "key", pattern_of(F.col("v")))) / F.count("*").over(block)
    vote = side_counts(rule_sides(dirty, fds, ())).withColumn("size", F.sum("n").over(block)).withColumn("alike", alike)
    score = F.when(F.col("size") < config.single_max, F.col("n") * (1 + F.col("alike"))).otherwise(F.col("n"))
    best = vote.withColumn("score", score).groupBy("rule", "key").agg(F.min(F.struct((-F.col("score")).alias("m"), "v")).alias("b"))
    return apply_best(dirty, fds, best.select("rule", "key", F.col("b.v").alias("v"), (-F.col("b.m")).cast("double").alias("n")))


def _cleared(dirty: DataFrame, config: Config) -> DataFrame:
    """Values of unusual patterns blanked, to be filled by the other cleaners."""
    usual = usual_patterns(dirty, config.pattern_share).groupBy("attr").agg(F.collect_set("pattern").alias("p"))
    sets = {r.attr: r.p for r in usual.collect()}  # at most 1 / pattern_share patterns a column
    keep = lambda a: pattern_of(F.col(a)).isin(*sets.get(a, [""]))
    return dirty.select(*[F.when(keep(c), F.col(c)).alias(c) if c in ATTRS else F.col(c) for c in dirty.columns])


def _filled(dirty: DataFrame, config: Config) -> DataFrame:
    """Missing values take the mode among rows of the same country, where it has fill_share of them."""
    modes = long(dirty, tuple(a for a in ATTRS if a != "country"), ("_id", "country")).filter(F.col("value").isNotNull() & F.col("country").isNotNull()).groupBy("country", "attr", "value").agg(F.count("*").alias("n"))
    modes = modes.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy("country", "attr")))
    best = modes.groupBy("country", "attr").agg(F.min(F.struct((-F.col("n")).alias("m"), "value", "share")).alias("b")).filter(F.col("b.share") >= config.fill_share)
    wide = best.groupBy("country").agg(*[F.max(F.when(F.col("attr") == a, F.col("b.value"))).alias(f"_m_{a}") for a in ATTRS if a != "country"])
    return dirty.join(wide, "country", "left").select(*[F.coalesce(c, f"_m_{c}").alias(c) if c in ATTRS and c != "country" else F.col(c) for c in dirty.columns])


def repaired(dirty: DataFrame, fds: list[D.Dependency], config: Config = Config()) -> DataFrame:
    fds = [f for f in fds if len(f.lhs) <= config.max_lhs]
    steps = {"dependency": lambda d: _dependency(d, fds, config), "pattern": lambda d: _cleared(d, config), "missing": lambda d: _filled(d, config)}
    order = planned(dirty, fds, config)
    for _ in range(config.rounds):
        for name in order:
            dirty = materialize(steps[name](dirty), "workflow")
    return dirty


def correct(dirty: DataFrame, fds: list[D.Dependency], config: Config = Config()) -> DataFrame:
    """_id, attr, repair (null where only cleared), score."""
    after = repaired(dirty, fds, config).select("_id", *[F.col(a).alias(f"r_{a}") for a in ATTRS])
    rows = F.array(*[F.struct(F.lit(a).alias("attr"), F.col(a).alias("was"), F.col(f"r_{a}").alias("repair")) for a in ATTRS])
    return dirty.join(after, "_id").select("_id", F.inline(rows)).filter(~F.col("was").eqNullSafe(F.col("repair"))).select("_id", "attr", "repair", F.lit(1.0).alias("score"))


def flags(dirty: DataFrame, repairs: DataFrame) -> DataFrame:
    """Changed cells; missing ones count, as they are a rule's violation whether or not they could be filled."""
    blank = long(dirty).filter(F.col("value").isNull()).select("_id", "attr")
    return repairs.select("_id", "attr").union(blank).distinct()


def detect(dirty: DataFrame, fds: list[D.Dependency], config: Config = Config()) -> DataFrame:
    return flags(dirty, correct(dirty, fds, config))


def ladder(config: Config = Config()) -> list[Config]:
    """The configurations to try, each with one more change."""
    first = replace(config, sampling="full" if config.sampling == "coreset" else "coreset")
    second = replace(first, max_lhs=2)
    return [config, first, second, replace(second, single_max=max(1, config.single_max // 10))]


def run_ladder(dirty: DataFrame, fds: list[D.Dependency], budget_s: float, config: Config = Config()) -> dict:
    """The first configuration that finishes within the budget, with its time."""
    import time

    for step, c in enumerate(ladder(config)):
        began = time.monotonic()
        got = measure.timed(correct(dirty, fds, c), budget_s)
        took = time.monotonic() - began
        if took <= budget_s and got["status"] == "ok":
            break
    return {"step": step, "sampling": c.sampling, "max_lhs": c.max_lhs, "single_max": c.single_max, "seconds": round(took, 3), "status": "ok" if took <= budget_s else "over_budget"}


