"""staged_cleaner, auto_slices, augment_balance and advisor: combinations of the systems.

Stages run from cheap to costly; each gets only the cells that none before it repaired.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellscrub.operators.fd import Dependency
from cellscrub.schema import ATTRS
from cellscrub.session import materialize
from cellscrub.systems import corrector_ensemble, fd_majority, record_prompt
from cellscrub.systems.base import Labels, long


def simple_forms(c: Column) -> list[Column]:
    """Candidate repairs in order of rank: the general normal forms, dashes as blanks, no punctuation at the end."""
    kinds = corrector_ensemble.normal_forms(c)
    return [kinds["decoded"], kinds["titled"], kinds["upper"], F.replace(c, F.lit("-"), F.lit(" ")), F.regexp_replace(c, r"[\p{P}]+$", ""), kinds["lower"]]


def simple_rules(dirty: DataFrame, cells: DataFrame) -> DataFrame:
    """Entity decoding, full upper or lower case, and dashes, where the repaired value is one the column already has."""
    known = long(dirty).filter("value IS NOT NULL").groupBy("attr", F.col("value").alias("repair")).agg(F.count("*").alias("n")).filter("n > 1")
    options = F.array(*[F.struct(F.lit(i).alias("rank"), form.alias("repair")) for i, form in enumerate(simple_forms(F.col("value")))])
    own = cells.select("_id", "attr").join(long(dirty), ["_id", "attr"]).filter("value IS NOT NULL")
    tried = own.select("_id", "attr", "value", F.inline(options)).filter("repair <> value").join(known, ["attr", "repair"])
    best = tried.groupBy("_id", "attr").agg(F.min(F.struct((-F.col("n")).alias("m"), "rank", "repair")).alias("b"))
    return best.select("_id", "attr", F.col("b.repair").alias("repair"), F.lit(1.0).alias("score"))


def correct(dirty: DataFrame, cells: DataFrame, fds: list[Dependency], labels: Labels, completer=record_prompt.RulebookCompleter(), confident: float = 0.6) -> DataFrame:
    """_id, attr, repair, score, stage."""
    left = materialize(cells.select("_id", "attr"), "staged")
    out = None
    stages = {
        "rules": lambda c: simple_rules(dirty, c),
        "dependencies": lambda c: fd_majority.correct(dirty, fds, min_support=2).join(c, ["_id", "attr"], "left_semi"),
        "ensemble": lambda c: corrector_ensemble.correct(dirty, c, labels, threshold=confident),
        "prompt": lambda c: record_prompt.correct(dirty, c, completer),
    }
    for stage, run in stages.items():
        found = materialize(run(left).select("_id", "attr", "repair", "score").withColumn("stage", F.lit(stage)), f"stage-{stage}")
        out = found if out is None else out.unionByName(found)
        left = materialize(left.join(found, ["_id", "attr"], "left_anti"), "staged")
    return out


def auto_slices(dirty: DataFrame, by: tuple[str, ...] = ("country", "region", "locality"), least: int = 20) -> DataFrame:
    """by, mean drop of the other columns' entropy when sliced by it, and the number of slices of usable size."""
    cells = long(dirty, ATTRS).filter("value IS NOT NULL")

    def entropy(df: DataFrame, keys: list[str]) -> DataFrame:
        counts = df.groupBy(*keys, "attr", "value").agg(F.count("*").alias("n"))
        total = F.sum("n").over(Window.partitionBy(*keys, "attr"))
        p = F.col("n") / total
        return counts.select(*keys, "attr", "n", (-p * F.log2(p)).alias("h"), F.col("n").alias("w")).groupBy(*keys, "attr").agg(F.sum("h").alias("h"), F.sum("w").alias("w"))

    whole = entropy(cells, []).select("attr", F.col("h").alias("h0"))
    out = None
    for c in by:
        sliced = entropy(long(dirty, tuple(a for a in ATTRS if a != c), ("_id", c)).filter(f"value IS NOT NULL AND {c} IS NOT NULL").withColumnRenamed(c, "slice"), ["slice"])
        drop = sliced.join(whole, "attr").groupBy("attr").agg((F.max("h0") - F.sum(F.col("h") * F.col("w")) / F.sum("w")).alias("drop"), F.max("h0").alias("h0"))
        size = dirty.filter(F.col(c).isNotNull()).groupBy(c).count().agg(F.count_if(F.col("count") >= least).alias("usable"), F.count("*").alias("slices"))
        row = drop.agg(F.round(F.avg(F.when(F.col("h0") > 0, F.col("drop") / F.col("h0")).otherwise(0)), 6).alias("mean_drop")).crossJoin(F.broadcast(size)).select(F.lit(c).alias("by"), "mean_drop", "usable", "slices")
        out = row if out is None else out.unionByName(row)
    return out


def augment(dirty: DataFrame, certified: DataFrame, weight: int = 1) -> DataFrame:
    """dirty with certified records (attributes only) added `weight` times under ids of their own, to balance evidence."""
    extra = certified.select(F.concat(F.lit("certified-"), F.md5(F.concat_ws("|", *ATTRS))).alias("_id"), *ATTRS).withColumn("_r", F.explode(F.sequence(F.lit(1), F.lit(weight))))
    return dirty.select("_id", *ATTRS).unionByName(extra.withColumn("_id", F.concat_ws("-", "_id", F.col("_r").cast("string"))).drop("_r"))


def advise(rows: int, error_rate: float, fd_coverage: float, distinct_ratio: float) -> list[tuple[int, str, str]]:
    """Ordered recommendation from metadata: (rank, system, reason)."""
    out = [("rules", "cheap and precise on form errors at any size")]
    if fd_coverage >= 0.25 and error_rate <= 0.5:
        out.append(("fd_majority", "dependencies cover enough attributes and most evidence is clean"))
    if distinct_ratio <= 0.3:
        out.append(("corrector_ensemble", "values repeat, so the table itself holds evidence"))
    if rows <= 1_000_000 or distinct_ratio <= 0.1:
        out.append(("record_prompt", "the number of distinct records keeps calls affordable"))
    else:
        out.append(("column_imputer", "linear cost where prompts would take too long"))
    return [(i + 1, s, r) for i, (s, r) in enumerate(out)]
