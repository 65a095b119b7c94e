"""Samples, slices and error-rate control; all draws are hashes of ids, so no result depends on partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellscrub.schema import ATTRS


def hash_order(seed: int, *cols: str) -> Column:
    return F.md5(F.concat_ws("|", F.lit(str(seed)), *[F.col(c) for c in cols]))


def fixed(df: DataFrame, k: int, seed: int = 1, key: str = "_id") -> DataFrame:
    """k rows in hash order: a top-k, no full sort."""
    return df.withColumn("_h", hash_order(seed, key)).orderBy("_h").limit(k).drop("_h")


def bernoulli(df: DataFrame, share: float, seed: int = 1, key: str = "_id") -> DataFrame:
    """About share of the rows; map-only."""
    return df.filter(F.conv(F.substring(hash_order(seed, key), 1, 8), 16, 10).cast("long") < int(share * 2**32))


def stratified(df: DataFrame, strata: tuple[str, ...], k: int, seed: int = 1, key: str = "_id") -> DataFrame:
    """k rows that keep the strata's shares, remainders by size of the fraction (then by stratum)."""
    counts = df.groupBy(*strata).agg(F.count("*").alias("_n"))
    total = counts.agg(F.sum("_n").alias("_total"))
    # in whole numbers, so that equal remainders are equal
    quota = counts.crossJoin(F.broadcast(total)).withColumn("_part", F.col("_n") * k % F.col("_total")).withColumn("_base", ((F.col("_n") * k - F.col("_part")) / F.col("_total")).cast("long"))
    # strata are few: one window over them deals out what is left
    rest = F.lit(k) - F.sum("_base").over(Window.partitionBy(F.lit(0)))
    rank = F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc("_part"), *strata))
    quota = quota.withColumn("_quota", F.col("_base") + (rank <= rest).cast("long")).select(*strata, "_quota")
    place = F.row_number().over(Window.partitionBy(*strata).orderBy(hash_order(seed, key)))
    joined = df.join(quota, list(strata))
    return joined.withColumn("_place", place).filter("_place <= _quota").drop("_place", "_quota")


def balanced(df: DataFrame, by: str, groups: int, per: int, seed: int = 1, key: str = "_id") -> DataFrame:
    """per rows of each of the largest groups."""
    top = df.groupBy(by).agg(F.count("*").alias("_n")).orderBy(F.desc("_n"), by).limit(groups).select(by)
    place = F.row_number().over(Window.partitionBy(by).orderBy(hash_order(seed, key)))
    return df.join(top, by).withColumn("_place", place).filter(F.col("_place") <= per).drop("_place")


def dedup_dirty(pairs: DataFrame, attrs: tuple[str, ...] = ATTRS) -> DataFrame:
    """Of records whose dirty sides are alike, the one with the smallest id."""
    first = pairs.groupBy(*[f"d_{a}" for a in attrs]).agg(F.min("_id").alias("_id")).select("_id")
    return pairs.join(first, "_id", "left_semi")


def by(df: DataFrame, col: str, value) -> DataFrame:
    """A slice: an equality that reaches the scan."""
    return df.filter(F.col(col) == F.lit(value))


def restore(cells: DataFrame, target: float, seed: int = 1, mode: str = "global", strata: tuple[str, ...] = ("attr", "category")) -> DataFrame:
    """cells in which erroneous ones were turned back to clean until their share is target.

    global: exactly E - round(target N) in one hash order; proportional: the same share of every stratum (rounded);
    bernoulli: by a hash threshold, map-only. One seed's samples at lower rates lie inside those at higher rates.
    """
    bad = F.col("category") != "clean"
    order = hash_order(seed, "_id", "attr")
    n, e = cells.agg(F.count("*"), F.count_if(bad)).first()
    keep = min(e, int(target * n + 0.5))
    if mode == "bernoulli":
        kept = F.conv(F.substring(order, 1, 8), 16, 10).cast("long") < int((keep / e if e else 1) * 2**32)
        out = cells.withColumn("_keep", kept)
    elif mode == "proportional":
        share = keep / e if e else 1.0
        w = Window.partitionBy(*strata)
        place = F.row_number().over(w.orderBy(order))
        out = cells.filter(bad).withColumn("_keep", place <= F.floor(F.count("*").over(w) * share + 0.5)).unionByName(cells.filter(~bad).withColumn("_keep", F.lit(True)))
    else:
        # the hash that the keep-th error has is the threshold: a top-k of single values
        last = cells.filter(bad).select(order.alias("h")).orderBy("h").limit(keep).agg(F.max("h")).first()[0] if keep else None
        out = cells.withColumn("_keep", order <= F.lit(last) if last is not None else F.lit(False))
    back = bad & ~F.col("_keep")
    return out.withColumn("dirty", F.when(back, F.col("clean")).otherwise(F.col("dirty"))).withColumn("category", F.when(back, "clean").otherwise(F.col("category"))).drop("_keep")
