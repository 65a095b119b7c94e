"""Profiles of an edition: distinct values and records, co-location, category shares, spread over slices."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellscrub.schema import ATTRS, CATEGORIES
from cellscrub.session import materialize


def _long(df: DataFrame, cols: tuple[str, ...]) -> DataFrame:
    return df.select(F.inline(F.array(*[F.struct(F.lit(c).alias("attr"), F.col(c).cast("string").alias("value")) for c in cols])))


def distinct_counts(df: DataFrame, cols: tuple[str, ...] = ("_id", *ATTRS, "graph_iri"), approx: bool = False) -> DataFrame:
    """attr, n_distinct. Exact: one (attr, value) aggregation with map-side combine; approx: mergeable sketches."""
    if approx:
        return _long(df, cols).groupBy("attr").agg(F.hll_sketch_estimate(F.hll_sketch_agg("value", F.lit(14))).alias("n_distinct"))
    return _long(df, cols).filter(F.col("value").isNotNull()).distinct().groupBy("attr").agg(F.count("*").alias("n_distinct"))


def distinct_records(df: DataFrame, cols: tuple[str, ...] = ATTRS) -> DataFrame:
    """n_rows, n_records, rows_per_record."""
    per = df.groupBy(*cols).agg(F.count("*").alias("n"))
    return per.agg(F.sum("n").alias("n_rows"), F.count("*").alias("n_records"), F.round(F.avg("n"), 6).alias("rows_per_record"))


def colocation(df: DataFrame, who: str = "name", where: tuple[str, ...] = ATTRS[1:]) -> DataFrame:
    """n_addresses, mean_names, max_names: how many names share one address."""
    pairs = df.select(who, *where).distinct().groupBy(*where).agg(F.count("*").alias("names"))
    return pairs.agg(F.count("*").alias("n_addresses"), F.round(F.avg("names"), 6).alias("mean_names"), F.max("names").alias("max_names"))


def distribution(df: DataFrame, col: str) -> DataFrame:
    """Value, n, share."""
    counts = df.groupBy(col).agg(F.count("*").alias("n"))
    total = counts.agg(F.sum("n").alias("total"))
    return counts.crossJoin(F.broadcast(total)).select(col, "n", F.round(F.col("n") / F.col("total"), 6).alias("share"))


def error_rate(classified: DataFrame) -> DataFrame:
    """n_cells, n_clean, n_errors, error_rate."""
    bad = (F.col("category") != "clean").cast("long")
    return classified.agg(F.count("*").alias("n_cells"), F.sum(1 - bad).alias("n_clean"), F.sum(bad).alias("n_errors"), F.round(F.avg(bad), 6).alias("error_rate"))


def category_shares(counted: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """by, category, n, share from (by, category, n) counts."""
    per = counted.groupBy(*by, "category").agg(F.sum("n").alias("n"))
    total = counted.groupBy(*by).agg(F.sum("n").alias("total")) if by else counted.agg(F.sum("n").alias("total"))
    joined = per.join(total, list(by)) if by else per.crossJoin(F.broadcast(total))
    return joined.select(*by, "category", "n", F.round(F.col("n") / F.col("total"), 6).alias("share"))


def slice_table(classified: DataFrame, slices: tuple[str, ...]) -> DataFrame:
    """slice_col, slice, category, n for all slices at once (grouping sets), and for everything under 'all'."""
    sets = classified.select(*[F.col(s).alias(f"_{i}") for i, s in enumerate(slices)], "category").groupingSets([[F.col(f"_{i}"), F.col("category")] for i in range(len(slices))] + [[F.col("category")]], *[f"_{i}" for i in range(len(slices))], "category").agg(F.count("*").alias("n"), *[F.grouping(f"_{i}").alias(f"g{i}") for i in range(len(slices))])
    name, value = F.lit("all"), F.lit("all")
    for i, s in enumerate(slices):
        name = F.when(F.col(f"g{i}") == 0, s).otherwise(name)
        value = F.when(F.col(f"g{i}") == 0, F.col(f"_{i}")).otherwise(value)
    return sets.select(name.alias("slice_col"), value.alias("slice"), "category", "n")


def attribute_cube(classified: DataFrame) -> DataFrame:
    """attr, category, n over the cube of both ('all' for a rolled-up side)."""
    cube = classified.cube("attr", "category").agg(F.count("*").alias("n"), F.grouping("attr").alias("ga"), F.grouping("category").alias("gc"))
    return cube.select(F.when(F.col("ga") == 1, "all").otherwise(F.col("attr")).alias("attr"), F.when(F.col("gc") == 1, "all").otherwise(F.col("category")).alias("category"), "n")


def slice_spread(counted: DataFrame, by: str) -> DataFrame:
    """category, least, median and greatest share over the slices of `by`."""
    counted = materialize(counted.groupBy(by, "category").agg(F.sum("n").alias("n")), "spread")
    total = counted.groupBy(by).agg(F.sum("n").alias("total"))
    every = counted.select(by).distinct().crossJoin(F.broadcast(counted.sparkSession.createDataFrame([(c,) for c in CATEGORIES], "category string")))
    per = counted.groupBy(by, "category").agg(F.sum("n").alias("n"))
    shares = every.join(per, [by, "category"], "left").join(total, by).withColumn("share", F.coalesce("n", F.lit(0)) / F.col("total"))
    return shares.groupBy("category").agg(*[F.round(f, 6).alias(n) for n, f in (("least", F.min("share")), ("median", F.percentile("share", F.lit(0.5))), ("greatest", F.max("share")))])


def distinct_ratio(df: DataFrame, by: str, cols: tuple[str, ...] = ATTRS) -> DataFrame:
    """by, attr, ratio of distinct values to rows."""
    long = df.select(F.col(by).alias("slice"), F.inline(F.array(*[F.struct(F.lit(c).alias("attr"), F.col(c).alias("value")) for c in cols])))
    counts = long.groupBy("slice", "attr", "value").agg(F.count("*").alias("n")).groupBy("slice", "attr").agg(F.count("value").alias("d"), F.sum("n").alias("n"))
    return counts.select("slice", "attr", F.round(F.col("d") / F.col("n"), 6).alias("ratio"))


def variant_usage(cells: DataFrame, by: str, pattern: str) -> DataFrame:
    """by, share of dirty and of clean values that contain the pattern."""
    one = lambda c: F.round(F.avg(F.coalesce(F.col(c).rlike(pattern), F.lit(False)).cast("int")), 6)
    return cells.groupBy(by).agg(one("dirty").alias("dirty_share"), one("clean").alias("clean_share"))
