"""Filters between extraction and the two editions, and the funnel they make."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cellscrub.functions import text as X
from cellscrub.schema import ATTRS, CORE_ATTRS


def has_core_signal(street: str = "streetAddress", locality: str = "addressLocality", postcode: str = "postalCode") -> Column:
    """Street, locality or postcode is not blank."""
    return F.coalesce(*[F.nullif(F.trim(F.col(c)), F.lit("")) for c in (street, locality, postcode)]).isNotNull()


def retention(raw: DataFrame, by: str = "source") -> DataFrame:
    kept = has_core_signal().cast("long")
    return raw.groupBy(by).agg(F.count("*").alias("n_before"), F.sum(kept).alias("n_after"), F.round(F.avg(kept), 6).alias("retention"))


def matched_only(pairs: DataFrame) -> DataFrame:
    return pairs.filter(F.col("c_country").isNotNull())


def complete(pairs: DataFrame, side: str = "c") -> DataFrame:
    """One side (the clean one) complete in all but the name; a blank value is none."""
    return pairs.filter(reduce(lambda x, y: x & y, (F.coalesce(F.trim(F.col(f"{side}_{a}")) != "", F.lit(False)) for a in CORE_ATTRS)))


def drop_page_duplicates(pairs: DataFrame) -> DataFrame:
    """One row per page and identical dirty and clean values, that with the smallest id."""
    values = [f"{s}_{a}" for a in ATTRS for s in ("d", "c")]
    same = F.md5(F.concat_ws("\x1f", "graph_iri", *[F.coalesce(F.col(v), F.lit("\x00")) for v in values]))
    first = F.row_number().over(Window.partitionBy("_same").orderBy("_id"))
    return pairs.withColumn("_same", same).withColumn("_n", first).filter("_n = 1").drop("_n", "_same")


def edition_plain(pairs: DataFrame) -> DataFrame:
    return pairs.drop("d_name", "c_name", "i_name")


def edition_named(pairs: DataFrame, threshold: int = 100) -> DataFrame:
    """Names agree as token sets; at 100 this is containment either way with something in common."""
    d, c = X.unaccent(F.lower("d_name")), X.unaccent(F.lower("c_name"))
    if threshold < 100:
        return pairs.filter(F.col("c_name").isNotNull() & (X.token_set_ratio(d, c) >= threshold))
    x, y = X.tokens(d), X.tokens(c)
    inside = (F.size(F.array_except(x, y)) == 0) | (F.size(F.array_except(y, x)) == 0)
    return pairs.filter(F.col("c_name").isNotNull() & F.col("d_name").isNotNull() & (F.size(F.array_intersect(x, y)) > 0) & inside)


def certify_locality(df: DataFrame, gazetteer: DataFrame, max_edit: int = 2, col: str = "locality") -> DataFrame:
    """Locality replaced by its region's listed one: equal, then contained either way, then within max_edit.

    The join is by region; the gazetteer is small per region, and Spark broadcasts it below its size threshold.
    """
    options = gazetteer.select("region", F.col("locality").alias("listed")).distinct().groupBy("region").agg(F.array_sort(F.collect_list("listed")).alias("_listed"))
    v = F.col(col)
    rank = lambda o: F.when(F.lower(o) == F.lower(v), 0).when(F.contains(F.lower(o), F.lower(v)) | F.contains(F.lower(v), F.lower(o)), 1).when(F.levenshtein(F.lower(o), F.lower(v)) <= max_edit, 2)
    ranked = F.filter(F.transform("_listed", lambda o: F.struct(rank(o).alias("rank"), F.levenshtein(F.lower(o), F.lower(v)).alias("away"), o.alias("listed"))), lambda s: s["rank"].isNotNull())
    best = F.array_min(ranked)
    joined = df.join(options, "region", "left")
    return joined.withColumn("_best", best).withColumn("certified", F.col("_best").isNotNull()).withColumn(col, F.coalesce("_best.listed", col)).drop("_listed", "_best")


def funnel(steps: list[tuple[str, DataFrame]]) -> DataFrame:
    """step, n_rows for every step, in one job."""
    out = None
    for i, (name, df) in enumerate(steps):
        row = df.agg(F.count("*").alias("n_rows")).select(F.lit(i).alias("step"), F.lit(name).alias("name"), "n_rows")
        out = row if out is None else out.union(row)
    return out
