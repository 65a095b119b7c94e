"""Alignment of nested statements and geocoder replies with the eight attributes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellscrub.functions import text as X

LOCALITY = (("city", "town"), ("village", "borough", "neighborhood", "hamlet", "municipality"))
REGION = (("region", "state"), ("county", "province", "state_district"))


def split_street(street: Column) -> tuple[Column, Column]:
    """(road, house_number): number first or last, block codes; null road where nothing but a number is left."""
    s = X.normalize(street)
    first, last, block = r"^(\d+[A-Za-z]?(?:[-/]\d+[A-Za-z]?)?)[,\s]+(.+)$", r"^(.+?)[,\s]+(\d+[A-Za-z]?(?:[-/]\d+[A-Za-z]?)?)$", r"^([A-Z]\d{1,2})[,\s]+(\d+[A-Za-z]?)$"
    road = F.when(s.rlike(block), F.regexp_extract(s, block, 1)).when(s.rlike(first), F.regexp_extract(s, first, 2)).when(s.rlike(last), F.regexp_extract(s, last, 1)).when(~s.rlike(r"^\d+[A-Za-z]?$"), s)
    number = F.when(s.rlike(block), F.regexp_extract(s, block, 2)).when(s.rlike(first), F.regexp_extract(s, first, 1)).when(s.rlike(last), F.regexp_extract(s, last, 2)).when(s.rlike(r"^\d+[A-Za-z]?$"), s)
    return F.nullif(road, F.lit("")), number


def route_country(value: Column) -> tuple[Column, Column]:
    """(country, country_code): two letters are a code."""
    code = X.normalize(value).rlike("^[A-Za-z]{2}$")
    return F.when(~code, X.normalize(value)), F.when(code, X.normalize(value))


def choose_level(address: Column, dirty: Column, tiers: tuple[tuple[str, ...], tuple[str, ...]]) -> Column:
    """Of a reply's keys the preferred ones, then the others; several: nearest to the dirty value, then key order."""
    options = []
    order = 0
    for tier, keys in enumerate(tiers):
        for k in keys:
            v = F.element_at(address, k)
            away = F.coalesce(F.levenshtein(F.lower(v), F.lower(dirty)), F.lit(0))
            options.append(F.when(v.isNotNull(), F.struct(F.lit(tier).alias("tier"), away.alias("away"), F.lit(order).alias("order"), v.alias("value"))))
            order += 1
    return F.array_min(F.filter(F.array(*options), lambda o: o.isNotNull()))["value"]


def align_records(raw: DataFrame) -> DataFrame:
    """Extracted records (name and the five address fields) as the eight attributes."""
    road, number = split_street(F.col("streetAddress"))
    country, code = route_country(F.col("addressCountry"))
    keep = [c for c in ("_id", "graph_iri", "node", "source") if c in raw.columns]
    return raw.select(*keep, X.normalize(F.col("name")).alias("name"), number.alias("house_number"), road.alias("road"), F.col("postalCode").alias("postcode"), F.col("addressLocality").alias("locality"), F.col("addressRegion").alias("region"), country.alias("country"), code.alias("country_code"))


def align_replies(replies: DataFrame) -> DataFrame:
    """Replies (_id, name, address map, dirty locality and region) as the clean attributes."""
    a = F.col("address")
    one = lambda k: F.element_at(a, k)
    return replies.select("_id", "name", one("house_number").alias("house_number"), one("road").alias("road"), one("postcode").alias("postcode"), choose_level(a, F.col("dirty_locality"), LOCALITY).alias("locality"), choose_level(a, F.col("dirty_region"), REGION).alias("region"), one("country").alias("country"), F.upper(one("country_code")).alias("country_code"))
