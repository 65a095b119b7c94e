"""The given tables, and the clean entity table derived from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cellscrub.schema import ATTRS

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _pick(index: Column, values: tuple[str, ...]) -> Column:
    return F.element_at(F.array(*[F.lit(v) for v in values]), (index + 1).cast("int"))


def entities(spark: SparkSession, sf_dir: str, skew: bool = False) -> DataFrame:
    """One row per customer with the eight clean attributes; key k, and nation for slicing.

    Every 29th entity lives at its neighbour's address. With skew, 52 % of the entities (by hash) move to nation 0.
    Joins are equi-joins on keys; nation and region are small enough for Spark to broadcast by size.
    """
    customer, part = table(spark, sf_dir, "customer"), table(spark, sf_dir, "part")
    nation = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    k = F.col("c_custkey")
    people = customer.select(k.alias("k"), F.when(k % 29 == 28, k - 1).otherwise(k).alias("a"), F.col("c_mktsegment").alias("own_segment"))
    moved = F.when(F.conv(F.substring(F.md5(k.cast("string")), 1, 4), 16, 10).cast("int") % 100 < 52, 0).otherwise(F.col("c_nationkey")) if skew else F.col("c_nationkey")
    owners = customer.select(k.alias("a"), moved.alias("nat"), F.col("c_mktsegment").alias("segment"))
    of_k = part.select(F.col("p_partkey").alias("k"), F.col("p_name").alias("own_part"), F.col("p_brand").alias("poi"))
    of_a = part.select(F.col("p_partkey").alias("a"), F.col("p_name").alias("part"), F.col("p_size").alias("psize"))
    both = people.join(owners, "a").join(of_k, "k").join(of_a, "a").join(nation, F.col("nat") == F.col("n_nationkey"))
    index = F.array_position(F.array(*[F.lit(s) for s in SEGMENTS]), F.col("segment")).cast("int") - 1
    a, nat = F.col("a"), F.col("nat")
    direction = _pick(a % 5, ("North ", "South ", "East ", "West ", ""))
    kind = _pick(F.col("psize") % 4, ("Street", "Avenue", "Boulevard", "Road"))
    code = F.least(nat, F.lit(23))
    return both.select(
        "k",
        "nat",
        "poi",
        F.concat(F.upper(F.left("own_part", F.lit(1))), F.expr("substring(own_part, 2)"), F.lit(" "), F.initcap("own_segment"), F.lit(" "), (F.floor(F.col("k") / 2) % 211).cast("string")).alias("name"),
        F.concat((a % 40 + 1).cast("string"), F.when(a % 7 == 0, "a").otherwise("")).alias("house_number"),
        F.concat(direction, F.initcap(F.element_at(F.split("part", " "), 2)), F.lit(" "), kind).alias("road"),
        F.lpad((nat * 400 + index * 80 + a % 3).cast("string"), 5, "0").alias("postcode"),
        F.concat(F.lit("Port "), F.initcap("segment"), F.lit(" "), nat.cast("string")).alias("locality"),
        F.concat(F.upper(F.left("r_name", F.lit(1))), F.lower(F.expr("substring(r_name, 2)")), F.when(index < 3, " Inner").otherwise(" Outer")).alias("region"),
        F.concat(F.lit("Nation "), nat.cast("string")).alias("country"),
        F.concat(_pick(F.floor(code / 5), tuple("ABCDE")), _pick(code % 5, tuple("ABCDE"))).alias("country_code"),
    )


def addr_clean(spark: SparkSession, sf_dir: str, carrier: str = "orders", skew: bool = False) -> DataFrame:
    """_id, graph_iri, poi and the clean attributes: one row per mention that the carrier table makes of an entity."""
    pages = table(spark, sf_dir, "pages").select(F.col("page_id").alias("page"), F.col("url").alias("graph_iri"))
    n_pages = pages.count()
    who = entities(spark, sf_dir, skew)
    if carrier == "customer":
        rows = who.withColumn("key", F.col("k"))
    else:
        orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("key"), F.col("o_custkey").alias("k"))
        if carrier == "lineitem":
            lines = table(spark, sf_dir, "lineitem")
            same = F.row_number().over(_same_line(lines))
            lines = lines.withColumn("n", same).select(F.col("l_orderkey").alias("key"), F.xxhash64(*lines.columns, "n").alias("line"))
            orders = orders.join(lines, "key").withColumn("key", F.abs(F.col("line"))).drop("line")
        rows = orders.join(who, "k")
    placed = rows.join(pages, F.col("key") % n_pages == F.col("page"))
    return placed.select(F.md5(F.col("key").cast("string")).alias("_id"), "graph_iri", "poi", *ATTRS)


def _same_line(lines: DataFrame):
    from pyspark.sql import Window

    return Window.partitionBy(*lines.columns).orderBy(F.lit(1))


_SEG_INDEX = "CASE o.c_mktsegment WHEN 'AUTOMOBILE' THEN 0 WHEN 'BUILDING' THEN 1 WHEN 'FURNITURE' THEN 2 WHEN 'HOUSEHOLD' THEN 3 ELSE 4 END"
_CAP = "upper(left({0}, 1)) || lower(substr({0}, 2))"

#: The same table in DuckDB: `entities` by customer and `addr` by order.
ADDR_SQL = f"""
entities AS MATERIALIZED (
  SELECT e.k, o.c_nationkey AS nat, pk.p_brand AS poi,
    upper(left(pk.p_name, 1)) || substr(pk.p_name, 2) || ' ' || {_CAP.format("e.seg")} || ' ' || (e.k // 2) % 211 AS name,
    (e.a % 40 + 1) || CASE WHEN e.a % 7 = 0 THEN 'a' ELSE '' END AS house_number,
    ['North ', 'South ', 'East ', 'West ', ''][e.a % 5 + 1] || {_CAP.format("split_part(pa.p_name, ' ', 2)")} || ' ' || ['Street', 'Avenue', 'Boulevard', 'Road'][pa.p_size % 4 + 1] AS road,
    lpad(CAST(o.c_nationkey * 400 + {_SEG_INDEX} * 80 + e.a % 3 AS VARCHAR), 5, '0') AS postcode,
    'Port ' || {_CAP.format("o.c_mktsegment")} || ' ' || o.c_nationkey AS locality,
    {_CAP.format("r_name")} || CASE WHEN {_SEG_INDEX} < 3 THEN ' Inner' ELSE ' Outer' END AS region,
    'Nation ' || o.c_nationkey AS country,
    chr(65 + least(o.c_nationkey, 23) // 5) || chr(65 + least(o.c_nationkey, 23) % 5) AS country_code
  FROM (SELECT c_custkey AS k, CASE WHEN c_custkey % 29 = 28 THEN c_custkey - 1 ELSE c_custkey END AS a, c_mktsegment AS seg FROM customer) e
  JOIN customer o ON o.c_custkey = e.a JOIN part pk ON pk.p_partkey = e.k JOIN part pa ON pa.p_partkey = e.a
  JOIN nation ON o.c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
), addr AS MATERIALIZED (
  SELECT md5(CAST(o_orderkey AS VARCHAR)) AS _id, url AS graph_iri, poi, {", ".join(ATTRS)}
  FROM orders JOIN entities ON o_custkey = k JOIN pages ON page_id = o_orderkey % (SELECT count(*) FROM pages)
)"""
