"""The pair construction pipeline: statements to records, sparse filter, lookup, alignment, filters, two editions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellscrub.operators import align, curate, georef, inject
from cellscrub.schema import ATTRS, CORE_ATTRS
from cellscrub.session import materialize
from cellscrub.sources import quads as Q
from cellscrub.sources.tables import addr_clean


def statements(spark: SparkSession, sf_dir: str, carrier: str = "orders", profile: str = "named", seed: int = 7) -> DataFrame:
    """_id, graph_iri, micro, name and the five address fields, as found on pages: a tenth in the microformat."""
    pairs = inject.corrupt(addr_clean(spark, sf_dir, carrier), profile, seed)
    odd = F.coalesce(F.regexp_extract("c_country", r"(\d+)$", 1).try_cast("int") % 2, F.lit(0)) == 1
    number, road = F.nullif(F.col("d_house_number"), F.lit("")), F.nullif(F.col("d_road"), F.lit(""))
    street = F.when(odd, F.concat_ws(" ", road, number)).otherwise(F.concat_ws(" ", number, road))
    h = inject.draw(seed, "statement", F.col("_id"))
    country = F.when(h % 2 == 0, F.col("d_country")).otherwise(F.col("d_country_code"))
    blank = h % 100 < 11
    lone = lambda c: F.when(~blank, c)
    return pairs.select("_id", "graph_iri", (F.floor(h / 100) % 10 == 0).alias("micro"), F.col("d_name").alias("name"), F.nullif(lone(street), F.lit("")).alias("streetAddress"), lone(F.col("d_postcode")).alias("postalCode"), lone(F.col("d_locality")).alias("addressLocality"), F.col("d_region").alias("addressRegion"), country.alias("addressCountry"))


def extracted(stated: DataFrame) -> DataFrame:
    """Statements through quads of both vocabularies and back: graph_iri, node, name, fields, source."""
    emitted = Q.emit_quads(stated.filter("NOT micro")).unionByName(Q.emit_quads(stated.filter("micro"), micro=True))
    quads = materialize(Q.parse_quads(Q.format_quads(emitted)).filter("bad IS NULL"), "quads")  # nodes, parents and microformat read them
    return Q.combine(Q.build_linked(quads), Q.build_microformat(quads))


def build_pairs(spark: SparkSession, sf_dir: str, carrier: str = "orders", blank_names: int = 42) -> dict[str, DataFrame]:
    """Every step's result by name, from raw records to the two editions."""
    stated = statements(spark, sf_dir, carrier)
    raw = materialize(extracted(stated), "raw")
    kept = raw.filter(curate.has_core_signal())
    aligned = materialize(align.align_records(kept.withColumn("_id", F.md5(F.concat_ws("|", "graph_iri", "node")))), "aligned")
    clean = addr_clean(spark, sf_dir, "customer")
    ref = materialize(georef.reference(clean), "reference")
    hits = materialize(georef.lookup(aligned, ref), "hits")
    d = aligned.select("_id", "graph_iri", *[F.col(a).alias(f"d_{a}") for a in ATTRS])
    c = ref.select("ref_id", *[(F.when(F.conv(F.substring("ref_id", 1, 4), 16, 10).cast("int") % 100 >= blank_names, F.col(a)) if a == "name" else F.col(a)).alias(f"c_{a}") for a in ("name", *CORE_ATTRS)])
    matched = d.join(hits.select("_id", "ref_id"), "_id").join(c, "ref_id").drop("ref_id")
    full = curate.complete(matched)
    single = materialize(curate.drop_page_duplicates(full), "single")
    return {"raw": raw, "core": kept, "matched": matched, "complete": full, "plain": curate.edition_plain(single), "named": curate.edition_named(single)}


def write_editions(editions: dict[str, DataFrame], path: str) -> None:
    """Both editions as Parquet, partitioned by country code."""
    for name in ("plain", "named"):
        editions[name].withColumn("code", F.col("c_country_code")).repartition("code").write.mode("overwrite").partitionBy("code").parquet(f"{path}/{name}")
