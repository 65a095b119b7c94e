"""Quads as text: parsing, emission, and rebuilding records from the linked and the microformat vocabulary."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ADDRESS_TYPE = "PostalAddress"
FIELDS = ("streetAddress", "postalCode", "addressLocality", "addressRegion", "addressCountry")
MICRO_FIELDS = {"street-address": "streetAddress", "postal-code": "postalCode", "locality": "addressLocality", "region": "addressRegion", "country-name": "addressCountry"}
_LINE = r'^(\S+)\s+<([^>]*)>\s+("(?:[^"\\]|\\.)*"(?:@[\w-]+)?|<[^>]*>|_:\S+)\s+<([^>]*)>\s*\.\s*$'


def parse_quads(lines: DataFrame, col: str = "value") -> DataFrame:
    """subject, predicate, object, graph_iri, bad (the line where it is malformed, else null)."""
    # the pattern runs once a line: its groups are written one below the other, and a line that does not match stays whole;
    # only text that holds a line end itself takes one run a group
    line, several = F.col(col), F.col(col).contains("\n")
    groups = F.split(F.regexp_replace(line, _LINE, "$1\n$2\n$4\n$3"), "\n", 4)
    part = lambda i: F.when(several, F.regexp_extract(line, _LINE, i)).otherwise(F.get(groups, F.lit((0, 1, 3, 2)[i - 1])))
    ok = F.when(several, line.rlike(_LINE)).otherwise(F.size(groups) == 4)
    literal = F.regexp_replace(F.regexp_replace(part(3), r'^"|"(@[\w-]+)?$', ""), r'\\(["\\])', "$1")
    text = F.when(part(3).startswith('"'), F.replace(literal, F.lit("\\n"), F.lit("\n"))).otherwise(F.regexp_replace(part(3), "^<|>$", ""))
    return lines.select(F.when(ok, part(1)).alias("subject"), F.when(ok, part(2)).alias("predicate"), F.when(ok, text).alias("object"), F.when(ok, part(4)).alias("graph_iri"), F.when(~ok, F.col(col)).alias("bad"))


def read_quads(spark: SparkSession, path: str) -> DataFrame:
    return parse_quads(spark.read.text(path))


def format_quads(quads: DataFrame) -> DataFrame:
    """value: one line a quad; nodes start with `_:`."""
    escaped = F.replace(F.replace(F.replace(F.col("object"), F.lit("\\"), F.lit("\\\\")), F.lit('"'), F.lit('\\"')), F.lit("\n"), F.lit("\\n"))
    obj = F.when(F.col("object").startswith("_:"), F.col("object")).otherwise(F.concat(F.lit('"'), escaped, F.lit('"')))
    return quads.select(F.concat_ws(" ", "subject", F.concat(F.lit("<"), "predicate", F.lit(">")), obj, F.concat(F.lit("<"), "graph_iri", F.lit("> ."))).alias("value"))


def emit_quads(records: DataFrame, micro: bool = False) -> DataFrame:
    """subject, predicate, object, graph_iri of records (_id, graph_iri, name and FIELDS), nulls left out.

    The linked vocabulary gives each record a typed address node and a parent that holds the name.
    """
    node = F.concat(F.lit("_:a"), F.left("_id", F.lit(12)))
    if micro:
        rows = [F.struct(node.alias("subject"), F.lit("vcard#" + m).alias("predicate"), F.col(f).alias("object")) for m, f in MICRO_FIELDS.items()]
    else:
        parent = F.concat(F.lit("_:p"), F.left("_id", F.lit(12)))
        rows = [F.struct(node.alias("subject"), F.lit("schema#" + f).alias("predicate"), F.col(f).alias("object")) for f in FIELDS]
        rows += [
            F.struct(node.alias("subject"), F.lit("rdf#type").alias("predicate"), F.lit(ADDRESS_TYPE).alias("object")),
            F.struct(parent.alias("subject"), F.lit("schema#address").alias("predicate"), node.alias("object")),
            F.struct(parent.alias("subject"), F.lit("schema#name").alias("predicate"), F.col("name").alias("object")),
        ]
    return records.select("graph_iri", F.inline(F.array(*rows))).filter("object IS NOT NULL").select("subject", "predicate", "object", "graph_iri")


def _gathered(quads: DataFrame, names: dict[str, str]) -> DataFrame:
    one = lambda p, f: F.max(F.when(F.col("predicate") == p, F.col("object"))).alias(f)
    return quads.groupBy("graph_iri", F.col("subject").alias("node")).agg(*[one(p, f) for p, f in names.items()])


def build_linked(quads: DataFrame) -> DataFrame:
    """graph_iri, node, name, FIELDS: typed address nodes with their parent's name, null without a parent.

    One aggregation over (graph, node) and one join with the parents, both keyed by graph and node.
    """
    nodes = _gathered(quads, {"rdf#type": "kind", **{"schema#" + f: f for f in FIELDS}}).filter(F.col("kind") == ADDRESS_TYPE).drop("kind")
    parents = _gathered(quads, {"schema#address": "node_ref", "schema#name": "name"}).filter("node_ref IS NOT NULL")
    names = parents.groupBy("graph_iri", F.col("node_ref").alias("node")).agg(F.max("name").alias("name"))
    return nodes.join(names, ["graph_iri", "node"], "left").select("graph_iri", "node", "name", *FIELDS)


def build_microformat(quads: DataFrame) -> DataFrame:
    found = _gathered(quads.filter(F.col("predicate").startswith("vcard#")), {"vcard#" + m: f for m, f in MICRO_FIELDS.items()})
    return found.select("graph_iri", "node", F.lit(None).cast("string").alias("name"), *FIELDS)


def combine(linked: DataFrame, micro: DataFrame) -> DataFrame:
    return linked.withColumn("source", F.lit("linked")).unionByName(micro.withColumn("source", F.lit("microformat")))


def page_quads(pages: DataFrame) -> DataFrame:
    """Quads of web pages: language, title, first heading and the number of links."""
    get = lambda rx: F.regexp_extract("html", rx, 1)
    values = {"lang": get(r'<html lang="([^"]*)"'), "title": get(r"<title>([^<]*)</title>"), "h1": get(r"<h1[^>]*>([^<]*)</h1>"), "links": F.regexp_count("html", F.lit('<a href="')).cast("string")}
    rows = F.array(*[F.struct(F.lit("page#" + k).alias("predicate"), v.alias("object")) for k, v in values.items()])
    return pages.select(F.concat(F.lit("_:b"), F.col("page_id").cast("string")).alias("subject"), F.inline(rows), F.col("url").alias("graph_iri")).select("subject", "predicate", "object", "graph_iri").filter("object <> ''")
