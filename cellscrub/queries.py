"""All queries of the cleaning benchmark by name, each with its DuckDB SQL where SQL can say it."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellscrub.functions import text as X
from cellscrub.operators import align, curate, fd, georef, inject, measure, profile, sampling, taxonomy
from cellscrub.plans import effectiveness, pairs, scalability
from cellscrub.schema import ATTRS
from cellscrub.session import materialize, scratch_dir
from cellscrub.sources import formats, quads
from cellscrub.sources.tables import ADDR_SQL, addr_clean, entities, table
from cellscrub.streaming import monitor
from cellscrub.systems import factor, fd_majority, record_prompt, rule_workflow, signature_detector, staged
from cellscrub.systems.base import Labels, records, repair_by_mode

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

CELLS = inject.cells_sql()
ROWS = f"WITH {ADDR_SQL}"
CELL = f"{ROWS}, {CELLS}"
FULL = f"{CELL}, {taxonomy.category_sql(True)}"
NATIVE = f"{CELL}, {taxonomy.category_sql(False)}"

TYPO_FIRST = ("clean", "missing", "typo", "encoding", "case", "punct", "reorder", "abbrev", "language", "containment", "one_word", "other")
RULES = [fd.Dependency(("postcode",), "locality"), fd.Dependency(("locality",), "country"), fd.Dependency(("country",), "country_code")]


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def _cells(s: SparkSession, d: str) -> DataFrame:
    injected = inject.corrupt(addr_clean(s, d)).withColumn("nation", F.col("c_country"))
    return inject.cells(injected, keep=("_id", "graph_iri", "poi", "nation"))


def _classified(s: SparkSession, d: str) -> DataFrame:
    return taxonomy.classify(_cells(s, d))


def _dirty(s: SparkSession, d: str) -> DataFrame:
    return records(inject.corrupt(addr_clean(s, d)))


_OUT = "_id, attr, dirty, clean, injected, category"

# --- stand-in data, injection, classification

query("addr_clean", f"{ROWS} SELECT * FROM addr")(lambda s, d: addr_clean(s, d))
query("addr_dirty", f"{CELL} SELECT _id, graph_iri, poi, nation, attr, dirty, clean, injected FROM cell")(_cells)
query("classify_native", f"{NATIVE} SELECT {_OUT} FROM classified")(lambda s, d: taxonomy.classify_native(_cells(s, d)).select(*_OUT.split(", ")))
query("classify_full", f"{FULL} SELECT {_OUT} FROM classified")(lambda s, d: _classified(s, d).select(*_OUT.split(", ")))
query("classify_by_pair", f"{FULL} SELECT {_OUT} FROM classified")(lambda s, d: taxonomy.classify(_cells(s, d), by_pair=True).select(*_OUT.split(", ")))
query("category_shares", f"{FULL} SELECT attr, category, count(*) AS n FROM classified GROUP BY ALL")(lambda s, d: taxonomy.classify_counted(_cells(s, d), ("attr",)))
query("inject_confusion", f"{FULL} SELECT injected, category, count(*) AS n FROM classified GROUP BY ALL")(lambda s, d: inject.confusion(_classified(s, d)))
query("category_by_slice", f"""{FULL} SELECT 'all' AS slice_col, 'all' AS slice, category, count(*) AS n FROM classified GROUP BY category
UNION ALL SELECT 'nation', nation, category, count(*) FROM classified GROUP BY nation, category UNION ALL SELECT 'poi', poi, category, count(*) FROM classified GROUP BY poi, category""")(lambda s, d: profile.slice_table(_classified(s, d), ("nation", "poi")))
query("attr_category_cube", f"{FULL} SELECT coalesce(attr, 'all') AS attr, coalesce(category, 'all') AS category, count(*) AS n FROM classified GROUP BY CUBE (attr, category)")(lambda s, d: profile.attribute_cube(_classified(s, d)))
query("error_totals", f"{FULL} SELECT count(*) AS n_cells, CAST(count(*) FILTER (category = 'clean') AS BIGINT) AS n_clean, CAST(count(*) FILTER (category <> 'clean') AS BIGINT) AS n_errors, round(avg(CASE WHEN category <> 'clean' THEN 1.0 ELSE 0.0 END), 6) AS error_rate FROM classified")(lambda s, d: profile.error_rate(_classified(s, d)))
query("slice_spread", f"""{FULL}, cnt AS (SELECT poi, category, count(*) AS n FROM classified GROUP BY ALL), tot AS (SELECT poi, sum(n) AS t FROM cnt GROUP BY poi), cats AS (SELECT unnest([{", ".join(repr(c) for c in profile.CATEGORIES)}]) AS category)
SELECT category, round(min(sh), 6) AS least, round(median(sh), 6) AS median, round(max(sh), 6) AS greatest FROM (SELECT cats.category, coalesce(n, 0) / t AS sh FROM tot CROSS JOIN cats LEFT JOIN cnt ON cnt.poi = tot.poi AND cnt.category = cats.category) GROUP BY category""")(lambda s, d: profile.slice_spread(_classified(s, d).groupBy("poi", "category").agg(F.count("*").alias("n")), "poi"))
query("all_matches", f"{NATIVE} SELECT _id, attr, matches FROM classified WHERE dirty IS DISTINCT FROM clean")(lambda s, d: taxonomy.all_matches(_cells(s, d)).filter("dirty IS DISTINCT FROM clean").select("_id", "attr", F.array_join("matches", ",").alias("matches")))
query("dictionary_coverage", f"""{CELL}, t AS (SELECT attr, unnest({taxonomy.tokens_sql("coalesce(dirty, '')")}) AS t FROM cell)
SELECT attr, count(*) AS n_tokens, round(avg(CASE WHEN t IN ({', '.join(repr(k) for k in X.ALIASES)}) THEN 1.0 ELSE 0 END), 6) AS alias_share, round(avg(CASE WHEN t IN ({', '.join(repr(k) for k in X.ABBREVIATIONS)}) THEN 1.0 ELSE 0 END), 6) AS abbrev_share FROM t GROUP BY attr""")(lambda s, d: taxonomy.dictionary_coverage(_cells(s, d)))
query("order_ablation", f"{CELL}, {taxonomy.category_sql(order=TYPO_FIRST)} SELECT category, count(*) AS n FROM classified GROUP BY category")(lambda s, d: taxonomy.classify_native(_cells(s, d), order=TYPO_FIRST).groupBy("category").agg(F.count("*").alias("n")))
query("exact_compare", f"{CELL}, {taxonomy.category_sql(compare='exact')} SELECT category, count(*) AS n FROM classified GROUP BY category")(lambda s, d: taxonomy.classify_native(_cells(s, d), compare="exact").groupBy("category").agg(F.count("*").alias("n")))

# --- profiles

query("distinct_values", f"{ROWS} " + " UNION ALL ".join(f"SELECT '{c}' AS attr, count(DISTINCT {c}) AS n_distinct FROM addr" for c in ("_id", *ATTRS, "graph_iri")))(lambda s, d: profile.distinct_counts(addr_clean(s, d)))
query("distinct_values_sketch")(lambda s, d: profile.distinct_counts(addr_clean(s, d), approx=True))
query("distinct_records", f"{ROWS} SELECT CAST(sum(n) AS BIGINT) AS n_rows, count(*) AS n_records, round(avg(n), 6) AS rows_per_record FROM (SELECT count(*) AS n FROM addr GROUP BY {', '.join(ATTRS)})")(lambda s, d: profile.distinct_records(addr_clean(s, d)))
query("colocation", f"{ROWS} SELECT count(*) AS n_addresses, round(avg(n), 6) AS mean_names, max(n) AS max_names FROM (SELECT count(DISTINCT name) AS n FROM addr GROUP BY {', '.join(ATTRS[1:])})")(lambda s, d: profile.colocation(addr_clean(s, d)))
query("country_distribution", f"{ROWS} SELECT country, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM addr GROUP BY country")(lambda s, d: profile.distribution(addr_clean(s, d), "country"))
query("distinct_ratio", f"{ROWS} " + " UNION ALL ".join(f"SELECT country AS slice, '{a}' AS attr, round(count(DISTINCT {a}) / count(*), 6) AS ratio FROM addr GROUP BY country" for a in ATTRS))(lambda s, d: profile.distinct_ratio(addr_clean(s, d), "country"))
query("variant_usage", f"{CELL} SELECT nation, round(avg(CASE WHEN regexp_matches(coalesce(dirty, ''), 'St\\.|Street') THEN 1.0 ELSE 0 END), 6) AS dirty_share, round(avg(CASE WHEN regexp_matches(clean, 'St\\.|Street') THEN 1.0 ELSE 0 END), 6) AS clean_share FROM cell GROUP BY nation")(lambda s, d: profile.variant_usage(_cells(s, d), "nation", r"St\.|Street"))

# --- dependencies

query("fd_check", f"{ROWS} SELECT count(*) AS n_groups, count(*) FILTER (k > 1) AS n_violating, count(*) FILTER (k > 1) = 0 AS holds FROM (SELECT count(DISTINCT country) AS k FROM addr GROUP BY country_code)")(lambda s, d: fd.holds(addr_clean(s, d), ["country_code"], "country"))
query("fd_g3", f"{ROWS} SELECT CAST(sum(n) AS BIGINT) AS n_rows, CAST(sum(n - m) AS BIGINT) AS n_remove, round(sum(n - m) / sum(n), 6) AS g3 FROM (SELECT sum(n) AS n, max(n) AS m FROM (SELECT locality, road, count(*) AS n FROM addr GROUP BY ALL) GROUP BY locality)")(lambda s, d: fd.g3(addr_clean(s, d), ["locality"], "road"))
query("fd_discover", f"{ROWS}, {fd.minimal_sql('entities')} SELECT lhs, rhs, lhs_size, CAST(0 AS DOUBLE) AS g3 FROM found")(lambda s, d: fd.as_frame(s, fd.discover(entities(s, d))))
query("fd_summary", f"{ROWS}, {fd.minimal_sql('entities')} SELECT rhs, lhs_size, count(*) AS n FROM found GROUP BY ALL")(lambda s, d: fd.summary(s, fd.discover(entities(s, d))))
query("fd_slice_only")(lambda s, d: fd.slice_only(s, fd.discover(entities(s, d).filter("country = 'Nation 3'"), max_lhs=2), fd.discover(entities(s, d), max_lhs=2)))
query("fd_approximate")(lambda s, d: fd.as_frame(s, fd.discover(entities(s, d), max_lhs=1, epsilon=0.05)))
query("fd_counterexamples", f"{ROWS} SELECT country_code, count(DISTINCT country) AS n_values, string_agg(DISTINCT country, '|' ORDER BY country) AS rhs_values FROM addr GROUP BY country_code HAVING count(DISTINCT country) > 1")(lambda s, d: fd.counterexamples(addr_clean(s, d), ["country_code"], "country"))
_GRADED = "SELECT p_brand, p_size, p_type, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS grade, p_brand || '/' || p_type AS line FROM part"
_PART_COLS = ("p_brand", "p_size", "p_type", "grade", "line")
query("fd_parts", f"WITH graded AS ({_GRADED}), {fd.minimal_sql('graded', _PART_COLS)} SELECT lhs, rhs, lhs_size, CAST(0 AS DOUBLE) AS g3 FROM found")(lambda s, d: fd.as_frame(s, fd.discover(table(s, d, "part").selectExpr("p_brand", "p_size", "p_type", "CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS grade", "concat(p_brand, '/', p_type) AS line"), _PART_COLS)))

# --- samples and rates

_HASH = "md5('1|' || _id)"
query("fixed_sample", f"{ROWS} SELECT _id, country FROM addr ORDER BY {_HASH} LIMIT 1000")(lambda s, d: sampling.fixed(addr_clean(s, d), 1000).select("_id", "country"))
query("balanced_countries", f"{ROWS} SELECT _id, country FROM (SELECT _id, country, row_number() OVER (PARTITION BY country ORDER BY {_HASH}) AS p FROM addr WHERE country IN (SELECT country FROM addr GROUP BY country ORDER BY count(*) DESC, country LIMIT 5)) WHERE p <= 100")(lambda s, d: sampling.balanced(addr_clean(s, d), "country", 5, 100).select("_id", "country"))
query("stratified_sample", f"""{ROWS}, q AS (SELECT country, poi, count(*) AS n, (SELECT count(*) FROM addr) AS t FROM addr GROUP BY ALL),
r AS (SELECT *, n * 1000 // t AS b, row_number() OVER (ORDER BY n * 1000 % t DESC, country, poi) AS k FROM q), z AS (SELECT country, poi, b + CASE WHEN k <= 1000 - (SELECT sum(b) FROM r) THEN 1 ELSE 0 END AS quota FROM r)
SELECT country, poi, CAST(quota AS BIGINT) AS n FROM z WHERE quota > 0""")(lambda s, d: sampling.stratified(addr_clean(s, d), ("country", "poi"), 1000).groupBy("country", "poi").agg(F.count("*").alias("n")))
query("country_slice", f"{ROWS} SELECT * FROM addr WHERE country = 'Nation 3'")(lambda s, d: sampling.by(addr_clean(s, d), "country", "Nation 3"))
query("poi_slices", f"{ROWS} SELECT poi, count(*) AS n FROM addr WHERE CAST(substr(poi, 7) AS INTEGER) <= 22 GROUP BY poi")(lambda s, d: addr_clean(s, d).filter(F.expr("CAST(substring(poi, 7) AS INT) <= 22")).groupBy("poi").agg(F.count("*").alias("n")))
_KEPT = """, t AS (SELECT count(*) AS n, count(*) FILTER (category <> 'clean') AS e, least(count(*) FILTER (category <> 'clean'), CAST(floor(0.2 * count(*) + 0.5) AS BIGINT)) AS k FROM classified)"""
_RESTORED = """, r AS (SELECT *, row_number() OVER (PARTITION BY category <> 'clean' ORDER BY md5('1|' || _id || '|' || attr)) AS p, count(*) OVER () AS t FROM classified),
kept AS (SELECT _id, attr, CASE WHEN category <> 'clean' AND p > CAST(floor(0.2 * t + 0.5) AS BIGINT) THEN clean ELSE dirty END AS dirty, clean, CASE WHEN category <> 'clean' AND p > CAST(floor(0.2 * t + 0.5) AS BIGINT) THEN 'clean' ELSE category END AS category FROM r)"""
query("restore_global", f"{FULL}{_RESTORED} SELECT _id, attr, dirty, clean, category FROM kept")(lambda s, d: sampling.restore(materialize(_classified(s, d), "c"), 0.2).select("_id", "attr", "dirty", "clean", "category"))
query("restore_proportional", f"""{FULL}{_KEPT}, r AS (SELECT attr, category, row_number() OVER (PARTITION BY attr, category ORDER BY md5('1|' || _id || '|' || attr)) AS p, count(*) OVER (PARTITION BY attr, category) AS c FROM classified)
SELECT attr, CASE WHEN category <> 'clean' AND p > floor(c * (CAST(k AS DOUBLE) / e) + 0.5) THEN 'clean' ELSE category END AS category, count(*) AS n FROM r, t GROUP BY ALL""")(lambda s, d: sampling.restore(materialize(_classified(s, d), "c"), 0.2, mode="proportional").groupBy("attr", "category").agg(F.count("*").alias("n")))
query("restore_bernoulli", f"""{FULL}{_KEPT}, r AS (SELECT category <> 'clean' AND CAST('0x' || substr(md5('1|' || _id || '|' || attr), 1, 8) AS BIGINT) < CAST(floor((CAST(k AS DOUBLE) / e) * 4294967296) AS BIGINT) AS bad FROM classified, t)
SELECT count(*) AS n_cells, count(*) FILTER (NOT bad) AS n_clean, count(*) FILTER (bad) AS n_errors, round(avg(CASE WHEN bad THEN 1.0 ELSE 0 END), 6) AS error_rate FROM r""")(lambda s, d: profile.error_rate(sampling.restore(materialize(_classified(s, d), "c"), 0.2, mode="bernoulli")))


@query("restore_nested_check", "SELECT CAST(0 AS BIGINT) AS n_outside")
def _nested(s: SparkSession, d: str) -> DataFrame:
    cells = materialize(_classified(s, d), "c")
    wrong = lambda r: sampling.restore(cells, r).filter("category <> 'clean'").select("_id", "attr")
    return wrong(0.05).exceptAll(wrong(0.2)).agg(F.count("*").alias("n_outside"))


query("dedup_dirty", f"{CELL}, w AS (SELECT _id, {', '.join(f'''max(dirty) FILTER (attr = '{a}') AS d_{a}''' for a in ATTRS)} FROM cell GROUP BY _id) SELECT min(_id) AS _id FROM w GROUP BY {', '.join(f'd_{a}' for a in ATTRS)}")(lambda s, d: sampling.dedup_dirty(inject.corrupt(addr_clean(s, d))).select("_id"))

# --- pair construction


@query("quads_roundtrip", f"{ROWS} SELECT _id, name, country FROM addr")
def _roundtrip(s: SparkSession, d: str) -> DataFrame:
    rows = addr_clean(s, d).select("_id", "graph_iri", "name", F.concat_ws(" ", "house_number", "road").alias("streetAddress"), F.col("postcode").alias("postalCode"), F.col("locality").alias("addressLocality"), F.col("region").alias("addressRegion"), F.col("country").alias("addressCountry"))
    back = quads.build_linked(quads.parse_quads(quads.format_quads(quads.emit_quads(rows))))
    node = F.concat(F.lit("_:a"), F.left("_id", F.lit(12)))
    return rows.select("_id", node.alias("node"), "graph_iri").join(back, ["graph_iri", "node"]).select("_id", "name", F.col("addressCountry").alias("country"))


query("quads_from_pages", """SELECT '_:b' || page_id AS subject, 'page#' || k AS predicate, v AS object, url AS graph_iri FROM (
SELECT page_id, url, unnest(['lang', 'title', 'h1', 'links']) AS k, unnest([regexp_extract(html, '<html lang="([^"]*)"', 1), regexp_extract(html, '<title>([^<]*)</title>', 1), regexp_extract(html, '<h1[^>]*>([^<]*)</h1>', 1), CAST(len(regexp_extract_all(html, '<a href="')) AS VARCHAR)]) AS v FROM pages) WHERE v <> ''""")(lambda s, d: quads.page_quads(table(s, d, "pages")))
query("linked_records")(lambda s, d: pairs.extracted(pairs.statements(s, d)).filter("source = 'linked'"))
query("microformat_records")(lambda s, d: pairs.extracted(pairs.statements(s, d)).filter("source = 'microformat'"))
query("core_signal_retention")(lambda s, d: curate.retention(pairs.extracted(pairs.statements(s, d))))
query("build_funnel")(lambda s, d: curate.funnel(list(pairs.build_pairs(s, d).items())))
query("edition_plain")(lambda s, d: pairs.build_pairs(s, d)["plain"])
query("edition_named")(lambda s, d: pairs.build_pairs(s, d)["named"])
query("street_split")(lambda s, d: align.align_records(pairs.statements(s, d)).select("_id", "road", "house_number"))
query("country_routing")(lambda s, d: align.align_records(pairs.statements(s, d)).select("_id", "country", "country_code"))


@query("level_choice", f"""{ROWS} SELECT k, CASE WHEN k % 3 = 0 THEN 'Old ' || locality ELSE locality END AS locality, region FROM entities""")
def _levels(s: SparkSession, d: str) -> DataFrame:
    e = entities(s, d)
    old = F.when(F.col("k") % 3 == 0, F.concat(F.lit("Old "), "locality"))
    address = F.map_from_entries(F.filter(F.array(F.struct(F.lit("town").alias("a"), F.coalesce(old, F.col("locality")).alias("b")), F.struct(F.lit("village").alias("a"), F.col("name").alias("b")), F.struct(F.lit("county").alias("a"), F.col("region").alias("b"))), lambda x: x["b"].isNotNull()))
    return e.select("k", align.choose_level(address, F.col("locality"), align.LOCALITY).alias("locality"), align.choose_level(address, F.col("region"), align.REGION).alias("region"))


def _aligned(s: SparkSession, d: str) -> DataFrame:
    return _dirty(s, d)


query("lookup_ladder")(lambda s, d: georef.lookup(_aligned(s, d), georef.reference(addr_clean(s, d, "customer"))).groupBy("rung").agg(F.count("*").alias("n"), F.round(F.avg("score"), 6).alias("mean_score")))
query("lookup_freetext")(lambda s, d: georef.lookup_freetext(_aligned(s, d), georef.reference(addr_clean(s, d, "customer"))))


@query("reference_coverage")
def _coverage(s: SparkSession, d: str) -> DataFrame:
    sample = materialize(sampling.fixed(_aligned(s, d), 1000), "coverage")
    out = None
    for name, nations in (("full", None), ("eight", 8), ("four", 4)):
        hits = georef.lookup(sample, georef.reference(addr_clean(s, d, "customer"), nations)).withColumn("source", F.lit(name))
        out = hits if out is None else out.unionByName(hits)
    return georef.coverage(sample, out)


@query("reference_agreement")
def _agreement(s: SparkSession, d: str) -> DataFrame:
    sample = materialize(sampling.fixed(_aligned(s, d), 1000), "agreement")
    clean = addr_clean(s, d, "customer")
    return georef.agreement(georef.lookup(sample, georef.reference(clean)), georef.lookup(sample, georef.reference(clean), accept=0.6))


query("complete_filter", f"{CELL}, w AS (SELECT _id, {', '.join(f'''max(nullif(dirty, '')) FILTER (attr = '{a}') AS {a}''' for a in ATTRS)} FROM cell GROUP BY _id) SELECT _id FROM w WHERE " + " AND ".join(f"{a} IS NOT NULL" for a in ATTRS[1:]))(lambda s, d: curate.complete(inject.corrupt(addr_clean(s, d)), "d").select("_id"))
query("certify_locality")(lambda s, d: curate.certify_locality(_dirty(s, d), entities(s, d).select("region", "locality").distinct()).select("_id", "region", "locality", "certified"))
_SAME = "string_agg(coalesce(dirty, chr(2)) || chr(31) || coalesce(clean, chr(2)), chr(31) ORDER BY attr)"
_COPIED = "substr(md5(_id), 1, 1) IN ('0', '7')"


@query("page_dedup", f"{CELL}, v AS (SELECT _id, graph_iri, {_SAME} AS v FROM cell GROUP BY _id, graph_iri), w AS (SELECT * FROM v UNION ALL SELECT _id || '/copy', graph_iri, v FROM v WHERE {_COPIED}) SELECT min(_id) AS _id, count(*) AS n_alike FROM w GROUP BY graph_iri, v")
def _page_dedup(s: SparkSession, d: str) -> DataFrame:
    """Pairs of which an eighth stand twice on their page."""
    once = inject.corrupt(addr_clean(s, d))
    every = materialize(once.unionByName(once.filter(_COPIED).withColumn("_id", F.concat("_id", F.lit("/copy")))), "pairs")
    kept = curate.drop_page_duplicates(every)
    alike = every.groupBy("graph_iri", *[f"{x}_{a}" for a in ATTRS for x in ("d", "c")]).agg(F.min("_id").alias("_id"), F.count("*").alias("n_alike"))
    return kept.select("_id").join(alike.select("_id", "n_alike"), "_id")

# --- systems

_WIDE = f", w AS MATERIALIZED (SELECT _id, {', '.join(f'''max(nullif(trim(dirty), '')) FILTER (attr = '{a}') AS {a}''' for a in ATTRS)} FROM cell GROUP BY _id)"
_REPAIRED = _WIDE
for _i, (_l, _r) in enumerate((("postcode", "locality"), ("locality", "country"), ("country", "country_code"))):
    _from = "w" if _i == 0 else f"s{_i - 1}"
    _REPAIRED += f", b{_i} AS (SELECT {_l}, {_r} AS v FROM (SELECT {_l}, {_r}, row_number() OVER (PARTITION BY {_l} ORDER BY count(*) DESC, {_r}) AS p FROM {_from} WHERE {_l} IS NOT NULL AND {_r} IS NOT NULL GROUP BY {_l}, {_r}) WHERE p = 1), s{_i} AS MATERIALIZED (SELECT t.* REPLACE (coalesce(b{_i}.v, t.{_r}) AS {_r}) FROM {_from} t LEFT JOIN b{_i} ON t.{_l} = b{_i}.{_l})"
_CHANGED = " UNION ALL ".join(f"SELECT w._id, '{a}' AS attr, s2.{a} AS repair FROM w JOIN s2 USING (_id) WHERE w.{a} IS DISTINCT FROM s2.{a}" for a in ("locality", "country", "country_code"))
query("repair_r1", f"{CELL}{_REPAIRED} {_CHANGED}")(lambda s, d: fd_majority.correct(materialize(_dirty(s, d), "d"), RULES).select("_id", "attr", "repair"))
query("detect_r1", f"{CELL}{_REPAIRED} SELECT _id, attr FROM ({_CHANGED})")(lambda s, d: fd_majority.detect(materialize(_dirty(s, d), "d"), RULES))
query("repair_r2")(lambda s, d: rule_workflow.correct(materialize(_dirty(s, d), "d"), RULES).select("_id", "attr", "repair"))
query("detect_r2")(lambda s, d: rule_workflow.detect(materialize(_dirty(s, d), "d"), RULES))
query("ladder_r2")(lambda s, d: s.createDataFrame([rule_workflow.run_ladder(materialize(_dirty(s, d), "d"), RULES, 120.0)]).select("step", "sampling", "max_lhs", "single_max", "status"))
_VIOLATING = " UNION ".join(f"SELECT _id, '{r}' AS attr FROM w WHERE {l} IN (SELECT {l} FROM w WHERE {l} IS NOT NULL AND {r} IS NOT NULL GROUP BY {l} HAVING count(DISTINCT {r}) > 1) AND {r} IS NOT NULL" for l, r in (("postcode", "locality"), ("locality", "country"), ("country", "country_code")))
query("detect_l1", f"{CELL}{_WIDE} SELECT _id, attr FROM cell WHERE nullif(trim(dirty), '') IS NULL UNION {_VIOLATING}")(lambda s, d: factor.detect(materialize(_dirty(s, d), "d"), RULES))
query("cooccurrence_counts", f"{CELL}, c AS (SELECT _id, attr, trim(dirty) AS v FROM cell WHERE nullif(trim(dirty), '') IS NOT NULL) SELECT x.attr AS b_attr, x.v AS b, y.attr, y.v, count(*) AS n FROM c x JOIN c y ON x._id = y._id AND x.attr <> y.attr GROUP BY ALL")(lambda s, d: factor.cooccurrence(_dirty(s, d)))
query("signature_bits")(lambda s, d: signature_detector.signatures(materialize(_dirty(s, d), "d"), RULES).groupBy("attr", "bits").agg(F.count("*").alias("n")))
_HEAD = record_prompt.head("correct").replace("'", "''")
_PROMPTS = f""", p AS (SELECT DISTINCT {', '.join(ATTRS)} FROM w), b AS (SELECT md5(concat_ws(chr(31), {', '.join(f"coalesce({a}, chr(0))" for a in ATTRS)})) AS key, '{_HEAD}' || CAST(to_json(struct_pack({', '.join(f'{a} := {a}' for a in ATTRS)})) AS VARCHAR) AS prompt FROM p)"""
query("prompt_build", f"{CELL}{_WIDE}{_PROMPTS} SELECT key, prompt FROM b")(lambda s, d: record_prompt.prompts(_dirty(s, d)))
query("prompt_cost", f"""{CELL}{_WIDE}{_PROMPTS} SELECT (SELECT count(*) FROM w) AS n_rows, count(*) AS calls, CAST(0 AS BIGINT) AS bad_json, CAST(ceil(sum(length(prompt)) / 4) AS BIGINT) AS tokens, round(count(*) * CAST(0.00015 AS DOUBLE), 6) AS dollars FROM b""")(lambda s, d: record_prompt.cost(_dirty(s, d)))
query("prompt_swap")(lambda s, d: record_prompt.detect(_dirty(s, d)).withColumn("profile", F.lit("plain")).union(record_prompt.detect(_dirty(s, d), record_prompt.RulebookCompleter("strict")).withColumn("profile", F.lit("strict"))).groupBy("profile").agg(F.count("*").alias("n_flags")))


def _sample(s: SparkSession, d: str, rows: int = effectiveness.SAMPLE, rate: float | None = 0.2) -> effectiveness.Sample:
    return effectiveness.make_sample(materialize(_classified(s, d), "c"), rows, rate, fds=RULES)


for _name, _key in (("detect_l2", "signature_detector"), ("detect_l4", "column_imputer"), ("detect_p1", "record_prompt")):
    query(_name)(lambda s, d, k=_key: effectiveness.DETECTORS[k](_sample(s, d)))
for _name, _key in (("repair_l1", "factor"), ("repair_l3", "corrector_ensemble"), ("repair_l4", "column_imputer"), ("repair_p1", "record_prompt")):
    query(_name)(lambda s, d, k=_key: effectiveness.CORRECTORS[k](_sample(s, d)).select("_id", "attr", "repair"))
query("yardsticks")(lambda s, d: effectiveness.scores(_sample(s, d), detectors=("flag_all", "flag_nothing", "flag_missing"), correctors=("column_mode",)))


@query("staged_share")
def _staged(s: SparkSession, d: str) -> DataFrame:
    sample = _sample(s, d)
    got = staged.correct(sample.dirty, sample.errors, sample.fds, sample.labels())
    both = got.join(sample.cells, ["_id", "attr"])
    return both.groupBy("stage").agg(F.count("*").alias("n"), F.count_if(F.col("repair") == F.col("clean")).alias("n_right"))


query("auto_slices")(lambda s, d: staged.auto_slices(materialize(_dirty(s, d), "d")))
query("augment_balance")(lambda s, d: fd_majority.correct(materialize(staged.augment(_dirty(s, d), addr_clean(s, d, "customer")), "d"), RULES).groupBy("attr").agg(F.count("*").alias("n")))


@query("advisor")
def _advisor(s: SparkSession, d: str) -> DataFrame:
    rate = profile.error_rate(_classified(s, d)).first()
    rows = _dirty(s, d)
    ratio = profile.distinct_records(rows).first()
    return s.createDataFrame(staged.advise(rows.count(), rate.error_rate, 3 / 8, ratio.n_records / ratio.n_rows), "rank int, system string, reason string")


# --- measures

_SCORES = "round(coalesce(tp / nullif(n_out, 0), 0), 6) AS precision, round(coalesce(tp / nullif(n_true, 0), 0), 6) AS recall, round(coalesce(2 * (tp / nullif(n_out, 0)) * (tp / nullif(n_true, 0)) / nullif(tp / nullif(n_out, 0) + tp / nullif(n_true, 0), 0), 0), 6) AS f1, n_out = 0 OR n_true = 0 AS undefined"
_FLAG = "nullif(trim(dirty), '') IS NULL"
query("score_detection", f"{FULL} SELECT *, {_SCORES} FROM (SELECT count(*) FILTER ({_FLAG}) AS n_out, count(*) FILTER (category <> 'clean') AS n_true, count(*) FILTER (category <> 'clean' AND {_FLAG}) AS tp FROM classified)")(lambda s, d: measure.detection(c := materialize(_classified(s, d), "c"), effectiveness.flag_missing(c)))
_MODE = ", m AS (SELECT attr, dirty AS repair FROM (SELECT attr, dirty, row_number() OVER (PARTITION BY attr ORDER BY count(*) DESC, dirty) AS p FROM classified WHERE nullif(trim(dirty), '') IS NOT NULL GROUP BY attr, dirty) WHERE p = 1)"
_PROPOSED = "repair IS DISTINCT FROM dirty"
query("score_correction", f"{FULL}{_MODE} SELECT *, {_SCORES} FROM (SELECT count(*) FILTER ({_PROPOSED}) AS n_out, count(*) AS n_true, count(*) FILTER ({_PROPOSED} AND repair = clean) AS tp FROM classified JOIN m USING (attr) WHERE category <> 'clean')")(lambda s, d: measure.correction(c := materialize(_classified(s, d), "c"), repair_by_mode(c)))
query("recall_by_category", f"{FULL} SELECT category, count(*) AS n_true, count(*) FILTER ({_FLAG}) AS tp, round(count(*) FILTER ({_FLAG}) / count(*), 6) AS recall FROM classified WHERE category <> 'clean' GROUP BY category")(lambda s, d: measure.recall_by_category(c := materialize(_classified(s, d), "c"), effectiveness.flag_missing(c)))
query("f1_by_category", f"{FULL}{_MODE} SELECT category, n_out, n_true, tp, f1 FROM (SELECT *, {_SCORES} FROM (SELECT category, count(*) FILTER ({_PROPOSED}) AS n_out, count(*) AS n_true, count(*) FILTER ({_PROPOSED} AND repair = clean) AS tp FROM classified JOIN m USING (attr) WHERE category <> 'clean' GROUP BY category))")(lambda s, d: measure.f1_by_category(c := materialize(_classified(s, d), "c"), repair_by_mode(c)))


@query("mean_of_runs")
def _means(s: SparkSession, d: str) -> DataFrame:
    cells = materialize(_classified(s, d), "c")
    parts = [measure.detection(c := sampling.restore(cells, 0.1, seed), effectiveness.flag_missing(c)).withColumn("system", F.lit("flag_missing")) for seed in (1, 2, 3)]
    return measure.mean_of_runs(parts[0].unionByName(parts[1]).unionByName(parts[2]), ("system",))


SYSTEMS = {"detect": ("signature_detector", "factor", "fd_majority", "rule_workflow", "column_imputer", "record_prompt"), "correct": ("corrector_ensemble", "factor", "fd_majority", "rule_workflow", "column_imputer", "record_prompt")}
RATES = (0.05, 0.1, 0.2, None)
SLICES = {"all": "named", "second_country": "second_country", "non_latin": "non_latin_country"}


def _curve(s: SparkSession, d: str, task: str, name: str, slice_: str = "all", rows: int = 1000, seeds: tuple[int, ...] = (1,)) -> DataFrame:
    """One system's scores at every error rate, on records drawn from a slice, with the dependencies mined on their clean
    side, and the mean over the rates. `rows` and `seeds` are the protocol's sample size and repetitions."""
    cells = materialize(effectiveness.classified_cells(s, d, profile=SLICES[slice_]).filter("nation = 'Nation 7'" if slice_ != "all" else "true"), "curve")
    return effectiveness.rate_curve(cells, RATES, rows, seeds, **{"detectors": (), "correctors": ()} | {f"{task}ors": (name,)}).withColumn("slice", F.lit(slice_))


for _task, _names in SYSTEMS.items():
    for _name in _names:
        query(f"rate_curve_{_task}_{_name}")(lambda s, d, t=_task, n=_name: _curve(s, d, t, n))
for _slice in ("second_country", "non_latin"):
    query(f"rate_curve_{_slice}_detect")(lambda s, d, v=_slice: _curve(s, d, "detect", "record_prompt", v).unionByName(_curve(s, d, "detect", "factor", v)))
    query(f"rate_curve_{_slice}_correct")(lambda s, d, v=_slice: _curve(s, d, "correct", "record_prompt", v))
query("end_to_end")(lambda s, d: effectiveness.end_to_end(_sample(s, d), "record_prompt", "record_prompt"))
for _task, _names in SYSTEMS.items():
    query(f"size_ladder_{_task}")(lambda s, d, t=_task, n=_names: scalability.size_ladder(s, d, fds=RULES, budget_s=120.0, **{"detectors": (), "correctors": ()} | {f"{t}ors": n}))


@query("sample_table")
def _samples(s: SparkSession, d: str) -> DataFrame:
    """The effectiveness samples: slice, aimed rate (0: as it is), rows, columns and the rate that came out."""
    out = None
    for name, kind in (SLICES | {"library": "library", "shopping_center": "shopping_center"}).items():
        where = {"all": "true", "library": "poi = 'Brand#1'", "shopping_center": "poi = 'Brand#2'"}.get(name, "nation = 'Nation 7'")
        cells = materialize(effectiveness.classified_cells(s, d, profile=kind).filter(where), "slice")
        ids = sampling.fixed(sampling.dedup_dirty(inject.wide(cells)), effectiveness.SAMPLE, 1).select("_id")
        chosen = materialize(cells.join(ids, "_id", "left_semi"), "sample")
        for rate in RATES if name in SLICES else (None,):
            got = profile.error_rate(chosen if rate is None else sampling.restore(chosen, rate, 1))
            row = got.select(F.lit(name).alias("slice"), F.lit(rate or 0.0).alias("aim"), (F.col("n_cells") / len(ATTRS)).cast("long").alias("n_rows"), F.lit(len(ATTRS)).alias("n_columns"), "error_rate")
            out = row if out is None else out.unionByName(row)
    return out


def _poi_sample(s: SparkSession, d: str, brand: str, kind: str) -> effectiveness.Sample:
    return effectiveness.Sample(materialize(effectiveness.classified_cells(s, d, profile=kind, where=F.col("poi") == brand), "poi"), max_lhs=1)


_POI = (("Brand#1", "library"), ("Brand#2", "shopping_center"))


@query("poi_overall")
def _poi(s: SparkSession, d: str) -> DataFrame:
    out = None
    for brand, kind in _POI:
        got = effectiveness.scores(_poi_sample(s, d, brand, kind), detectors=SYSTEMS["detect"], correctors=SYSTEMS["correct"]).withColumn("slice", F.lit(kind))
        out = got if out is None else out.unionByName(got)
    return out


@query("poi_by_category")
def _poi_categories(s: SparkSession, d: str) -> DataFrame:
    """Recall of every detector and F1 of every corrector by error category, on both slices. Systems that flag
    what they repair run once for both tasks. One runs after the other: each one under way costs the driver plans,
    broadcasts and threads, whatever the tables' size."""
    scored = {"detect": (measure.recall_by_category, "recall"), "correct": (measure.f1_by_category, "f1")}
    both = {"fd_majority": fd_majority, "rule_workflow": rule_workflow}

    def result(kind: str, sample: effectiveness.Sample, task: str, name: str, out: DataFrame) -> DataFrame:
        score, value = scored[task]
        got = score(sample.cells, out).select(F.lit(kind).alias("slice"), F.lit(task).alias("task"), F.lit(name).alias("system"), "category", "n_true", "tp", F.col(value).alias("score"))
        return materialize(got.coalesce(1), "poi-scores")  # one row a category

    def once(kind: str, sample: effectiveness.Sample, task: str, name: str) -> list[DataFrame]:
        table_ = effectiveness.DETECTORS if task == "detect" else effectiveness.CORRECTORS
        out = materialize(table_[name](sample), f"{task}-{name}")
        if name not in both:
            return [result(kind, sample, task, name, out)]
        return [result(kind, sample, "detect", name, both[name].flags(sample.dirty, out)), result(kind, sample, "correct", name, out)]

    samples = [(kind, _poi_sample(s, d, brand, kind)) for brand, kind in _POI]
    runs = [(t, n) for t in ("correct", "detect") for n in SYSTEMS[t] if t == "correct" or n not in both]
    return reduce(DataFrame.unionByName, [part for task, name in runs for kind, sample in samples for part in once(kind, sample, task, name)])


@query("label_learning")
def _label_learning(s: SparkSession, d: str) -> DataFrame:
    """Learned detection on real labels: documents' quality marks against numeric signs of their text, fitted on four
    fifths of the labelled rows (by hash) and scored on the rest."""
    from cellscrub.systems import label_model

    docs, labels = table(s, d, "documents"), table(s, d, "labels")
    return label_model.held_out_scores(docs, labels)


# --- noise that the tables hold themselves


@query("natural_noise_pages", "SELECT CASE WHEN t = c THEN 'clean' ELSE 'encoding' END AS category, count(*) AS n FROM (SELECT trim(regexp_replace(t, '\\s+', ' ', 'g')) AS t, trim(regexp_replace(replace(t, '&amp;', '&'), '\\s+', ' ', 'g')) AS c FROM (SELECT regexp_extract(html, '<title>([^<]*)</title>', 1) AS t FROM pages)) GROUP BY ALL")
def _page_noise(s: SparkSession, d: str) -> DataFrame:
    title = F.regexp_extract("html", "<title>([^<]*)</title>", 1)
    cells = table(s, d, "pages").select(title.alias("dirty"), F.replace(title, F.lit("&amp;"), F.lit("&")).alias("clean"))
    return taxonomy.classify(cells).groupBy("category").agg(F.count("*").alias("n"))


@query("natural_noise_docs", "SELECT CASE WHEN t = c THEN 'clean' ELSE 'punct' END AS category, count(*) AS n FROM (SELECT trim(regexp_replace(t, '\\s+', ' ', 'g')) AS t, trim(regexp_replace(regexp_replace(t, '[%*&$#]{3}', '', 'g'), '\\s+', ' ', 'g')) AS c FROM (SELECT unnest(string_split(text, chr(10))) AS t FROM documents)) GROUP BY ALL")
def _document_noise(s: SparkSession, d: str) -> DataFrame:
    """Every line of every text against itself without junk symbols."""
    lines = table(s, d, "documents").select(F.explode(F.split("text", "\n")).alias("dirty"))
    cells = lines.select("dirty", F.regexp_replace("dirty", "[%*&$#]{3}", "").alias("clean"))
    return taxonomy.classify_native(cells).groupBy("category").agg(F.count("*").alias("n"))


# --- surrounding operators

query("join_anti_unmatched", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT user_id FROM events)")(lambda s, d: table(s, d, "customer").join(table(s, d, "events"), F.col("c_custkey") == F.col("user_id"), "left_anti").select("c_custkey"))
query("join_semi_matched", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")(lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"))
query("join_full_repairs", f"{CELL}, x AS (SELECT _id, attr FROM cell WHERE dirty IS NULL), y AS (SELECT _id, attr FROM cell WHERE injected = 'missing') SELECT CASE WHEN x._id IS NULL THEN 'right' WHEN y._id IS NULL THEN 'left' ELSE 'both' END AS side, count(*) AS n FROM x FULL JOIN y ON x._id = y._id AND x.attr = y.attr GROUP BY ALL")(lambda s, d: (c := _cells(s, d)).filter("dirty IS NULL").select("_id", "attr", F.lit(1).alias("l")).join(c.filter("injected = 'missing'").select("_id", "attr", F.lit(1).alias("r")), ["_id", "attr"], "full").groupBy(F.when(F.col("l").isNull(), "right").when(F.col("r").isNull(), "left").otherwise("both").alias("side")).agg(F.count("*").alias("n")))
query("join_theta_edit", f"{ROWS}, v AS (SELECT DISTINCT country, road FROM addr) SELECT a.country, a.road AS road_a, b.road AS road_b FROM v a JOIN v b ON a.country = b.country AND a.road < b.road AND levenshtein(a.road, b.road) <= 2")(lambda s, d: (v := addr_clean(s, d).select("country", "road").distinct()).alias("a").join(v.alias("b"), (F.col("a.country") == F.col("b.country")) & (F.col("a.road") < F.col("b.road"))).filter(F.levenshtein("a.road", "b.road", 2) >= 0).select("a.country", F.col("a.road").alias("road_a"), F.col("b.road").alias("road_b")))
query("join_interval_ship", "SELECT o_orderpriority, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey AND l_shipdate BETWEEN o_orderdate AND o_orderdate + INTERVAL 30 DAYS GROUP BY o_orderpriority")(lambda s, d: table(s, d, "orders").join(table(s, d, "lineitem"), (F.col("l_orderkey") == F.col("o_orderkey")) & F.col("l_shipdate").between(F.col("o_orderdate"), F.col("o_orderdate") + F.expr("INTERVAL 30 DAYS"))).groupBy("o_orderpriority").agg(F.count("*").alias("n")))


@query("join_asof_events", "SELECT p.event_id, coalesce(max_by(e.event_id, (e.ts, e.event_id)), -1) AS last_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p LEFT JOIN (SELECT * FROM events WHERE event_type <> 'purchase') e ON e.user_id = p.user_id AND e.ts <= p.ts GROUP BY p.event_id")
def _asof(s: SparkSession, d: str) -> DataFrame:
    """The latest other event of the same user: one sort by user and time, no range join."""
    e = table(s, d, "events")
    other = F.when(F.col("event_type") != "purchase", F.col("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") == "purchase", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return e.withColumn("last_id", F.last(other, ignorenulls=True).over(w)).filter("event_type = 'purchase'").select("event_id", F.coalesce("last_id", F.lit(-1)).alias("last_id"))


query("rollup_region_country", f"{ROWS} SELECT coalesce(region, 'all') AS region, coalesce(country, 'all') AS country, count(*) AS n FROM addr GROUP BY ROLLUP (region, country)")(lambda s, d: addr_clean(s, d).rollup("region", "country").agg(F.count("*").alias("n")).select(F.coalesce("region", F.lit("all")).alias("region"), F.coalesce("country", F.lit("all")).alias("country"), "n"))
query("window_rank", f"{ROWS} SELECT country, n, rank() OVER (ORDER BY n DESC) AS r, dense_rank() OVER (ORDER BY n DESC) AS dr, CAST(ntile(4) OVER (ORDER BY n DESC, country) AS INTEGER) AS q FROM (SELECT country, count(*) AS n FROM addr GROUP BY country)")(lambda s, d: profile.distribution(addr_clean(s, d), "country").select("country", "n", F.rank().over(Window.orderBy(F.desc("n"))).cast("long").alias("r"), F.dense_rank().over(Window.orderBy(F.desc("n"))).cast("long").alias("dr"), F.ntile(4).over(Window.orderBy(F.desc("n"), "country")).alias("q")))
query("window_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_ms(ts) RANGE BETWEEN 3600000 PRECEDING AND CURRENT ROW) AS n FROM events")(lambda s, d: table(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_millis(F.col("ts").cast("timestamp"))).rangeBetween(-3600000, 0)).alias("n")))
query("topk_candidates", f"{ROWS} SELECT country, road, n FROM (SELECT country, road, n, row_number() OVER (PARTITION BY country ORDER BY n DESC, road) AS p FROM (SELECT country, road, count(*) AS n FROM addr GROUP BY ALL)) WHERE p <= 3")(lambda s, d: addr_clean(s, d).groupBy("country", "road").agg(F.count("*").alias("n")).withColumn("p", F.row_number().over(Window.partitionBy("country").orderBy(F.desc("n"), "road"))).filter("p <= 3").drop("p"))
query("setops_flags", f"{CELL}, x AS (SELECT _id, attr FROM cell WHERE dirty IS NULL OR dirty = ''), y AS (SELECT _id, attr FROM cell WHERE injected IN ('missing', 'case')) SELECT 'both' AS part, count(*) AS n FROM (SELECT * FROM x INTERSECT SELECT * FROM y) UNION ALL SELECT 'only', count(*) FROM (SELECT * FROM y EXCEPT SELECT * FROM x)")(lambda s, d: (x := (c := _cells(s, d)).filter("dirty IS NULL OR dirty = ''").select("_id", "attr")).intersect(y := c.filter("injected IN ('missing', 'case')").select("_id", "attr")).agg(F.lit("both").alias("part"), F.count("*").alias("n")).union(y.subtract(x).agg(F.lit("only"), F.count("*"))))
query("json_props", "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY event_type")(lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("total")))
query("variant_props", "SELECT event_type, max(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS top FROM events GROUP BY event_type")(lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.max(F.variant_get(F.parse_json("props"), "$.k", "long")).alias("top")))
query("array_ops", f"{ROWS} SELECT DISTINCT name, len(string_split(lower(name), ' ')) AS n_tokens, array_to_string(list_sort(string_split(lower(name), ' ')), ' ') AS sorted FROM addr")(lambda s, d: addr_clean(s, d).select("name").distinct().select("name", F.size(X.tokens(F.col("name"))).cast("long").alias("n_tokens"), F.array_join(F.array_sort(X.tokens(F.col("name"))), " ").alias("sorted")))
query("date_error_rate", f"{FULL} SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n_cells, count(*) FILTER (category <> 'clean') AS n_errors FROM classified JOIN (SELECT md5(CAST(o_orderkey AS VARCHAR)) AS _id, o_orderdate FROM orders) USING (_id) GROUP BY month")(lambda s, d: _classified(s, d).join(table(s, d, "orders").select(F.md5(F.col("o_orderkey").cast("string")).alias("_id"), F.date_format("o_orderdate", "yyyy-MM").alias("month")), "_id").groupBy("month").agg(F.count("*").alias("n_cells"), F.count_if(F.col("category") != "clean").alias("n_errors")))


@query("vector_nearest", "SELECT e.vec_id, arg_min(l.vec_id, (round(sqrt(list_sum(list_transform(list_zip(e.embedding, l.embedding), lambda p: (CAST(p[1] AS DOUBLE) - p[2]) * (CAST(p[1] AS DOUBLE) - p[2])))), 6), l.vec_id)) AS nearest FROM embeddings e, (SELECT * FROM embeddings WHERE vec_id < 20) l WHERE e.vec_id >= 20 GROUP BY e.vec_id")
def _nearest(s: SparkSession, d: str) -> DataFrame:
    """Every vector's nearest of the 20 labelled ones; those are a fixed number, so they are broadcast."""
    e = table(s, d, "embeddings")
    labelled = e.filter("vec_id < 20").select(F.col("vec_id").alias("lid"), F.col("embedding").alias("lv"))
    away = F.round(F.sqrt(F.aggregate(F.zip_with("embedding", "lv", lambda a, b: F.pow(a.cast("double") - b.cast("double"), F.lit(2.0))), F.lit(0.0), lambda a, x: a + x)), 6)
    pairs_ = e.filter("vec_id >= 20").crossJoin(F.broadcast(labelled)).select("vec_id", F.struct(away.alias("away"), "lid").alias("n"))
    return pairs_.groupBy("vec_id").agg(F.min("n").alias("n")).select("vec_id", F.col("n.lid").alias("nearest"))


query("conversation_prompts", "SELECT conv_id, count(*) AS n_turns, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id")(lambda s, d: table(s, d, "conversations").groupBy("conv_id").agg(F.count("*").alias("n_turns"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda t: t["role"]), ">").alias("roles")))

# --- streams (their batch form; tests/ compare it with the stream)

_EVENTS = "x AS (SELECT event_id, user_id, event_type, props, CAST('0x' || substr(md5('7|' || event_id || '|event'), 1, 8) AS BIGINT) % 1000000 % 1000 AS h, CASE WHEN event_id % 97 = 0 THEN ts - INTERVAL 3 HOURS ELSE ts END AS ts FROM events)"
query("stream_tumbling_batch", f"WITH {_EVENTS} SELECT time_bucket(INTERVAL 1 HOUR, ts) AS window_start, count(*) AS n, count(*) FILTER (h < 100) AS n_errors FROM x GROUP BY ALL")(lambda s, d: monitor.error_rate(monitor.dirtied(table(s, d, "events"))))
query("stream_sliding_batch", f"WITH {_EVENTS} SELECT time_bucket(INTERVAL 30 MINUTES, ts) - o * INTERVAL 30 MINUTES AS window_start, count(*) AS n, count(*) FILTER (h < 100) AS n_errors FROM x, (SELECT unnest([0, 1]) AS o) GROUP BY ALL")(lambda s, d: monitor.error_rate(monitor.dirtied(table(s, d, "events")), "1 hour", "30 minutes"))
query("stream_session_batch", f"WITH {_EVENTS}, g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 4 HOURS THEN 0 ELSE 1 END AS new FROM x WINDOW w AS (PARTITION BY user_id ORDER BY ts)), k AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS grp FROM g) SELECT user_id, min(ts) AS session_start, count(*) AS n FROM k GROUP BY user_id, grp")(lambda s, d: monitor.sessions(monitor.dirtied(table(s, d, "events"))))
query("stream_dedup", "SELECT event_id, event_type FROM events")(lambda s, d: monitor.deduplicated((e := table(s, d, "events")).union(e)).select("event_id", "event_type"))
query("stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment")(lambda s, d: monitor.enriched(table(s, d, "events"), table(s, d, "customer")).groupBy("c_mktsegment").agg(F.count("*").alias("n")))

# --- files and SQL surface

for _kind in ("json", "csv", "orc", "parquet"):
    query(f"source_{_kind}", f"{ROWS} SELECT * FROM addr")(lambda s, d, k=_kind: formats.round_trip(addr_clean(s, d), k))
query("sink_partitioned", f"{ROWS} SELECT _id, country FROM addr WHERE country_code = 'AD'")(lambda s, d: formats.write_partitioned(addr_clean(s, d).select("_id", "country", "country_code"), f"{scratch_dir(s)}/partitioned-{uuid.uuid4().hex}", "country_code").filter("country_code = 'AD'").select("_id", "country"))
query("sql_report", f"{FULL} SELECT attr, category, count(*) AS n FROM classified WHERE attr = 'road' GROUP BY ALL")(lambda s, d: formats.category_report(_classified(s, d), "road"))


@query("sql_decodings", f"{CELL} SELECT _id, clean AS decoded FROM cell WHERE injected = 'encoding' AND dirty <> clean")
def _decodings(s: SparkSession, d: str) -> DataFrame:
    formats.register(s, {"encoded_cells": _cells(s, d).filter("injected = 'encoding' AND dirty <> clean")})
    return s.sql("SELECT _id, decoded FROM encoded_cells, LATERAL decodings(dirty) WHERE decoded = clean")
