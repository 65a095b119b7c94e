"""Deterministic errors over clean records: for every cell a hash draw picks the category, and a rule makes the value."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellscrub.schema import ATTRS, ERRORS, PROFILES

DRAWS = 1_000_000

# What the injector writes for a word. No cleaning system may see these tables.
#: English word -> the form that injected translations use
TRANSLATIONS = {"Street": "Calle", "Avenue": "Avenida", "Boulevard": "Bulevar", "Road": "Camino", "North": "Norte", "South": "Sur", "East": "Este", "West": "Oeste", "Port": "Puerto", "Nation": "Nación", "Inner": "Interior", "Outer": "Exterior", "Building": "Edificio", "Furniture": "Muebles", "Household": "Hogar", "Machinery": "Maquinaria", "Automobile": "Automóvil"}
#: long form -> the short form that injected abbreviations use
SHORT_FORMS = {"Street": "St.", "Avenue": "Ave", "Boulevard": "Blvd.", "Road": "Rd.", "North": "N", "South": "S", "East": "E", "West": "W", "Port": "Pt.", "Nation": "Nat.", "Inner": "Inn.", "Outer": "Out.", "Building": "Bldg.", "Furniture": "Furn.", "Household": "Hh.", "Machinery": "Mach.", "Automobile": "Auto."}


def draw(seed: int, attr: str, ident: Column) -> Column:
    """0..999999 from seed, id and attribute."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), ident, F.lit(f"|{attr}"))), 1, 8), 16, 10).cast("long") % DRAWS


def _words(c: Column) -> Column:
    return F.split(c, " ")


def _swap_words(c: Column, table: dict[str, str]) -> Column:
    pairs = F.create_map(*[F.lit(x) for pair in table.items() for x in pair])
    return F.array_join(F.transform(_words(c), lambda w: F.coalesce(F.element_at(pairs, w), w)), " ")


def _several(c: Column) -> Column:
    return F.size(_words(c)) > 1


def _without_last(c: Column) -> Column:
    return F.array_join(F.slice(_words(c), 1, F.size(_words(c)) - 1), " ")


CORRUPTORS: dict[str, Callable[[Column, Column], Column]] = {
    "missing": lambda c, d: F.when(d % 2 == 0, F.lit("")),
    "encoding": lambda c, d: F.concat(F.lit("&#"), F.ascii(c).cast("string"), F.lit(";"), F.substring(c, 2, 1000)),
    "case": lambda c, d: F.when(c == F.upper(c), F.lower(c)).otherwise(F.upper(c)),
    "punct": lambda c, d: F.when(_several(c), F.replace(c, F.lit(" "), F.lit("-"))).otherwise(F.concat(c, F.lit("."))),
    "reorder": lambda c, d: F.when(_several(c), F.concat(F.element_at(_words(c), -1), F.lit(" "), _without_last(c))).otherwise(c),
    "language": lambda c, d: _swap_words(c, TRANSLATIONS),
    "abbrev": lambda c, d: _swap_words(c, SHORT_FORMS),
    "containment": lambda c, d: F.when(_several(c) & (d % 2 == 0), _without_last(c)).otherwise(F.concat(c, F.lit(" Annex"))),
    "typo": lambda c, d: F.when(F.length(c) > 3, F.concat(F.substring(c, 1, 1), F.substring(c, 3, 1), F.substring(c, 2, 1), F.substring(c, 4, 1000))).otherwise(F.concat(c, F.lit("x"))),
    "one_word": lambda c, d: F.when(_several(c), F.concat(_without_last(c), F.lit(" Zanzibar"))).otherwise(c),
    "other": lambda c, d: F.concat(F.lit("misplaced entry no "), (d % 97).cast("string")),
}


def thresholds(profile: str | tuple[float, ...], scale: float = 1.0) -> list[tuple[str, int]]:
    """Category and upper end of its draws."""
    shares = PROFILES[profile] if isinstance(profile, str) else profile
    out, at = [], 0.0
    for category, share in zip(ERRORS, shares):
        at += share / 100 * scale
        out.append((category, round(at * DRAWS)))
    return out


def corrupted(c: Column, d: Column, profile: str | tuple[float, ...], scale: float = 1.0) -> tuple[Column, Column]:
    """(value, injected category) of one cell."""
    value, label, low = None, None, 0
    for category, high in thresholds(profile, scale):
        if high > low:
            here = (d >= low) & (d < high)
            bad = CORRUPTORS[category](c, d)
            value = F.when(here, bad) if value is None else value.when(here, bad)
            label = F.when(here, category) if label is None else label.when(here, category)
        low = high
    return (c, F.lit("clean")) if value is None else (value.otherwise(c), label.otherwise("clean"))


def corrupt(clean: DataFrame, profile: str | tuple[float, ...] = "named", seed: int = 7, scale: float = 1.0, attrs: tuple[str, ...] = ATTRS, bias: dict[str, dict[str, float]] | None = None) -> DataFrame:
    """Pairs: d_<attr>, c_<attr> and i_<attr> (injected category) beside the other columns; one projection.

    bias multiplies a category's share for an attribute, as {attr: {category: factor}}.
    """
    cols = []
    for a in attrs:
        shares = PROFILES[profile] if isinstance(profile, str) else profile
        if bias and a in bias:
            shares = tuple(s * bias[a].get(c, 1.0) for c, s in zip(ERRORS, shares))
        value, label = corrupted(F.col(a), draw(seed, a, F.col("_id")), shares, scale)
        cols += [value.alias(f"d_{a}"), F.col(a).alias(f"c_{a}"), label.alias(f"i_{a}")]
    return clean.select(*[c for c in clean.columns if c not in attrs], *cols)


def cells(pairs: DataFrame, attrs: tuple[str, ...] = ATTRS, keep: tuple[str, ...] = ("_id",)) -> DataFrame:
    """Long form: keep columns, attr, dirty, clean, and injected where the pairs have it."""
    labelled = f"i_{attrs[0]}" in pairs.columns
    rows = F.array(*[F.struct(F.lit(a).alias("attr"), F.col(f"d_{a}").alias("dirty"), F.col(f"c_{a}").alias("clean"), *([F.col(f"i_{a}").alias("injected")] if labelled else [])) for a in attrs])
    return pairs.select(*keep, F.inline(rows))


def wide(long: DataFrame, attrs: tuple[str, ...] = ATTRS, keys: tuple[str, ...] = ("_id",)) -> DataFrame:
    """Pairs from cells."""
    one = lambda a, c: F.max(F.when(F.col("attr") == a, F.col(c))).alias(f"{c[0]}_{a}")
    return long.groupBy(*keys).agg(*[one(a, c) for a in attrs for c in ("dirty", "clean")])


def confusion(classified: DataFrame) -> DataFrame:
    """injected, category, n: what the cascade makes of each injected category."""
    return classified.groupBy("injected", "category").agg(F.count("*").alias("n"))


def _case_words(c: str, table: dict[str, str]) -> str:
    whens = " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in table.items())
    return f"array_to_string(list_transform(string_split({c}, ' '), lambda w: CASE w {whens} ELSE w END), ' ')"


def cells_sql(profile: str = "named", seed: int = 7, scale: float = 1.0, source: str = "addr", extra: str = "") -> str:
    """`cell`: the long form of the injected pairs, as a CTE after ADDR_SQL."""
    several, short = "len(string_split(c, ' ')) > 1", "array_to_string(string_split(c, ' ')[1:len(string_split(c, ' ')) - 1], ' ')"
    rules = {
        "missing": "CASE WHEN d % 2 = 0 THEN '' END",
        "encoding": "'&#' || ascii(c) || ';' || substr(c, 2)",
        "case": "CASE WHEN c = upper(c) THEN lower(c) ELSE upper(c) END",
        "punct": f"CASE WHEN {several} THEN replace(c, ' ', '-') ELSE c || '.' END",
        "reorder": f"CASE WHEN {several} THEN string_split(c, ' ')[-1] || ' ' || {short} ELSE c END",
        "language": _case_words("c", TRANSLATIONS),
        "abbrev": _case_words("c", SHORT_FORMS),
        "containment": f"CASE WHEN {several} AND d % 2 = 0 THEN {short} ELSE c || ' Annex' END",
        "typo": "CASE WHEN length(c) > 3 THEN substr(c, 1, 1) || substr(c, 3, 1) || substr(c, 2, 1) || substr(c, 4) ELSE c || 'x' END",
        "one_word": f"CASE WHEN {several} THEN {short} || ' Zanzibar' ELSE c END",
        "other": "'misplaced entry no ' || d % 97",
    }
    value, label, low = "", "", 0
    for category, high in thresholds(profile, scale):
        if high > low:
            value += f" WHEN d >= {low} AND d < {high} THEN {rules[category]}"
            label += f" WHEN d >= {low} AND d < {high} THEN '{category}'"
        low = high
    union = " UNION ALL ".join(f"SELECT _id, graph_iri, poi, country AS nation, '{a}' AS attr, {a} AS c FROM {source}" for a in ATTRS)
    return f"""
cell AS MATERIALIZED (
  SELECT _id, graph_iri, poi, nation, attr, CASE{value} ELSE c END AS dirty, c AS clean, CASE{label} ELSE 'clean' END AS injected
  FROM (SELECT *, CAST('0x' || substr(md5('{seed}|' || _id || '|' || attr), 1, 8) AS BIGINT) % {DRAWS} AS d FROM ({union})) {extra}
)"""
