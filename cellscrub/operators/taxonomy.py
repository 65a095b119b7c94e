"""Twelve-way error classification of cells: the first rule that fires wins.

Values are judged as distinct (dirty, clean) texts where `by_pair` is set, which pays when values repeat. The rules with
built-in functions form one expression; only pairs that still need decoding or an exact edit distance after it (a small
residue by construction) are filtered out and sent through Arrow UDFs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cellscrub.functions import text as X
from cellscrub.functions.dicts import ABBREVIATIONS, ALIASES, accent_table
from cellscrub.schema import CATEGORIES

TYPO_EDITS = 2


def _prepared(cells: DataFrame) -> DataFrame:
    d, g = X.normalize(F.coalesce("dirty", F.lit(""))), X.normalize(F.coalesce("clean", F.lit("")))
    out = cells.withColumn("_d", d).withColumn("_g", g)
    out = out.withColumn("_dt", F.array_sort(X.tokens(F.col("_d")))).withColumn("_gt", F.array_sort(X.tokens(F.col("_g"))))
    return out.withColumn("_dm", X.multiset(F.col("_dt"))).withColumn("_gm", X.multiset(F.col("_gt")))


def rules(min_len: int = 0) -> dict[str, Column]:
    """Condition of every rule on prepared cells. encoding and typo are what built-in functions can tell."""
    d, g, dt, gt, dm, gm = (F.col(c) for c in ("_d", "_g", "_dt", "_gt", "_dm", "_gm"))
    some = (F.size(dt) > 0) & (F.size(gt) > 0)
    lost, added = F.size(F.array_except(gm, dm)), F.size(F.array_except(dm, gm))
    same_order = X.same_expanded(X.tokens(d), X.tokens(g))
    sure, _ = X.within(d, g, TYPO_EDITS)
    return {
        "clean": d == g,
        "missing": d == "",
        "encoding": X.entity_decoded(d) == g,
        "case": X.casefold(d) == X.casefold(g),
        "punct": X.squash(X.casefold(d)) == X.squash(X.casefold(g)),
        "reorder": some & (dt == gt),
        "language": some & (F.array_sort(X.concepts(dt)) == F.array_sort(X.concepts(gt))),
        "abbrev": some & same_order,
        "containment": some & (lost + added > 0) & ((lost == 0) | (added == 0)),
        "typo": sure & (F.greatest(F.length(d), F.length(g)) >= min_len),
        "one_word": some & (lost == 1) & (added == 1) & (F.size(F.array_intersect(dm, gm)) >= 1),
        "other": F.lit(True),
    }


def classify_native(cells: DataFrame, order: tuple[str, ...] = CATEGORIES, compare: str = "normalized", min_len: int = 0) -> DataFrame:
    """cells with category, built-in functions only: entities of one letter, plain edit distance.

    In the standard order the rules that need no tokens come first, and tokens are only made where none of them fires.
    """
    cond = rules(min_len)
    if compare == "exact":
        cond["clean"] = F.col("dirty").eqNullSafe(F.col("clean"))

    def chain(names, start=None):
        for c in names:
            start = F.when(cond[c], c) if start is None else start.when(cond[c], c)
        return start

    if tuple(order) != CATEGORIES:
        return _prepared(cells).withColumn("category", chain(order).otherwise("other")).drop("_d", "_g", "_dt", "_gt", "_dm", "_gm")
    d, g = X.normalize(F.coalesce("dirty", F.lit(""))), X.normalize(F.coalesce("clean", F.lit("")))
    open_ = F.col("_first").isNull()
    out = cells.withColumn("_d", d).withColumn("_g", g).withColumn("_first", chain(CATEGORIES[:5]))
    out = out.withColumn("_dt", F.when(open_, F.array_sort(X.tokens(F.col("_d"))))).withColumn("_gt", F.when(open_, F.array_sort(X.tokens(F.col("_g")))))
    out = out.withColumn("_dm", F.when(open_, X.multiset(F.col("_dt")))).withColumn("_gm", F.when(open_, X.multiset(F.col("_gt"))))
    late = chain(CATEGORIES[5:-1], F.when(~open_, F.col("_first"))).otherwise("other")
    return out.withColumn("category", late).drop("_d", "_g", "_first", "_dt", "_gt", "_dm", "_gm")


def _with_residue(pairs: DataFrame, **options) -> DataFrame:
    """Exact decoding, folding and edit distance where they could change the native category.

    All of it is one Arrow UDF over values that are null for every other row, so the rows need not be split and the
    native rules run once.
    """
    first = classify_native(pairs, **options)
    d, g = X.normalize(F.coalesce("dirty", F.lit(""))), X.normalize(F.coalesce("clean", F.lit("")))
    wide_chars = (F.octet_length(d) > F.char_length(d)) | (F.octet_length(g) > F.char_length(g))
    undecoded = F.col("category").isin(*CATEGORIES[3:]) & (X.maybe_encoded(d) | wide_chars)
    distant = F.col("category").isin("one_word", "other") & X.within(d, g, TYPO_EDITS)[1]
    asked = first.withColumn("_ask", undecoded | distant)
    seen = asked.withColumn("_seen", X.second_look(F.when(F.col("_ask"), d), F.when(F.col("_ask"), g)))
    has = lambda bit: F.col("_seen").bitwiseAND(bit) > 0
    after = lambda name: F.col("category").isin(*CATEGORIES[CATEGORIES.index(name) + 1 :])
    again = (
        F.when(has(X.SAME), "clean")
        .when(has(X.DECODES), "encoding")
        .when(has(X.FOLDS) & after("case"), "case")
        .when(has(X.ROMANIZES) & after("language"), "language")
        .when(has(X.NEAR) & F.col("category").isin("one_word", "other"), "typo")
    )
    return seen.withColumn("category", F.coalesce(again, "category")).drop("_ask", "_seen")


def classify(cells: DataFrame, by_pair: bool = False, **options) -> DataFrame:
    """cells with category; with by_pair each distinct (dirty, clean) is judged once and joined back."""
    if not by_pair:
        return _with_residue(cells, **options)
    pairs = _with_residue(cells.select("dirty", "clean").distinct(), **options)
    same = F.col("a.dirty").eqNullSafe(F.col("b.dirty")) & F.col("a.clean").eqNullSafe(F.col("b.clean"))
    return cells.alias("a").join(pairs.alias("b"), same).select("a.*", "b.category")


def classify_counted(cells: DataFrame, keys: tuple[str, ...], **options) -> DataFrame:
    """keys, category, n without joining back: equal cells are counted first, so only distinct ones are judged."""
    counted = cells.groupBy(*keys, "dirty", "clean").agg(F.count("*").alias("n"))
    return _with_residue(counted, **options).groupBy(*keys, "category").agg(F.sum("n").alias("n"))


def all_matches(cells: DataFrame) -> DataFrame:
    """cells with the array of all rules that fire, which the cascade hides."""
    cond = {k: v for k, v in rules().items() if k != "other"}
    fired = F.filter(F.array(*[F.when(c, k) for k, c in cond.items()]), lambda x: x.isNotNull())
    return _prepared(cells).withColumn("matches", fired).drop("_d", "_g", "_dt", "_gt", "_dm", "_gm")


def dictionary_coverage(cells: DataFrame) -> DataFrame:
    """attr, n_tokens, share of the dirty tokens that the alias and abbreviation tables know."""
    t = cells.select("attr", F.explode(X.tokens(F.coalesce("dirty", F.lit("")))).alias("t"))
    return t.groupBy("attr").agg(F.count("*").alias("n_tokens"), F.round(F.avg(F.col("t").isin(*ALIASES).cast("int")), 6).alias("alias_share"), F.round(F.avg(F.col("t").isin(*ABBREVIATIONS).cast("int")), 6).alias("abbrev_share"))


def tokens_sql(text: str) -> str:
    """The folded tokens of an SQL text expression."""
    a, b = accent_table()
    return f"list_filter(string_split(regexp_replace({_folded_sql(f'translate({text}, {chr(39)}{a}{chr(39)}, {chr(39)}{b}{chr(39)})')}, '[^\\p{{L}}\\p{{N}}]+', ' ', 'g'), ' '), lambda t: t <> '')"


def _folded_sql(text: str) -> str:
    return f"replace(replace(lower({text}), 'ß', 'ss'), 'ς', 'σ')"


def rules_sql(exact_typo: bool = False, compare: str = "normalized") -> dict[str, str]:
    """Condition of every rule over the columns that `category_sql` prepares."""
    alias = "CASE t " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in ALIASES.items()) + " ELSE t END"
    longer = "CASE {0} " + " ".join(f"WHEN '{k}' THEN [{', '.join(repr(y) for y in v)}]" for k, v in ABBREVIATIONS.items()) + " ELSE [] END"
    exp = lambda x: f"list_concat(list_concat([{x}], {longer.format(x)}), CASE WHEN regexp_matches({x}, '.str$') THEN [{x} || 'asse'] ELSE [] END)"
    squash = lambda x: f"regexp_replace({x}, '[\\p{{P}}\\p{{S}}\\p{{Z}}\\s]', '', 'g')"
    # DuckDB counts edits of bytes; the letters that the tables' translations use become one byte each
    marked = "áéíóúüñÁÉÍÓÚÜÑ"
    one_byte = lambda x: f"translate({x}, '{marked}', {' || '.join(f'chr({i + 1})' for i in range(len(marked)))})"
    fold = _folded_sql
    decoded = "CASE WHEN regexp_matches(d, '&#[0-9]{1,4};') THEN split_part(d, '&#', 1) || chr(CAST(regexp_extract(d, '&#([0-9]{1,4});', 1) AS INTEGER)) || regexp_replace(d, '^.*?&#[0-9]{1,4};', '') ELSE d END"
    return {
        "clean": "d = g" if compare == "normalized" else "dirty IS NOT DISTINCT FROM clean",
        "missing": "d = ''",
        "encoding": f"{decoded} = g",
        "case": f"{fold('d')} = {fold('g')}",
        "punct": f"{squash(fold('d'))} = {squash(fold('g'))}",
        "reorder": "som AND dt = gt",
        "language": f"som AND list_sort(list_transform(dt, lambda t: {alias})) = list_sort(list_transform(gt, lambda t: {alias}))",
        "abbrev": f"som AND len(ds) = len(gs) AND len(list_filter(range(1, len(ds) + 1), lambda i: list_has_any({exp('ds[i]')}, {exp('gs[i]')}))) = len(ds)",
        "containment": "som AND lost + added > 0 AND (lost = 0 OR added = 0)",
        "typo": f"{'damerau_levenshtein' if exact_typo else 'levenshtein'}({one_byte('d')}, {one_byte('g')}) <= 2",
        "one_word": "som AND lost = 1 AND added = 1 AND len(list_filter(dm, lambda t: list_contains(gm, t))) >= 1",
    }


def category_sql(exact_typo: bool = False, order: tuple[str, ...] = CATEGORIES, compare: str = "normalized") -> str:
    """`classified`: `cell` with category and `matches` (all rules that fire), as a CTE; exact_typo counts transpositions
    as one edit."""
    tag = lambda x: f"list_transform({x}, lambda t, i: t || '#' || (i - list_position({x}, t) + 1))"
    minus = lambda p, q: f"len(list_filter({p}, lambda t: NOT list_contains({q}, t)))"
    rules = rules_sql(exact_typo, compare)
    cases = " ".join(f"WHEN {rules[c]} THEN '{c}'" for c in order if c in rules)
    matches = ", ".join(f"CASE WHEN {rule} THEN '{c}' END" for c, rule in rules.items())
    return f"""
prepared AS (
  SELECT *, list_sort(ds) AS dt, list_sort(gs) AS gt FROM (
    SELECT *, {tokens_sql("d")} AS ds, {tokens_sql("g")} AS gs FROM (
      SELECT *, trim(regexp_replace(coalesce(dirty, ''), '\\s+', ' ', 'g')) AS d, trim(regexp_replace(coalesce(clean, ''), '\\s+', ' ', 'g')) AS g FROM cell))
), tagged AS (
  SELECT *, {tag("dt")} AS dm, {tag("gt")} AS gm FROM prepared
), measured AS (
  SELECT *, {minus("gm", "dm")} AS lost, {minus("dm", "gm")} AS added, len(dt) > 0 AND len(gt) > 0 AS som FROM tagged
), classified AS (
  SELECT *, CASE {cases} ELSE 'other' END AS category, concat_ws(',', {matches}) AS matches
  FROM measured
)"""
