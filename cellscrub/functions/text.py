"""String primitives as column expressions; Arrow UDFs only where Spark has no function, behind a filter."""

from __future__ import annotations

import html
import re
import unicodedata
from urllib.parse import unquote

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cellscrub.functions.dicts import ABBREVIATIONS, ALIASES, accent_table, romanization_table

ZERO_WIDTH = r"[\u200B-\u200D\u2060\uFEFF]"
_ACCENTED, _PLAIN = accent_table()


def normalize(c: Column) -> Column:
    """Without zero-width characters, blanks collapsed, trimmed; case and punctuation stay. NFC: see `compose`."""
    c = F.regexp_replace(c, ZERO_WIDTH, "")
    return F.trim(F.regexp_replace(F.translate(c, "\u00a0", " "), r"\s+", " "))


@F.pandas_udf(T.StringType())
def compose(s: pd.Series) -> pd.Series:
    """Canonical composition (NFC)."""
    return s.map(lambda v: None if v is None else unicodedata.normalize("NFC", v))


@F.pandas_udf(T.StringType())
def casefold_any(s: pd.Series) -> pd.Series:
    """Full Unicode case folding."""
    return s.map(lambda v: None if v is None else v.casefold())


def casefold(c: Column) -> Column:
    """Case folding with built-in functions: lower case, sharp s as ss, one sigma."""
    return F.replace(F.replace(F.lower(c), F.lit("ß"), F.lit("ss")), F.lit("ς"), F.lit("σ"))


def squash(c: Column) -> Column:
    return F.regexp_replace(c, r"[\p{P}\p{S}\p{Z}\s]", "")


def unaccent(c: Column) -> Column:
    return F.translate(c, _ACCENTED, _PLAIN)


def romanize(c: Column) -> Column:
    """Greek and Cyrillic to Latin: single letters in one pass, those of several letters before."""
    table = romanization_table()
    c = unaccent(F.translate(F.lower(c), "άέήίόύώϊϋ", "αεηιουωιυ"))
    for letter, sound in table.items():
        if len(sound) > 1:
            c = F.replace(c, F.lit(letter), F.lit(sound))
    ones = {k: v for k, v in table.items() if len(v) == 1}
    none = [k for k, v in table.items() if not v]
    return F.translate(c, "".join(ones) + "".join(none), "".join(ones.values()))


def tokens(c: Column) -> Column:
    """Folded words: runs of letters and digits."""
    return F.filter(F.split(F.regexp_replace(casefold(unaccent(c)), r"[^\p{L}\p{N}]+", " "), " "), lambda t: t != "")


def multiset(sorted_tokens: Column) -> Column:
    """Sorted tokens with their ordinal, so that set functions act on multisets."""
    return F.transform(sorted_tokens, lambda t, i: F.concat(t, F.lit("#"), (i - F.array_position(sorted_tokens, t) + 2).cast("string")))


def _literal_map(table: dict[str, str]) -> Column:
    return F.create_map(*[F.lit(x) for pair in table.items() for x in pair])


def concepts(tokens_: Column) -> Column:
    """Tokens with translations and exonyms replaced by what they name."""
    table = _literal_map(ALIASES)
    return F.transform(tokens_, lambda t: F.coalesce(F.element_at(table, t), t))


def expansions(token: Column) -> Column:
    """A token with the long forms it may stand for; German street suffixes too."""
    table = F.create_map(*[x for k, v in ABBREVIATIONS.items() for x in (F.lit(k), F.array(*[F.lit(y) for y in v]))])
    own = F.coalesce(F.element_at(table, token), F.array().cast("array<string>"))
    suffix = F.when(token.rlike(".str$"), F.array(F.concat(token, F.lit("asse")))).otherwise(F.array().cast("array<string>"))
    return F.concat(F.array(token), own, suffix)


def same_expanded(a: Column, b: Column) -> Column:
    """Equal numbers of tokens that pairwise share a form."""
    pairs = F.zip_with(a, b, lambda x, y: F.coalesce(F.arrays_overlap(expansions(x), expansions(y)), F.lit(False)))
    return (F.size(a) == F.size(b)) & F.forall(pairs, lambda p: p)


@F.pandas_udf(T.IntegerType())
def damerau(a: pd.Series, b: pd.Series) -> pd.Series:
    """Unrestricted Damerau-Levenshtein distance."""
    return pd.Series([None if x is None or y is None else distance(x, y) for x, y in zip(a, b)], dtype="Int32")


def distance(a: str, b: str) -> int:
    big = len(a) + len(b)
    last: dict[str, int] = {}
    rows = [[big] * (len(b) + 2), [big, *range(len(b) + 1)]]
    for i, x in enumerate(a, 1):
        row, match = [big, i], 0
        for j, y in enumerate(b, 1):
            k, m = last.get(y, 0), match
            if x == y:
                match = j
            row.append(min(rows[i][j] + (x != y), row[j] + 1, rows[i][j + 1] + 1, rows[k][m] + (i - k - 1) + 1 + (j - m - 1)))
        rows.append(row)
        last[x] = i
    return rows[-1][-1]


def within(a: Column, b: Column, most: int) -> tuple[Column, Column]:
    """(surely within, perhaps within) `most` Damerau-Levenshtein edits, as DL <= Lev <= 2 DL."""
    lev = F.levenshtein(a, b, 2 * most)
    return (lev >= 0) & (lev <= most), lev > most


_ENTITY = re.compile(r"&(?:#[0-9]+|#[xX][0-9A-Fa-f]+|[A-Za-z][A-Za-z0-9]*);")


def decodings_of(value: str, depth: int = 2) -> list[str]:
    """What a value may have been before it was wrongly encoded, up to `depth` steps.

    Entities are decoded as browsers do, which also take some without a semicolon (`&amp`), and only where it is there.
    """

    def steps(v: str) -> set[str]:
        out = {html.unescape(v), _ENTITY.sub(lambda m: html.unescape(m[0]), v)}
        try:
            out.add(unquote(v, errors="strict"))
        except UnicodeDecodeError:
            pass
        for codec in ("latin-1", "cp1252"):
            try:
                out.add(v.encode(codec).decode("utf-8"))
            except UnicodeError:
                pass
        if "\\u" in v:
            try:
                out.add(v.encode("latin-1", "backslashreplace").decode("unicode_escape"))
            except UnicodeError:
                pass
        return {o for o in out if o != v}

    found, level = set(), {value}
    for _ in range(depth):
        level = {o for v in level for o in steps(v)} - found
        found |= level
    return sorted(unicodedata.normalize("NFC", f) for f in found)


def decodes_one_kind(value: str, clean: str) -> bool:
    """Whether one kind of entity, decoded wherever it stands while all others stay, turns a value into another."""
    return any(unicodedata.normalize("NFC", value.replace(e, html.unescape(e))) == clean for e in set(_ENTITY.findall(value)) if html.unescape(e) != e)


SAME, DECODES, FOLDS, ROMANIZES, NEAR = 1, 2, 4, 8, 16


def _latin_concepts(value: str) -> list[str]:
    marks = str.maketrans(romanization_table())
    plain = "".join(c for c in unicodedata.normalize("NFD", value.casefold()) if not unicodedata.combining(c))
    words = "".join(c if c.isalnum() else " " for c in plain.translate(marks)).split()
    return sorted(ALIASES.get(w, w) for w in words)


def relation(dirty: str, clean: str) -> int:
    """The bits of all that holds between two values; edits count up to two."""
    d, c = unicodedata.normalize("NFC", dirty), unicodedata.normalize("NFC", clean)
    if d == c:
        return SAME
    words = _latin_concepts(c) if not (d.isascii() and c.isascii()) else []
    return (
        DECODES * (c in decodings_of(d) or decodes_one_kind(d, c))
        | FOLDS * (d.casefold() == c.casefold())
        | ROMANIZES * bool(words and words == _latin_concepts(d))
        | NEAR * (abs(len(d) - len(c)) <= 2 and distance(d, c) <= 2)
    )


@F.pandas_udf(T.IntegerType())
def second_look(dirty: pd.Series, clean: pd.Series) -> pd.Series:
    """`relation` for the rows that are not null, each distinct pair once a batch."""
    known: dict[tuple[str, str], int] = {}
    out = []
    for pair in zip(dirty, clean):
        if pair[0] is None:
            out.append(0)
        else:
            if pair not in known:
                known[pair] = relation(*pair)
            out.append(known[pair])
    return pd.Series(out, dtype="int32")


def maybe_encoded(c: Column) -> Column:
    """Cheap marker test before any decoding is tried."""
    return c.rlike(r"%[0-9A-Fa-f]{2}|&#?[A-Za-z0-9]+;|[ÃÂâ]|\\u[0-9a-fA-F]{4}")


def entity_decoded(c: Column) -> Column:
    """Decimal entities of one letter decoded with built-in functions."""
    return F.when(c.rlike("&#[0-9]{1,4};"), F.concat(F.substring_index(c, "&#", 1), F.char(F.regexp_extract(c, "&#([0-9]{1,4});", 1).cast("int")), F.regexp_replace(c, "^.*?&#[0-9]{1,4};", ""))).otherwise(c)


def token_set_ratio(a: Column, b: Column) -> Column:
    """0..100: the best indel ratio among the shared tokens and either whole token set."""
    x, y = F.array_distinct(F.array_sort(tokens(a))), F.array_distinct(F.array_sort(tokens(b)))
    both = F.array_join(F.array_sort(F.array_intersect(x, y)), " ")
    left = F.trim(F.concat_ws(" ", both, F.array_join(F.array_except(x, y), " ")))
    right = F.trim(F.concat_ws(" ", both, F.array_join(F.array_except(y, x), " ")))
    ratio = lambda p, q: F.when(F.length(p) + F.length(q) == 0, 0).otherwise(100 * (1 - F.levenshtein(p, q) / F.greatest(F.length(p), F.length(q))))
    whole = F.when((both != "") & ((both == left) | (both == right)), F.lit(100.0))
    return F.coalesce(whole, F.greatest(F.when(both != "", ratio(both, left)).otherwise(0), F.when(both != "", ratio(both, right)).otherwise(0), ratio(left, right)))


def ratio(a: Column, b: Column) -> Column:
    """1 - levenshtein / longer length; 1 for two empty values."""
    longest = F.greatest(F.length(a), F.length(b))
    return F.when(longest == 0, 1.0).otherwise(1 - F.levenshtein(a, b) / longest)


def ngrams(c: Column, n: int) -> Column:
    return F.when(F.length(c) >= n, F.transform(F.sequence(F.lit(1), F.length(c) - n + 1), lambda i: F.substring(c, i, F.lit(n)))).otherwise(F.array().cast("array<string>"))


def jaccard(a: Column, b: Column) -> Column:
    return F.coalesce(F.try_divide(F.size(F.array_intersect(a, b)), F.size(F.array_union(a, b))), F.lit(0.0))
