"""Names shared by all modules: the eight cleaned attributes, categories and fixed shares."""

from __future__ import annotations

ATTRS = ("name", "house_number", "road", "postcode", "locality", "region", "country", "country_code")
CORE_ATTRS = ATTRS[1:]

CATEGORIES = ("clean", "missing", "encoding", "case", "punct", "reorder", "language", "abbrev", "containment", "typo", "one_word", "other")
ERRORS = CATEGORIES[1:]

# Published shares of each category in percent of cells, in the order of ERRORS.
PROFILES = {
    "named": (23.7, 0.025, 2.1, 0.8, 0.6, 6.9, 9.3, 2.6, 1.2, 0.2, 1.5),
    "plain": (28.6, 0.001, 1.7, 0.8, 0.3, 6.4, 9.5, 1.8, 1.3, 0.4, 1.9),
    "major_country": (20.1, 0.038, 1.0, 0.5, 0.1, 7.0, 14.9, 2.2, 0.7, 0.0, 0.5),
    "second_country": (30.0, 0.003, 1.9, 1.2, 0.3, 5.3, 1.2, 2.7, 0.3, 0.0, 3.6),
    "non_latin_country": (29.6, 0.0, 7.8, 0.3, 0.1, 2.2, 0.4, 0.7, 6.4, 0.2, 0.3),
    "library": (27.3, 0.023, 2.8, 0.4, 0.6, 2.0, 5.8, 1.6, 1.1, 0.0, 6.6),
    "shopping_center": (22.4, 0.047, 3.1, 0.2, 7.3, 4.2, 7.1, 2.5, 6.5, 0.2, 0.6),
}
