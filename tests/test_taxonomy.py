import itertools

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from cellscrub.functions import text as X
from cellscrub.operators import taxonomy
from cellscrub.schema import CATEGORIES

PAIRS = [
    ("Atlanta", "Atlanta", "clean"), ("New  York ", "New York", "clean"), ("München", "München", "clean"), (None, "x", "missing"), ("", "x", "missing"), ("   ", "x", "missing"),
    ("M%C3%BCnchen", "München", "encoding"), ("Caf&#233;", "Café", "encoding"), ("MÃ¼nchen", "München", "encoding"),
    ("ATLANTA", "Atlanta", "case"), ("10a", "10A", "case"), ("STRASSE", "straße", "case"),
    ("Notre-Dame Street", "Notre Dame Street", "punct"), ("U.S.A.", "USA", "punct"),
    ("Howson Branch, Austin Public Library", "Austin Public Library -- Howson Branch", "reorder"), ("South 37th Avenue", "37th Avenue South", "reorder"),
    ("Austria", "Österreich", "language"), ("Athens", "Αθήνα", "language"), ("Ave", "Avenue", "abbrev"), ("Bachmannstr.", "Bachmannstraße", "abbrev"),
    ("New York", "New York City", "containment"), ("Finavia", "Finavia Oyj", "containment"), ("a a b", "a b", "containment"), ("Theater", "Theatre", "typo"), ("Marriott", "Mariot", "typo"), ("7", "12", "typo"), ("CA", "ABC", "typo"),
    ("VA Clinic", "Outpatient Clinic", "one_word"), ("California", "Highway 76", "other"), ("Strathroy", "Adelaide Metcalfe", "other"), ("100%", "a+b zz q", "other"),
]


def test_worked_examples(spark):
    df = spark.createDataFrame([(d, c, w) for d, c, w in PAIRS], "dirty string, clean string, want string")
    assert [(r.dirty, r.clean, r.category) for r in taxonomy.classify(df).collect() if r.category != r.want] == []
    by_pair = taxonomy.classify(df, by_pair=True)
    assert by_pair.filter("category <> want").count() == 0


def test_every_cell_has_one_category_and_reversal_is_symmetric(spark):
    values = ["Main Street", "Main St.", "main street", "Street Main", "Main-Street", "Calle Main", "Mian Street", "Main Street 5", "Old Road", "Other Street"]
    df = spark.createDataFrame([(a, b) for a, b in itertools.product(values, values)], "dirty string, clean string")
    got = {(r.dirty, r.clean): r.category for r in taxonomy.classify(df).collect()}
    assert len(got) == len(values) ** 2 and set(got.values()) <= set(CATEGORIES)
    assert all(got[a, b] == got[b, a] for a, b in got)


def textbook(a, b):
    """Unrestricted distance as a shortest path over all edits of short strings."""
    seen, level, steps = {a}, {a}, 0
    letters = sorted(set(a + b))
    while b not in level:
        steps += 1
        new = set()
        for s in level:
            new |= {s[:i] + s[i + 1 :] for i in range(len(s))} | {s[:i] + c + s[i:] for i in range(len(s) + 1) for c in letters} | {s[:i] + c + s[i + 1 :] for i in range(len(s)) for c in letters} | {s[:i] + s[i + 1] + s[i] + s[i + 2 :] for i in range(len(s) - 1)}
        level = new - seen
        seen |= new
    return steps


@settings(max_examples=40, deadline=None)
@given(st.text("ab", max_size=3), st.text("abc", max_size=3))
def test_edit_distance(a, b):
    assert X.distance(a, b) == textbook(a, b)


@pytest.mark.parametrize("value,want", [("100%", []), ("a+b", []), ("&amp;", ["&"])])
def test_decodings(value, want):
    assert X.decodings_of(value) == want


def test_entities_left_over_stay_encoding(spark):
    """A title cut off within an entity, and one that holds several kinds, of which one is decoded."""
    rows = [("Onesnd&amp;&amp; and&amp", "Onesnd&& and&amp"), ("a &amp; b &lt; c", "a & b &lt; c"), ("x&quot;y&amp;z &gt; &amp", 'x"y&amp;z &gt; &amp'), ("a&amp;b&amp", "a&b")]
    got = taxonomy.classify(spark.createDataFrame(rows, "dirty string, clean string")).collect()
    assert [r.category for r in got] == ["encoding", "encoding", "encoding", "containment"]
    assert X.decodings_of("a&amp;b&amp") == ["a&b&", "a&b&amp"]
